"""Language-model scores by context-tree weighting.

The model is a tree of contexts of 0 to DEPTH bytes; in each, the eight binary decisions of the next byte are counted,
estimated by Krichevsky and Trofimov's rule, and the estimates of all depths are mixed with the weights that the
training text gives them (a node's own estimate against the product of its children's, each with half the prior). The
trained tree is then held fixed: a text's score is the sum of the logarithms of its bytes' mixed probabilities.

All counts are over the whole training part. Documents are dealt to chunks by a hash; a chunk gathers its different
words and its different strings of DEPTH + 1 bytes, with training counts, and sends them to buckets: words by hash,
strings by their two bytes next to the last. A bucket sums the words and answers each chunk with the counts that it
asked for; of its strings it builds the subtrees, which no other bucket shares. Only the upper two levels (at most 256
nodes of 255 decisions) come to the driver and are broadcast. With them each bucket answers every chunk with the
probabilities of the strings that the chunk has, and a chunk's documents are scored where its answers are; so no task
holds more of the model than its own strings. Words are told by 62-bit hashes, strings are whole.

Base score: add-one unigram probabilities of words and end.

Defined cases: a null text is empty (one token, the end); without training text all counts are 0; a null id is neither
trained on nor held out; repeated rows are counted and scored each; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from minlabel.llm import text_arrays as ta
from minlabel.llm.shared import Shared
from minlabel.session import stored

DEPTH, FOLDS, HELD_OUT = 5, 7, 2
TOP = 2  # depth at which the subtrees of the buckets begin
WORDS, GRAMS, ASKED, NODES, TOTALS = range(5)
_HALF = np.log(0.5)


def log_gamma(x: np.ndarray) -> np.ndarray:
    """For x > 0, by Stirling's series after a shift."""
    x = np.asarray(x, np.float64)
    shift = np.zeros_like(x)
    for k in range(8):
        shift += np.log(x + k)
    y = x + 8
    r = 1 / (y * y)
    return (y - 0.5) * np.log(y) - y + 0.9189385332046727 + (1 / 12 - r * (1 / 360 - r * (1 / 1260 - r / 1680))) / y - shift


def log_estimate(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Logarithm of the Krichevsky-Trofimov probability of any sequence of a zeros and b ones."""
    return log_gamma(a + 0.5) + log_gamma(b + 0.5) - log_gamma(a + b + 1.0) - np.log(np.pi)


def _sealed(x: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(x).tobytes())


def _opened(b: bytes, kind) -> np.ndarray:
    return np.frombuffer(zstandard.ZstdDecompressor().decompress(b), kind)


def _steps(sorted_: np.ndarray) -> np.ndarray:
    """Differences of sorted numbers, which pack better."""
    return np.diff(sorted_, prepend=sorted_.dtype.type(0))


def _counted(values: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different values and the sums of their counts."""
    if not len(values):
        return values, counts
    order = np.argsort(values, kind="stable")
    v, c = values[order], counts[order]
    first = np.flatnonzero(np.concatenate(([True], v[1:] != v[:-1])))
    return v[first], np.add.reduceat(c, first)


def byte_strings(low: np.ndarray, offsets: np.ndarray, depth: int = DEPTH) -> np.ndarray:
    """For each byte the number of it with the depth bytes before it in its text; zeros before the text."""
    size = np.diff(offsets)
    place = np.arange(len(low)) - np.repeat(offsets[:-1], size)
    out = low.astype(np.uint64)
    for k in range(1, depth + 1):
        before = np.zeros(len(low), np.uint64)
        before[k:] = low[: len(low) - k]
        before[place < k] = 0
        out |= before << np.uint64(8 * k)
    return out


class Gathered:
    """Different values with counts, gathered part by part."""

    def __init__(self, limit: int = 3_000_000):
        self.parts, self.size, self.limit = [], 0, limit

    def add(self, values: np.ndarray, trained: np.ndarray | bool) -> None:
        v = np.sort(values << np.uint64(1) | trained) if values.dtype == np.uint64 and values.size and int(values.max()) < 1 << 62 else None
        if v is not None:
            first = np.flatnonzero(np.concatenate(([True], v[1:] != v[:-1])))
            self.parts.append((v[first] >> np.uint64(1), np.diff(np.append(first, len(v))) * (v[first] & np.uint64(1)).astype(np.int64)))
        else:
            self.parts.append(_counted(values, np.broadcast_to(np.asarray(trained, np.int64), values.shape)))
        self.size += len(self.parts[-1][0])
        if self.size > self.limit:
            self.all()

    def all(self) -> tuple[np.ndarray, np.ndarray]:
        if not self.parts:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        both = _counted(np.concatenate([p[0] for p in self.parts]), np.concatenate([p[1] for p in self.parts]))
        self.parts, self.size = [both], 0
        self.limit = max(self.limit, 2 * len(both[0]))
        return both


def _words_and_strings(data: np.ndarray, offsets: np.ndarray, hasher: ta.Hasher, tables, depth: int):
    low = tables[1][data]
    s, e, at = ta.words(tables[0][data], offsets)
    return hasher.words(low, s, e) >> np.uint64(2), at, byte_strings(low, offsets, depth)


def _tables():
    lower = np.arange(256, dtype=np.uint8)
    lower[65:91] += 32
    return ta.class_table("visible"), lower


def _gather(buckets: int, depth: int):
    """Documents of whole chunks -> what each chunk sends to each bucket."""

    def run(batches):
        hasher, tables = ta.Hasher(), _tables()
        chunk = None
        for batch in batches:
            numbers = batch.column("chunk").to_numpy()
            cut = [0, *(np.flatnonzero(numbers[1:] != numbers[:-1]) + 1).tolist(), len(numbers)] if len(numbers) else [0]
            for lo, hi in zip(cut, cut[1:]):
                if numbers[lo] != chunk:
                    if chunk is not None:
                        yield from send(chunk, words, strings, tokens, ends)
                    chunk, words, strings, tokens, ends = numbers[lo], Gathered(), Gathered(), 0, 0
                part = batch.slice(lo, hi - lo)
                data, offsets = ta.byte_arrays(part.column("text"))
                trained = part.column("trained").to_numpy(zero_copy_only=False)
                for i, j in ta.slices(offsets):
                    own = offsets[i : j + 1] - offsets[i]
                    w, at, g = _words_and_strings(data[offsets[i] : offsets[j]], own, hasher, tables, depth)
                    t = trained[i:j]
                    words.add(w, np.repeat(t, np.diff(at)).astype(np.uint64))
                    strings.add(g, np.repeat(t, np.diff(own)).astype(np.uint64))
                    tokens += int(np.diff(at)[t].sum())
                    ends += int(t.sum())
        if chunk is not None:
            yield from send(chunk, words, strings, tokens, ends)

    def send(chunk, words, strings, tokens, ends):
        rows = [(0, TOTALS, np.array([tokens, ends]).tobytes(), b"")]
        w, c = words.all()
        edge = np.searchsorted(w, (np.arange(buckets + 1, dtype=np.float64) / buckets * 2.0**62).astype(np.uint64))
        edge[-1] = len(w)
        rows += [(b, WORDS, _sealed(_steps(w[x:y])), _sealed(c[x:y])) for b, (x, y) in enumerate(zip(edge.tolist(), edge[1:].tolist())) if x < y]
        g, c = strings.all()
        where = (ta.mixed((g >> np.uint64(8)) & np.uint64(0xFFFF)) % np.uint64(buckets)).astype(np.int64)
        order = np.argsort(where, kind="stable")
        g, c, where = g[order], c[order], where[order]
        edge = np.searchsorted(where, np.arange(buckets + 1)).tolist()
        rows += [(b, GRAMS, _sealed(_steps(g[x:y])), _sealed(c[x:y])) for b, (x, y) in enumerate(zip(edge, edge[1:])) if x < y]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int32()), pa.array([int(chunk)] * len(rows), pa.int32()), pa.array([r[2] for r in rows], pa.binary()), pa.array([r[3] for r in rows], pa.binary())], names=["bucket", "kind", "chunk", "a", "b"])

    return run


def subtrees(keys: np.ndarray, counts: np.ndarray, depth: int = DEPTH):
    """Sorted strings with counts -> mixed probabilities of their last byte's eight decisions at depth TOP, and the nodes there: for each decision ids (two bytes and the bits before), zeros, ones, and logarithms of the weighted probability."""
    levels = {depth: (keys, counts)}
    for d in range(depth - 1, TOP - 1, -1):
        levels[d] = _counted(levels[d + 1][0] & np.uint64((1 << 8 * (d + 1)) - 1), levels[d + 1][1])
    mixed, nodes = np.zeros((len(keys), 8)), []
    for j in range(8):
        one = (keys >> np.uint64(7 - j)) & np.uint64(1) == 1
        p = weights = ids = None
        for d in range(depth, TOP - 1, -1):
            g, n = levels[d]
            at = g >> np.uint64(8 - j)
            first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
            bit = ((g >> np.uint64(7 - j)) & np.uint64(1)).astype(np.int64)
            all_, ones = np.add.reduceat(n, first), np.add.reduceat(n * bit, first)
            zeros, here = all_ - ones, at[first]
            own = log_estimate(zeros, ones)
            place = np.searchsorted(here, (keys >> np.uint64(8 - j)) & np.uint64((1 << (8 * d + j)) - 1))
            kt = (np.where(one, ones[place], zeros[place]) + 0.5) / (all_[place] + 1.0)
            if d == depth:
                p, total = kt, own
            else:
                children = np.bincount(np.searchsorted(here, ids & np.uint64((1 << (8 * d + j)) - 1)), weights, len(here))
                total = np.logaddexp(_HALF + own, _HALF + children)
                share = np.exp(_HALF + own - total)[place]
                p = share * kt + (1 - share) * p
            ids, weights = here, total
        mixed[:, j] = p
        nodes.append((ids, zeros, ones, weights))
    return mixed, nodes


def _build(depth: int):
    """Rows of a bucket (in the order of kinds) -> answers to the chunks, its strings with probabilities and which of them each chunk has, its nodes at depth TOP, totals."""

    def row(kind, bucket, chunk, a, b=b""):
        return pa.RecordBatch.from_arrays([*(pa.array([x], pa.int32()) for x in (kind, bucket, chunk)), *(pa.array([x], pa.binary()) for x in (a, b))], names=["kind", "bucket", "chunk", "a", "b"])

    def answers(bucket, rows):
        asked = [(chunk, np.cumsum(_opened(a, np.uint64)), _opened(b, np.int64)) for chunk, a, b in rows]
        known, n = _counted(np.concatenate([x[1] for x in asked]), np.concatenate([x[2] for x in asked]))
        yield row(TOTALS, bucket, -1, np.array([0, 0, int((n > 0).sum())]).tobytes())
        for chunk, w, _ in asked:
            yield row(WORDS, bucket, chunk, _sealed(_steps(w)), _sealed(n[np.searchsorted(known, w)]))

    def trees(bucket, rows):
        asked = [(chunk, np.cumsum(_opened(a, np.uint64))) for chunk, a, _ in rows]
        keys, n = _counted(np.concatenate([w for _, w in asked]), np.concatenate([_opened(b, np.int64) for _, _, b in rows]))
        mixed, nodes = subtrees(keys, n, depth)
        yield row(GRAMS, bucket, -1, _sealed(_steps(keys)), _sealed(mixed.astype(np.float32)))
        for chunk, w in asked:
            yield row(ASKED, bucket, chunk, _sealed(_steps(np.searchsorted(keys, w).astype(np.int32))))
        for last in np.unique((keys >> np.uint64(8)) & np.uint64(0xFF)).tolist():
            own = [(x[0][pick], x[1][pick], x[2][pick], x[3][pick]) for j, x in enumerate(nodes) for pick in [((x[0] >> np.uint64(j)) & np.uint64(0xFF)) == last]]
            table = np.concatenate([np.stack((np.full(len(x[0]), j), (x[0] & np.uint64((1 << j) - 1)).astype(np.int64), x[1], x[2])) for j, x in enumerate(own)], axis=1)
            yield row(NODES, bucket, last, _sealed(table), _sealed(np.concatenate([x[3] for x in own])))

    def run(batches):
        bucket = kind = None
        rows: list = []

        def done():
            if kind == TOTALS:
                for _, a, _ in rows:
                    yield row(TOTALS, bucket, -1, np.append(np.frombuffer(a, np.int64), 0).tobytes())
            elif rows:
                yield from (answers if kind == WORDS else trees)(bucket, rows)

        for batch in batches:
            for b, k, chunk, x, y in zip(*(batch.column(c).to_pylist() for c in ("bucket", "kind", "chunk", "a", "b"))):
                if (b, k) != (bucket, kind):
                    yield from done()
                    bucket, kind, rows = b, k, []
                rows.append((chunk, x, y))
        yield from done()

    return run


def _told(top: Shared):
    """A bucket's strings, then what each chunk has of them -> the chunk's strings and the logarithms of their probabilities."""

    def run(batches):
        keys = values = None
        for batch in batches:
            for kind, chunk, a, b in zip(*(batch.column(c).to_pylist() for c in ("kind", "chunk", "a", "b"))):
                if kind == GRAMS:
                    keys = np.cumsum(_opened(a, np.uint64))
                    values = top.value.logarithms(keys, _opened(b, np.float32).reshape(-1, 8)).astype(np.float32)
                    continue
                own = np.cumsum(_opened(a, np.int32))
                yield pa.RecordBatch.from_arrays([pa.array([GRAMS], pa.int32()), pa.array([chunk], pa.int32()), pa.array([_sealed(_steps(keys[own]))], pa.binary()), pa.array([_sealed(values[own])], pa.binary())], names=["kind", "chunk", "a", "b"])

    return run


class Top:
    """The tree's upper two levels."""

    def __init__(self, rows: list[tuple[int, bytes]]):
        """rows: last byte, and its nodes summed: decision, bits before, zeros, ones, children's weights."""
        self.one, zero = [], []
        parts = [(last, np.frombuffer(b, np.float64).reshape(5, -1)) for last, b in sorted(rows)]
        for j in range(8):
            ids, zeros, ones, below = [], [], [], []
            for last, t in parts:
                own = t[:, t[0] == j]
                ids.append((last << j) + own[1].astype(np.int64))
                zeros.append(own[2])
                ones.append(own[3])
                below.append(own[4])
            ids, zeros, ones, below = (np.concatenate(x) if x else np.zeros(0) for x in (ids, zeros, ones, below))
            own = log_estimate(zeros, ones)
            total = np.logaddexp(_HALF + own, _HALF + below)
            self.one.append((ids.astype(np.int64), zeros, ones, np.exp(_HALF + own - total)))
            bits, place = np.unique(ids.astype(np.int64) & ((1 << j) - 1), return_inverse=True)
            zeros, ones, below = (np.bincount(place, x, len(bits)) for x in (zeros, ones, total))
            own = log_estimate(zeros, ones)
            zero.append((bits, zeros, ones, np.exp(_HALF + own - np.logaddexp(_HALF + own, _HALF + below))))
        self.zero = zero

    def logarithms(self, keys: np.ndarray, mixed: np.ndarray) -> np.ndarray:
        """log10 of the last byte's probability of each string, from its decisions' probabilities at depth TOP."""
        out = np.zeros(len(keys))
        byte, last = (keys & np.uint64(0xFF)).astype(np.int64), ((keys >> np.uint64(8)) & np.uint64(0xFF)).astype(np.int64)
        for j in range(8):
            before, one = byte >> (8 - j), (byte >> (7 - j)) & 1 == 1
            p = mixed[:, j].astype(np.float64)
            for (ids, zeros, ones, share), at in ((self.one[j], (last << j) | before), (self.zero[j], before)):
                k = np.searchsorted(ids, at)
                p = share[k] * (np.where(one, ones[k], zeros[k]) + 0.5) / (zeros[k] + ones[k] + 1) + (1 - share[k]) * p
            out += np.log10(p)
        return out


class Lookup:
    """Hash table from strings to numbers."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.bits = max(8, int(2 * len(keys) - 1).bit_length())
        size = 1 << self.bits
        self.keys, self.values, self.probes = np.full(size, np.uint64(_NONE)), np.zeros(size, np.float32), 1
        at, left = self._at(keys), np.arange(len(keys))
        while len(left):
            free = self.keys[at[left]] == np.uint64(_NONE)
            self.keys[at[left[free]]] = keys[left[free]]  # of several, the last stays
            placed = self.keys[at[left]] == keys[left]
            self.values[at[left[placed]]] = values[left[placed]]
            left = left[~placed]
            at[left] = (at[left] + 1) & (size - 1)
            self.probes += 1

    def _at(self, keys):
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def add(self, keys: np.ndarray, out: np.ndarray) -> None:
        """Add the values of keys that are here to out."""
        at = self._at(keys)
        same = self.keys[at] == keys
        hit = np.flatnonzero(same)
        out[hit] += self.values[at[hit]]
        left = np.flatnonzero(~same)
        for _ in range(self.probes):
            if not len(left):
                return
            at[left] = (at[left] + 1) & (len(self.keys) - 1)
            same = self.keys[at[left]] == keys[left]
            out[left[same]] += self.values[at[left[same]]]
            left = left[~same & (self.keys[at[left]] != np.uint64(_NONE))]


_NONE = (1 << 64) - 1


def _nodes_of_last(key, group):
    """Nodes below one last byte, from all buckets, summed over the byte before it."""
    tables = [_opened(a, np.int64).reshape(4, -1) for a in group.column("a").to_pylist()]
    below = np.concatenate([_opened(b, np.float64) for b in group.column("b").to_pylist()])
    t = np.concatenate(tables, axis=1)
    ids, place = np.unique(t[0] << 8 | t[1], return_inverse=True)
    sums = [np.bincount(place, x, len(ids)) for x in (t[2], t[3], below)]
    return pa.table({"last": pa.array([key[0].as_py()], pa.int32()), "nodes": pa.array([np.stack((ids >> 8, ids & 0xFF, *sums)).astype(np.float64).tobytes()], pa.binary())})


def _scored(tokens: int, distinct: int, ends: int, depth: int):
    """Rows of a chunk, answers first -> scores."""
    names = ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score", "bits_per_byte"]
    whole = np.log10(tokens + distinct + 1.0)

    def gathered(rows, kind):
        return _counted(np.concatenate([x for x, _ in rows]), np.concatenate([x for _, x in rows])) if rows else (np.zeros(0, np.uint64), np.zeros(0, kind))

    def run(batches):
        hasher, tables = ta.Hasher(), _tables()
        chunk, known, asked = None, None, {}
        for batch in batches:
            numbers, answer = batch.column("chunk").to_numpy(), batch.column("a").is_valid().to_numpy(zero_copy_only=False)
            cut = np.flatnonzero(np.concatenate(([True], (numbers[1:] != numbers[:-1]) | (answer[1:] != answer[:-1])))).tolist() if len(numbers) else []
            for lo, hi in zip(cut, [*cut[1:], len(numbers)]):
                part = batch.slice(lo, hi - lo)
                if numbers[lo] != chunk:
                    chunk, known, strings, asked = numbers[lo], None, None, {WORDS: [], GRAMS: []}
                if answer[lo]:
                    for kind, a, b in zip(*(part.column(c).to_pylist() for c in ("kind", "a", "b"))):
                        asked[kind].append((np.cumsum(_opened(a, np.uint64)), _opened(b, np.int64 if kind == WORDS else np.float32)))
                    continue
                if known is None:
                    known = gathered(asked[WORDS], np.int64)
                    cost = np.log10(known[1] + 1.0)
                    strings = Lookup(*(np.concatenate(x) for x in zip(*asked[GRAMS]))) if asked[GRAMS] else Lookup(np.zeros(0, np.uint64), np.zeros(0, np.float32))
                    asked = {}
                data, offsets = ta.byte_arrays(part.column("text"))
                n = len(offsets) - 1
                n_words, n_known, base, score = (np.zeros(n, t) for t in (np.int64, np.int64, np.float64, np.float64))
                for i, j in ta.slices(offsets):
                    own = offsets[i : j + 1] - offsets[i]
                    w, at, g = _words_and_strings(data[offsets[i] : offsets[j]], own, hasher, tables, depth)
                    n_words[i:j] = np.diff(at)
                    if len(w):
                        k = np.searchsorted(known[0], w)
                        for target, x in ((n_known, known[1][k] > 0), (base, cost[k])):
                            sums = np.concatenate((np.zeros(1, target.dtype), np.cumsum(x, dtype=target.dtype)))
                            target[i:j] = sums[at[1:]] - sums[at[:-1]]
                    out = np.zeros(len(g), np.float32)
                    strings.add(g, out)
                    score[i:j] = _sums(out, own)
                base += np.log10(ends + 1.0) - (n_words + 1) * whole
                size = np.maximum(np.diff(offsets), 1)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(n_words + 1), pa.array(n_known + (ends > 0)), pa.array(np.full(n, tokens)), pa.array(base), pa.array(score), pa.array(-score * np.log2(10) / size)], names=names)

    return run


def _sums(x: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    total = np.concatenate(([0.0], np.cumsum(x, dtype=np.float64)))
    return total[offsets[1:]] - total[offsets[:-1]]


def scores(docs: DataFrame, depth: int = DEPTH) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte of each row."""
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rest = F.crc32(F.col("doc_id").cast("string")) % FOLDS
    given = docs.select("doc_id", docs["text"].cast("string").alias("text")).select(
        "doc_id", F.coalesce(rest != HELD_OUT, F.lit(False)).alias("trained"), F.coalesce(rest == HELD_OUT, F.lit(False)).alias("held_out"), "text",
        F.pmod(F.xxhash64("doc_id", "text"), F.lit(parts)).cast("int").alias("chunk"),
    )
    sent = given.select("chunk", "trained", "text").repartitionById(parts, F.col("chunk")).mapInArrow(_gather(parts, depth), "bucket int, kind int, chunk int, a binary, b binary")
    built = stored(sent.repartitionById(parts, F.col("bucket")).sortWithinPartitions("bucket", "kind").mapInArrow(_build(depth), "kind int, bucket int, chunk int, a binary, b binary"), "context-trees")

    totals = [np.frombuffer(r.a, np.int64) for r in built.where(F.col("kind") == TOTALS).select("a").toLocalIterator()]  # one for each chunk and bucket
    words, ends, distinct = np.sum(totals, axis=0).tolist() if totals else (0, 0, 0)
    tokens, distinct = words + ends, distinct + (ends > 0)
    # at most 256 rows of at most 255 nodes
    top = Shared(spark.sparkContext, Top([(r.last, r.nodes) for r in built.where(F.col("kind") == NODES).select("chunk", "a", "b").groupBy("chunk").applyInArrow(_nodes_of_last, "last int, nodes binary").collect()]))

    trees = built.where(F.col("kind").isin(GRAMS, ASKED)).repartitionById(parts, F.col("bucket")).sortWithinPartitions("bucket", "kind")
    answers = built.where(F.col("kind") == WORDS).select("kind", "chunk", "a", "b").unionByName(trees.mapInArrow(_told(top), "kind int, chunk int, a binary, b binary"))
    none = lambda kind, name: F.lit(None).cast(kind).alias(name)
    kind = given.schema["doc_id"].dataType.simpleString()
    rows = answers.select("kind", "chunk", "a", "b", none(kind, "doc_id"), none("boolean", "held_out"), none("string", "text")).unionByName(given.select(none("int", "kind"), "chunk", none("binary", "a"), none("binary", "b"), "doc_id", "held_out", "text"))
    dealt = rows.repartitionById(parts, F.col("chunk")).sortWithinPartitions("chunk", F.col("a").isNull())
    return dealt.mapInArrow(_scored(int(tokens), int(distinct), int(ends), depth), f"doc_id {kind}, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double, bits_per_byte double")
