"""Near-duplicate documents by ProbMinHash of weighted word shingles, banding and verification.

A document is the weighted set of its shingles of WORDS words (a weight is 1 and the logarithm of how often a shingle
occurs; a text of fewer words is one shingle). Each shingle sends a Poisson process of arrivals, at a rate equal to its
weight, to the REGISTERS registers; a register keeps the shingle of its first arrival. Two documents agree in a register
with the probability Jaccard of their weighted sets, which is the Jaccard index where all weights are equal. Arrivals are
made up to the time by which all registers are likely to be filled (early termination); documents with an empty register
go on, so the signatures are those of the endless processes.

The probability Jaccard can lie far below the Jaccard index where one text repeats a passage. So each document has the
same sketch at unit weights too. A document without repeated shingles has one sketch for both. A pair is linked if either
index, computed from the two sets with the weights that the sketches had, is at least THRESHOLD.

Documents with equal weighted shingle sets (told by a 128-bit digest of all shingles and counts) are collapsed first, to
the smallest id. Both signatures of these representatives are cut into bands; those that share a band are a bucket, and
each pair within a bucket is a candidate. Buckets of the same documents are one. Shingles are made anew for documents in
buckets only.

A bucket of up to CELL documents is verified in one place. A larger one is first parted by an exact filter: in one order
of all shingles (rarest first, by a table of counts of fixed size), two linked documents share one of their first
shingles, as many as the threshold lets differ and one more; so the documents with a common first shingle are its parts,
and a passage that many documents have in common brings them together only where it is most of them. A document is left
out of a part if too few of its shingles follow there to reach the threshold with any of the others. In parts that are
still larger than CELL, rounds merge components: a part's leader is of its largest component, each document outside is
compared with one leader, and components that are linked join, the smaller one under the larger; so a part of g copies of
one text costs about g comparisons for each round. What is then not one component is dealt to cells, each of two blocks
of the part, and a cell verifies its pairs across components. No link between candidates is lost: pairs that are not
compared lie in one component, or cannot reach the threshold. Only banding can lose a link: a pair of Jaccard index j
shares no band of the unit sketch with probability (1 - j ** ROWS) ** BANDS, 7e-5 at 0.8. A cell hands on a forest of its
links; connected components of all links are the classes.

Ids of documents in buckets are broadcast to the scan that makes their shingles up to FEW_IDS (8 MB) of them, and joined
by a shuffle beyond that.

Defined cases: null and empty texts have no shingles and are linked to nothing; a null id is left out of the result;
rows with one id and different texts share bands, are compared by one of the texts, and get the smallest class; ids may
be of any type that has an order; other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from minlabel.graph import Graph
from minlabel.ids import dense_ids
from minlabel.llm import text_arrays as ta
from minlabel.llm.shared import Shared
from minlabel.plans.engine import connected_components
from minlabel.schemas import INTEGERS
from minlabel.session import Scratch, stored

WORDS, THRESHOLD = 5, 0.8
BANDS, ROWS = 24, 5
REGISTERS = BANDS * ROWS
#: Documents of a bucket that are verified in one place, and rounds of leaders at most in larger ones.
CELL, STARS = 64, 8
#: Counters of the table that orders shingles, and ids that are broadcast at most.
SLOTS, FEW_IDS = 1 << 16, 1_000_000


def _uniform(h: np.ndarray) -> np.ndarray:
    """In (0, 1]."""
    return ((h >> np.uint64(11)).astype(np.float64) + 1) * 2.0**-53


def shingles(data: np.ndarray, offsets: np.ndarray, hasher: ta.Hasher, table: np.ndarray, size: int = WORDS):
    """Different shingles of the texts: document, hash and weight, ordered by both."""
    low = table[data]
    s, e, at = ta.words(low, offsets)
    h = hasher.words(low, s, e)
    n = np.diff(at)
    if not len(h):
        z = np.zeros(0, np.int64)
        return z, z.astype(np.uint64), z
    grams = np.zeros(len(h), np.uint64)
    place = np.arange(len(h)) - np.repeat(at[:-1], n)
    left = np.repeat(n, n) - place
    for j in range(size):
        ahead = np.minimum(np.arange(len(h)) + j, len(h) - 1)
        grams = np.where(j < left, grams * np.uint64(0x9E3779B97F4A7C15) + h[ahead], grams)
    keep = (left >= size) | (place == 0)  # a short text is one shingle
    doc, grams = np.repeat(np.arange(len(n)), n)[keep], ta.mixed(grams[keep])
    # one sort of whole numbers by document and hash
    order = np.lexsort((grams, doc)) if len(n) > 1 else np.argsort(grams, kind="stable")
    doc, grams = doc[order], grams[order]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (grams[1:] != grams[:-1])
    first = np.flatnonzero(new)
    return doc[first], grams[first], np.diff(np.append(first, len(doc)))


def signatures(doc: np.ndarray, grams: np.ndarray, weight: np.ndarray, n: int, m: int = REGISTERS) -> np.ndarray:
    """(n, m) array of the shingles that came first to each register; 0 where a document has none."""
    total = np.bincount(doc, weight, n)
    best, kept = np.full(n * m, np.inf), np.zeros(n * m, np.uint64)
    at, step = np.zeros(len(doc)), 0
    with np.errstate(divide="ignore"):
        horizon = np.where(total > 0, m * (np.log(m) + 2) / np.maximum(total, 1e-300), 0.0)
    live = np.arange(len(doc))
    while len(live):
        step += 1
        h = ta.mixed(grams[live] + np.uint64(step * 0xD1B54A32D192ED03 & 0xFFFFFFFFFFFFFFFF))
        at[live] += -np.log(_uniform(h)) / weight[live]
        inside = at[live] <= horizon[doc[live]]
        go = live[inside]
        cell = doc[go] * m + (ta.mixed(h[inside] ^ np.uint64(0xA0761D6478BD642F)) % np.uint64(m)).astype(np.int64)
        np.minimum.at(best, cell, at[go])
        won = best[cell] == at[go]
        kept[cell[won]] = grams[go[won]]
        live = go
        if not len(live):
            empty = np.isinf(best.reshape(n, m)).any(1) & (total > 0)
            if empty.any():  # start these anew with a later end
                horizon[empty] *= 2
                live = np.flatnonzero(empty[doc])
                best.reshape(n, m)[empty] = np.inf
                at[live], step = 0.0, 0
    return kept.reshape(n, m)


def band_codes(rows: np.ndarray) -> np.ndarray:
    """(n, BANDS) codes of signatures: documents that agree in all registers of a band have one code there."""
    rows = rows.reshape(-1, BANDS, ROWS)
    codes = np.zeros(rows.shape[:2], np.uint64)
    for r in range(ROWS):
        codes = ta.mixed(codes * np.uint64(0x9E3779B97F4A7C15) + rows[:, :, r])
    return ta.mixed(codes + np.arange(BANDS, dtype=np.uint64)).view(np.int64)


def sketches(docs: DataFrame, key: str = "doc_id", text: str = "text", packed: bool = False) -> DataFrame:
    """key, content (digest of the weighted shingle set; null without words), and bands of its two signatures, each once, or if packed instead sh (its shingles in order) and times (how often each occurs; empty if once each)."""
    columns = ["sh", "times"] if packed else ["bands"]

    def run(batches):
        hasher, table = ta.Hasher(), ta.class_table("visible")
        for batch in batches:
            data, offsets = ta.byte_arrays(batch.column("text"))
            content, out, times = [], [], []
            for i, j in ta.slices(offsets, 1 << 20):
                n = j - i
                doc, grams, weight = shingles(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], hasher, table)
                cut = np.searchsorted(doc, np.arange(n + 1))
                own = list(zip(cut[:-1].tolist(), cut[1:].tolist()))
                counts = weight.astype(np.uint32)
                repeated = np.bincount(doc, weight > 1, n) > 0
                for (x, y), more in zip(own, repeated.tolist()):
                    content.append(hashlib.blake2b(grams[x:y].tobytes() + (counts[x:y].tobytes() if more else b""), digest_size=16).digest() if x < y else None)
                if packed:
                    out += [grams[x:y].tobytes() for x, y in own]
                    times += [counts[x:y].tobytes() if more else b"" for (x, y), more in zip(own, repeated.tolist())]
                    continue
                codes = band_codes(signatures(doc, grams, 1 + np.log(weight), n)).tolist()
                # at unit weights the sketch is another one only where a shingle is repeated
                again = np.flatnonzero(repeated)
                if len(again):
                    of = np.full(n, -1)
                    of[again] = np.arange(len(again))
                    pick = of[doc] >= 0
                    for at, more in zip(again.tolist(), band_codes(signatures(of[doc[pick]], grams[pick], np.ones(pick.sum()), len(again))).tolist()):
                        codes[at] = list({*codes[at], *more})
                out += [c if x < y else [] for c, (x, y) in zip(codes, own)]
            made = [pa.array(out, pa.binary()), pa.array(times, pa.binary())] if packed else [pa.array(out, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(content, pa.binary()), *made], names=["key", "content", *columns])

    given = docs.select(docs[key].alias("key"), docs[text].cast("string").alias("text")).where("key is not null")
    return given.mapInArrow(run, f"key {given.schema['key'].dataType.simpleString()}, content binary, " + ("sh binary, times binary" if packed else "bands array<bigint>"))


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard index of two sorted arrays of different numbers."""
    if not len(a) or not len(b):
        return 0.0
    both = int((b[np.minimum(np.searchsorted(b, a), len(b) - 1)] == a).sum())
    return both / (len(a) + len(b) - both)


def probability_jaccard(a: np.ndarray, wa: np.ndarray, b: np.ndarray, wb: np.ndarray) -> float:
    """Of two sorted arrays with weights: the sum over shared elements i of 1 / sum over all j of max(wa[j] / wa[i], wb[j] / wb[i])."""
    at = np.minimum(np.searchsorted(b, a), max(len(b) - 1, 0))
    shared = b[at] == a if len(b) else np.zeros(len(a), bool)
    if not shared.any():
        return 0.0
    x, y = wa[shared], wb[at[shared]]
    alone = np.ones(len(b), bool)
    alone[at[shared]] = False
    order = np.argsort(x / y, kind="stable")
    x, y = x[order], y[order]
    # elements whose ratio is smaller count by their weight in b, the others by that in a
    below = np.concatenate(([0.0], np.cumsum(y)))[:-1] + wb[alone].sum()
    above = np.cumsum(x[::-1])[::-1] + wa[~shared].sum()
    return float((1 / (above / x + below / y)).sum())


def _weights(times: np.ndarray, n: int) -> np.ndarray:
    return 1 + np.log(times) if len(times) else np.ones(n)


def similarity(a: np.ndarray, ta_: np.ndarray, b: np.ndarray, tb: np.ndarray, j: float | None = None) -> float:
    """The larger of the two indices, of shingles and how often each occurs (empty: once each)."""
    j = jaccard(a, b) if j is None else j
    return max(j, probability_jaccard(a, _weights(ta_, len(a)), b, _weights(tb, len(b)))) if len(ta_) or len(tb) else j


def shared_sums(sets: list[np.ndarray], weights: list[np.ndarray] | None = None, wide: int = 8192) -> np.ndarray:
    """For each two of the sets, the weight (1 each if none are given) in the first of the elements that they share."""
    n = len(sets)
    element, place, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    owner = np.repeat(np.arange(n), [len(x) for x in sets])
    keep = times[place] > 1
    column, owner = (np.cumsum(times > 1) - 1)[place[keep]], owner[keep]
    value = np.concatenate(weights)[keep] if weights else np.ones(len(column))
    order = np.argsort(column, kind="stable")
    column, owner, value = column[order], owner[order], value[order]
    edges = np.searchsorted(column, np.arange(0, len(element) + wide, wide))
    out = np.zeros((n, n))
    for x, y in zip(edges[:-1].tolist(), edges[1:].tolist()):
        if x < y:
            held = np.zeros((n, min(wide, int(column[y - 1]) % wide + 1)), np.float64 if weights else np.float32)
            held[owner[x:y], column[x:y] % wide] = value[x:y]
            out += held @ (held > 0).astype(held.dtype).T
    return out


def _slot_counts(batches):
    """Shingles of a part, counted by slot."""
    counts = np.zeros(SLOTS, np.int64)
    for batch in batches:
        for x in batch.column("sh"):
            counts += np.bincount((np.frombuffer(x.as_buffer(), np.uint64) % np.uint64(SLOTS)).astype(np.int64), minlength=SLOTS)
    some = np.flatnonzero(counts)
    yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(counts[some])], names=["slot", "n"])


def first_shingles(held: DataFrame, threshold: float) -> DataFrame:
    """key, band, room (shingles from there on), size and repeated (it has a shingle more than once): of each document (key, sh, times) the rarest shingles, of which linked documents have one in common. What two documents share is, by number or by weight, at least the threshold's share of each; so the first shingle that they share leaves that much behind it in both."""
    table = np.zeros(SLOTS, np.int64)
    for r in held.select("sh").mapInArrow(_slot_counts, "slot int, n bigint").groupBy("slot").agg(F.sum("n").alias("n")).toLocalIterator():  # SLOTS rows at most
        table[r.slot] = r.n
    counts = Shared(held.sparkSession.sparkContext, table)

    def run(batches):
        for batch in batches:
            out, sizes, repeated = [], [], []
            for sh, t in zip(batch.column("sh"), batch.column("times")):
                own, times = np.frombuffer(sh.as_buffer(), np.uint64), np.frombuffer(t.as_buffer(), np.uint32)
                order = np.lexsort((own, counts.value[(own % np.uint64(SLOTS)).astype(np.int64)]))
                size = len(own) - int(np.ceil(threshold * len(own) - 1e-9)) + 1
                if len(times):
                    weight = _weights(times, len(own))[order]
                    size = max(size, int((np.cumsum(weight[::-1])[::-1] >= threshold * weight.sum() - 1e-9).sum()))
                out.append(own[order[:size]].view(np.int64))
                sizes.append(len(own))
                repeated.append(len(times) > 0)
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(out, pa.list_(pa.int64())), pa.array(sizes, pa.int64()), pa.array(repeated, pa.bool_())], names=["key", "bands", "size", "repeated"])

    kind = held.schema["key"].dataType.simpleString()
    return held.mapInArrow(run, f"key {kind}, bands array<bigint>, size bigint, repeated boolean").select("key", "size", "repeated", F.posexplode("bands").alias("place", "band")).select("key", "band", (F.col("size") - F.col("place")).alias("room"), "size", "repeated")


def _with_room(firsts: DataFrame, threshold: float) -> DataFrame:
    """key and band of the first shingles with which a pair can begin that reaches the threshold: to a text of the least size there, a document must have so many shingles left. (Where shingles are repeated, weights decide, and all stay.)"""
    least = firsts.groupBy("band").agg(F.min("size").alias("least"), F.max("repeated").alias("some"), F.min("key").alias("low"), F.max("key").alias("high")).where("low < high").select("band", "least", "some")
    need = F.lit(threshold / (1 + threshold)) * (F.col("size") + F.col("least")) - F.lit(1e-6)
    return firsts.join(least, "band").where(F.col("some") | (F.col("room") >= need)).select("key", "band")


def _buckets(banded: DataFrame) -> DataFrame:
    """band, g (documents) and key of the rows (key, band) of bands with more than one document; of bands with the same documents one."""
    ends = banded.groupBy("band").agg(F.min("key").alias("low"), F.max("key").alias("high")).where("low < high").select("band")
    shared = banded.join(ends, "band", "left_semi").distinct()
    mark = lambda seed: F.sum(F.xxhash64("key", F.lit(seed)).cast("decimal(20,0)"))
    sets = shared.groupBy("band").agg(F.count("*").alias("g"), F.min("key").alias("low"), F.max("key").alias("high"), mark(1).alias("m1"), mark(2).alias("m2"))
    one = sets.groupBy("g", "low", "high", "m1", "m2").agg(F.min("band").alias("band")).select("band", "g")
    return shared.join(one, "band").select("band", "g", "key")


def _verified(threshold: float):
    """Rows of whole cells (band, x, y; side, label, key, sh, times) -> a forest of the links across labels: a, b."""

    def links(rows):
        names, labels, sides, sets, times = zip(*rows)
        if len(rows) == 2:
            if labels[0] != labels[1] and (sides[0] != sides[1] or sides[0] == 2) and similarity(sets[0], times[0], sets[1], times[1]) >= threshold:
                yield names
            return
        of = np.array(sides)
        number = {x: k for k, x in enumerate(dict.fromkeys(labels))}
        own = np.array([number[x] for x in labels])
        wanted = np.triu((own[:, None] != own) & ((of[:, None] != of) | (of == 2)), 1)
        if not wanted.any():
            return
        size = np.array([len(x) for x in sets], np.float64)
        common = shared_sums(sets)
        linked = wanted & (common / (size[:, None] + size - common) >= threshold)
        some = np.array([len(t) > 0 for t in times])
        if some.any():  # the share of each one's weight that the other has bounds the weighted index
            weight = [_weights(t, len(x)) for t, x in zip(times, sets)]
            share = shared_sums(sets, [w / w.sum() for w in weight]) + 1e-9
            for p, q in zip(*(x.tolist() for x in np.nonzero(wanted & ~linked & (some[:, None] | some) & (share >= threshold) & (share.T >= threshold)))):
                linked[p, q] = probability_jaccard(sets[p], weight[p], sets[q], weight[q]) >= threshold
        up = list(range(len(number)))

        def find(x):
            while up[x] != x:
                up[x] = x = up[up[x]]
            return x

        for p, q in zip(*(x.tolist() for x in np.nonzero(linked))):
            a, b = find(own[p]), find(own[q])
            if a != b:
                up[a] = b
                yield names[p], names[q]

    def run(batches):
        cell, rows = None, []
        for batch in batches:
            a, b = [], []
            kind = batch.schema.field("key").type
            got = [batch.column(c).to_pylist() for c in ("band", "x", "y", "key", "label", "side")]
            for band, x, y, key, label, side, sh, t in zip(*got, batch.column("sh"), batch.column("times")):
                if (band, x, y) != cell:
                    if len(rows) > 1:
                        for p, q in links(rows):
                            a.append(p)
                            b.append(q)
                    cell, rows = (band, x, y), []
                rows.append((key, label, side, np.frombuffer(sh.as_py(), np.uint64), np.frombuffer(t.as_py(), np.uint32)))
            yield pa.RecordBatch.from_arrays([pa.array(a, kind), pa.array(b, kind)], names=["a", "b"])
        if len(rows) > 1:
            last = list(links(rows))
            yield pa.RecordBatch.from_arrays([pa.array([p for p, _ in last], kind), pa.array([q for _, q in last], kind)], names=["a", "b"])

    return run


def compared(pairs: DataFrame, held: DataFrame, threshold: float) -> DataFrame:
    """pairs(a, b, ...) with linked; held: key, sh, times."""
    columns = pairs.columns
    side = lambda c: held.select(F.col("key").alias(c), F.col("sh").alias(f"sh_{c}"), F.col("times").alias(f"times_{c}"))
    rows = pairs.join(side("a"), "a").join(side("b"), "b").select(*columns, "sh_a", "times_a", "sh_b", "times_b")

    def run(batches):
        read = lambda x, kind: np.frombuffer(x.as_py(), kind)
        for batch in batches:
            at = [batch.column(c) for c in ("sh_a", "times_a", "sh_b", "times_b")]
            linked = [similarity(read(a, np.uint64), read(x, np.uint32), read(b, np.uint64), read(y, np.uint32)) >= threshold for a, x, b, y in zip(*at)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in columns), pa.array(linked, pa.bool_())], names=[*columns, "linked"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pairs.schema.fields)
    return rows.mapInArrow(run, f"{kinds}, linked boolean")


def _leaders(big: DataFrame, labels: DataFrame, k: int) -> DataFrame:
    """a, b: each document of the large parts that is outside the greatest component of one of them, with a leader from there; label of its component, and rank and to of the leader's. Components are ranked by size, then by the most crowded document: a text that the others are copies of shares most bands with them."""
    now = big.join(labels, "key")
    per = now.groupBy("band", "label").agg(F.max(F.struct("n", "score", "label")).alias("rank"), F.min(F.struct(F.xxhash64("key", F.lit(k)).alias("h"), "key")).alias("first"))
    top = per.groupBy("band").agg(F.count("*").alias("labels"), F.max(F.struct("rank", F.col("first.key").alias("leader"))).alias("top")).where("labels > 1").select("band", F.col("top.leader").alias("b"), F.col("top.rank").alias("rank"))
    open_ = now.join(top, "band").where("label <> rank.label")
    return open_.groupBy(F.col("key").alias("a"), "label").agg(F.max(F.struct("rank", "b")).alias("t")).select("a", "label", "t.b", F.col("t.rank.n").alias("n"), F.col("t.rank.score").alias("score"), F.col("t.rank.label").alias("to"))


def _joined(labels: DataFrame, links: DataFrame) -> DataFrame:
    """labels(key, label, n, score) after each linked component has gone under the greatest that it is linked to. That one has a higher rank, so there is no circle; what hangs two deep is gathered here, the rest in later rounds."""
    hook = links.where("linked").groupBy("label").agg(F.max(F.struct("n", "score", "to")).alias("t")).select("label", F.col("t.to").alias("to"))
    for _ in range(2):
        hook = hook.join(hook.select(F.col("label").alias("to"), F.col("to").alias("further")), "to", "left").select("label", F.coalesce("further", "to").alias("to"))
    new = labels.join(hook, "label", "left").select("key", "score", F.coalesce("to", "label").alias("label"))
    return new.drop("score").join(new.groupBy("label").agg(F.count("*").alias("n"), F.max("score").alias("score")), "label").select("key", "label", "n", "score")


def _cells(rows: DataFrame, cell: int) -> DataFrame:
    """key, label, band, x, y, side of each document of the buckets (band, g, key, label) that are not one component, for each cell that it is sent to. In each bucket the documents outside its largest component are dealt to blocks, and those within it to others; a cell is two blocks, of which one at least is outside."""
    per = rows.groupBy("band", "label").agg(F.count("*").alias("c"))
    top = per.groupBy("band").agg(F.count("*").alias("labels"), F.sum("c").alias("all"), F.max(F.struct("c", "label")).alias("t")).where("labels > 1")
    # a bucket of one block is one cell
    top = top.select("band", F.col("t.label").alias("own"), F.when(F.col("all") <= cell, 0).otherwise(F.ceil(F.col("t.c") / cell)).cast("int").alias("inner"), F.ceil(F.when(F.col("all") <= cell, F.col("all")).otherwise(F.col("all") - F.col("t.c")) / cell).cast("int").alias("outer"))
    now = rows.join(top, "band").withColumn("h", F.xxhash64("key", F.lit(7))).withColumn("inside", (F.col("label") == F.col("own")) & (F.col("inner") > 0))
    # outer blocks are numbered before inner ones
    now = now.withColumn("i", F.when(F.col("inside"), F.col("outer") + F.pmod("h", F.greatest("inner", F.lit(1)))).otherwise(F.pmod("h", F.greatest("outer", F.lit(1)))).cast("int"))
    now = now.withColumn("j", F.explode(F.sequence(F.lit(0), F.when(F.col("inside"), F.col("outer")).otherwise(F.col("outer") + F.col("inner")) - 1)))
    return now.select("key", "label", "band", F.least("i", "j").alias("x"), F.greatest("i", "j").alias("y"), F.when(F.col("i") == F.col("j"), 2).otherwise((F.col("i") < F.col("j")).cast("int")).alias("side"))


def classes(docs: DataFrame, key: str = "doc_id", text: str = "text", threshold: float = THRESHOLD, cell: int = CELL) -> DataFrame:
    """key, class_id (smallest id of the class), representative (smallest id with the same shingles) and rows (how many have the id) of every row's id."""
    scratch = Scratch()
    held = scratch.stored(sketches(docs, key, text), "sketches")
    # the smallest id of each content stands for it; its row is found again by the id, so hot contents move no sketches
    first = scratch.stored(held.where("content is not null").groupBy("content").agg(F.min("key").alias("representative")), "contents")
    alone = held.join(first.select("content", F.col("representative").alias("key")), ["content", "key"], "left_semi")
    found = scratch.stored(_buckets(alone.select("key", F.explode("bands").alias("band"))), "buckets")
    ids = scratch.stored(found.groupBy("key").agg(F.max("g").alias("g"), F.sum("g").alias("score")), "ids")
    n = ids.agg(F.count("*").alias("all"), F.count_if(F.col("g") > cell).alias("large")).first()
    few = lambda df, size: F.broadcast(df) if size <= FEW_IDS else df
    some = docs.select(docs[key].alias("key"), docs[text].alias("text")).join(few(ids.select("key"), n["all"]), "key", "left_semi")
    wanted = scratch.stored(sketches(some, "key", "text", True).groupBy("key").agg(F.min_by(F.struct("sh", "times"), "content").alias("s")).select("key", "s.sh", "s.times"), "shingles")
    crowded = wanted.join(few(ids.where(F.col("g") > cell).select("key"), n.large), "key", "left_semi")
    parts = scratch.stored(_buckets(_with_room(first_shingles(crowded, threshold), threshold)) if n.large else found.limit(0), "parts")
    buckets = found.where(F.col("g") <= cell).unionByName(parts)
    big = parts.where(F.col("g") > cell).select("band", "key")
    labels, links = scratch.stored(ids.join(big, "key", "left_semi").select("key", F.col("key").alias("label"), F.lit(1).cast("bigint").alias("n"), "score")), []
    for k in range(STARS):
        tried = scratch.stored(compared(_leaders(big, labels, k), wanted, threshold), "compared")
        got = tried.agg(F.count("*").alias("tried"), F.count_if("linked").alias("linked")).first()
        if got.linked:
            links.append(tried.where("linked").select("a", "b"))
            labels = scratch.stored(_joined(labels, tried))
        if got.linked * 20 < max(got.tried, 1):
            break
    now = buckets.join(labels.select("key", "label"), "key", "left").withColumn("label", F.coalesce("label", "key"))
    cells = _cells(now, cell)
    dealt = cells.join(wanted, "key").repartition("band", "x", "y").sortWithinPartitions("band", "x", "y")
    kind = held.schema["key"].dataType.simpleString()
    links.append(scratch.stored(dealt.select("band", "x", "y", "key", "label", "side", "sh", "times").mapInArrow(_verified(threshold), f"a {kind}, b {kind}"), "links"))
    pairs = links[0]
    for more in links[1:]:
        pairs = pairs.unionByName(more)
    linked = _components(pairs, scratch)
    members = held.select("key", "content").join(first, "content", "left").select("key", F.coalesce("representative", "key").alias("representative"))
    members = members.join(linked.select(F.col("key").alias("representative"), "label"), "representative", "left").select("key", "representative", F.coalesce("label", "representative").alias("class_id"))
    out = stored(members.groupBy("key").agg(F.min("class_id").alias("class_id"), F.min("representative").alias("representative"), F.count("*").alias("rows")).withColumnRenamed("key", key), "classes")
    scratch.clear()
    return out


def _components(pairs: DataFrame, scratch: Scratch) -> DataFrame:
    """key and label (the smallest key) of all linked keys."""
    if isinstance(pairs.schema["a"].dataType, INTEGERS):
        kind = pairs.schema["a"].dataType
        result = connected_components(Graph.from_edges(pairs.select(F.col("a").cast("bigint").alias("src"), F.col("b").cast("bigint").alias("dst"))))
        return result.labels.select(F.col("id").cast(kind).alias("key"), F.col("label").cast(kind).alias("label"))
    ids = scratch.stored(dense_ids(pairs.select(F.explode(F.array("a", "b")).alias("key")).distinct(), "key").select("key", "id"), "ids")  # in the order of the keys
    ends = pairs.join(ids.select(F.col("key").alias("a"), F.col("id").alias("src")), "a").join(ids.select(F.col("key").alias("b"), F.col("id").alias("dst")), "b").select("src", "dst")
    labels = connected_components(Graph.from_edges(ends)).labels
    return labels.join(ids, "id").select("key", "label").join(ids.select(F.col("id").alias("label"), F.col("key").alias("least")), "label").select("key", F.col("least").alias("label"))


def deduplicated(docs: DataFrame, key: str = "doc_id", text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """One row of docs for each class: that of the smallest id, as it is. Rows without an id stay; of several rows with the id that stays, that with the smallest hash of all columns stays."""
    found = classes(docs, key, text, threshold).where(F.col(key) == F.col("class_id"))
    kept = docs.join(found.where("rows = 1").select(key), key, "left_semi")
    again = docs.join(found.where("rows > 1").select(key), key, "left_semi")
    one = again.groupBy(F.col(key).alias("_id")).agg(F.min_by(F.struct(*[F.col(f"`{c}`") for c in docs.columns]), F.xxhash64(*[F.col(f"`{c}`") for c in docs.columns])).alias("_row")).select("_row.*")
    return kept.select(*[F.col(f"`{c}`") for c in docs.columns]).unionByName(one).unionByName(docs.where(F.col(key).isNull()))
