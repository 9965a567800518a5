"""Removing repeated passages: windows of bytes, ordered by radix passes to a fixed depth.

Every window of WINDOW bytes (a suffix, cut at that depth) belongs to the smallest hashed gram of GRAM bytes in it, its
minimizer; grams that would crowd a bucket, as a look at some documents shows, come after all others. Runs of windows with one minimizer are shipped as one piece of text, to the bucket of the gram's hash; equal
windows so meet in one bucket, wherever they stand. Within a map task equal pieces are collapsed first: those of
larger ids are covered at once, and only the smallest id's is shipped, so that a passage of a third of all documents comes to
its bucket once from each task. In a bucket equal pieces are collapsed again; of what is left, windows whose fingerprint
is alone among those of their gram are dropped, and the rest are sorted by most-significant-digit passes of 8 bytes:
after each pass windows that are alone are done, and groups equal through the last pass are the repeated windows. A
window that starts in a document with a smaller id covers its bytes. The covered ranges go back to the documents by id
and hash of the text.

Equal pieces are told by 64-bit hashes; windows by all their bytes.

Defined cases: a null text is empty; texts under WINDOW bytes keep all; rows without id neither cover nor lose bytes;
rows of one id do not cover each other, and repeated rows lose the same bytes; other columns are ignored, or pass
through without_repeats, also ones that begin with ml_, as names of the operator's own do.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from minlabel.llm import text_arrays as ta
from minlabel.llm.shared import aside

WINDOW, GRAM = 50, 8
#: Bytes of text whose pieces a map task collapses together, and buckets for each shuffle partition.
#: Bytes of pieces of a bucket whose windows are sorted at once, and bytes that are hashed at once, which take some 60 times
#: as much memory.
CHUNK, BUCKETS, SORTED, HASHED = 16 << 20, 2, 4 << 20, 1 << 19
#: A gram is crowded if its pieces are more than this part of a bucket's share; one document in so many is looked at for them.
CROWDED, LOOKED_AT = 16, 16
_BIG = np.iinfo(np.int64).max


def _eights(data: np.ndarray, kind: str = "<u8") -> np.ndarray:
    """The 8 bytes from each place on, as numbers; zeros beyond the end."""
    n = len(data)
    padded = np.concatenate((data, np.zeros(16, np.uint8)))
    out = np.empty(n, np.uint64)
    for k in range(min(8, n)):
        out[k::8] = np.frombuffer(padded.data, kind, (n - k + 7) // 8, k)
    return out


def _postponed(h: np.ndarray, crowded: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of crowded grams, and what they rank by: after all others, the most crowded (the first) last."""
    known = np.argsort(crowded)
    sieve = np.zeros(1 << 16, bool)
    sieve[(crowded >> np.uint64(48)).astype(np.int64)] = True
    at = np.flatnonzero(sieve[(h >> np.uint64(48)).astype(np.int64)])
    k = known[np.minimum(np.searchsorted(crowded, h[at], sorter=known), len(crowded) - 1)]
    same = crowded[k] == h[at]
    return at[same], np.uint64(0xFFFFFFFF) - k[same].astype(np.uint64)


def pieces(data: np.ndarray, offsets: np.ndarray, crowded: np.ndarray | None = None):
    """Runs of windows with one minimizer: document, first window, number of windows, place of the gram, hash of the gram. No window crosses documents. Crowded grams (hashes) are minimizers only of windows that have no other."""
    n, span = len(data), WINDOW - GRAM + 1
    z = np.zeros(0, np.int64)
    if n < WINDOW:
        return z, z, z, z, np.zeros(0, np.uint64)
    x = _eights(data)
    h = ta.mixed(x[: n - GRAM + 1] * np.uint64(0x9E3779B97F4A7C15) + x[GRAM - 8 : n - 7])
    # the leftmost smallest hash among span grams, by doubling; the place stands in the low half
    least = (h & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(h), dtype=np.uint64)
    if crowded is not None and len(crowded):
        at, rank = _postponed(h, crowded)
        least[at] = rank << np.uint64(32) | at.astype(np.uint64)
    reach = 1
    while reach * 2 <= span:
        least = np.minimum(least[: len(least) - reach], least[reach:])
        reach *= 2
    if reach < span:
        least = np.minimum(least[: len(least) - (span - reach)], least[span - reach :])
    gram = (least & np.uint64(0xFFFFFFFF)).astype(np.int64)
    size = np.diff(offsets)
    windows = np.maximum(size - WINDOW + 1, 0)
    first = offsets[:-1]
    inside = np.zeros(len(gram) + 1, np.int8)  # windows within one document
    some = windows > 0
    inside[first[some]] += 1
    np.subtract.at(inside, (first + windows)[some], 1)
    valid = np.cumsum(inside[:-1]) > 0
    start = valid.copy()
    start[1:] &= (gram[1:] != gram[:-1]) | ~valid[:-1]
    own = first[some]
    start[own] = True
    at = np.flatnonzero(start)
    doc = np.searchsorted(offsets, at, "right") - 1
    end = np.minimum(np.append(at[1:], len(gram)), first[doc] + windows[doc])
    return doc, at, end - at, gram[at], h[gram[at]]


def _sealed(x: np.ndarray, level: int = 1) -> bytes:
    return zstandard.ZstdCompressor(level=level).compress(np.ascontiguousarray(x).tobytes())


def _opened(b: bytes, kind) -> np.ndarray:
    return np.frombuffer(zstandard.ZstdDecompressor().decompress(b), kind)


def _contents(hasher, text, begin, length, ahead, n):
    """Hash of each piece: its bytes, and which windows it stands for."""
    return hasher.parts(hasher.prefix(text), begin, begin + length) ^ ta.mixed((ahead << 8 | n).astype(np.uint64))


def _collapsed(content: np.ndarray, doc: np.ndarray):
    """Order by content and doc; and for each in that order whether a smaller doc has its content."""
    order = np.lexsort((doc, content))
    c, d = content[order], doc[order]
    new = np.concatenate(([True], c[1:] != c[:-1]))[: len(c)]
    least = d[np.maximum.accumulate(np.where(new, np.arange(len(c)), 0))]
    return order, d > least


def _map_chunk(ids, keys, data, offsets, hasher, buckets, crowded=None):
    """Rows (bucket, blobs) of one chunk: what goes to each bucket, and ranges that are covered within the chunk."""
    found = []
    for i, j in ta.slices(offsets, HASHED):
        part, own = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        doc, at, n, place, h = pieces(part, own, crowded)
        found.append((doc + i, at + offsets[i], n, place - at, h, _contents(hasher, part, at, n + WINDOW - 1, place - at, n)))
    doc, at, n, ahead, h, content = (np.concatenate(x) for x in zip(*found))
    if not len(doc):
        return
    order, covered = _collapsed(content, ids[doc])
    over, ship = order[covered], np.sort(order[~covered])  # shipped by document, so that ids pack well
    deal = lambda rows: rows[np.argsort((h[rows] >> np.uint64(40)) % np.uint64(buckets), kind="stable")]
    over, ship = deal(np.sort(over)), deal(ship)
    b_over, b_ship = (((h[x] >> np.uint64(40)) % np.uint64(buckets)).astype(np.int64) for x in (over, ship))
    inside = at - offsets[doc]
    for b in np.unique(np.concatenate((b_over, b_ship))).tolist():
        own, done = ship[slice(*np.searchsorted(b_ship, [b, b + 1]))], over[slice(*np.searchsorted(b_over, [b, b + 1]))]
        length = n[own] + WINDOW - 1
        yield b, [
            _sealed(data[ta.ranges(at[own], length)], 5), _sealed(np.diff(ids[doc[own]], prepend=0)), _sealed(keys[doc[own]]), _sealed(inside[own].astype(np.int32)),
            _sealed(np.stack((n[own], ahead[own])).astype(np.uint8)), _sealed(np.diff(ids[doc[done]], prepend=0)), _sealed(keys[doc[done]]), _sealed(np.stack((inside[done], n[done] + WINDOW - 1)).astype(np.int32)),
        ]


def _crowds(buckets: int):
    """Grams with the most pieces of a partition, and the bytes of these; all bytes of pieces beside a null."""

    def run(batches):
        mass, total = {}, 0
        for batch in batches:
            data, offsets = ta.byte_arrays(batch.column("text"))
            for i, j in ta.slices(offsets, HASHED):
                _, _, n, _, h = pieces(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
                grams, place = np.unique(h, return_inverse=True)
                weight = np.bincount(place, n + WINDOW - 1, len(grams)).astype(np.int64)
                total += int(weight.sum())
                for g, w in zip(grams.view(np.int64).tolist(), weight.tolist()):
                    mass[g] = mass.get(g, 0) + w
            if len(mass) > 1 << 18:  # the light ones are forgotten
                mass = {g: w for g, w in mass.items() if w * 4 * CROWDED * buckets >= total}
        kept = [(g, w) for g, w in mass.items() if w * 4 * CROWDED * buckets >= total]
        yield pa.RecordBatch.from_arrays([pa.array([None, *(g for g, _ in kept)], pa.int64()), pa.array([total, *(w for _, w in kept)], pa.int64())], names=["gram", "bytes"])

    return run


def crowded_grams(given: DataFrame, buckets: int) -> np.ndarray:
    """Hashes of grams whose pieces would crowd a bucket, the most crowded first, by a part of the documents. They only settle which gram of a window is its minimizer: any choice that all windows agree in gives the same result."""
    seen = given.where(F.pmod(F.xxhash64("id"), F.lit(LOOKED_AT)) == 0).select("text").mapInArrow(_crowds(buckets), "gram bigint, bytes bigint")
    rows = seen.groupBy("gram").agg(F.sum("bytes").alias("bytes")).orderBy(F.col("gram").isNotNull(), F.desc("bytes")).limit(1 + CROWDED * buckets).collect()
    total = rows[0].bytes if rows else 0
    return np.array([r.gram for r in rows[1:] if r.bytes * CROWDED * buckets > total], np.int64).view(np.uint64)


def _shipped(buckets: int, chunk: int, crowded: np.ndarray | None = None):
    def run(batches):
        hasher = ta.Hasher()
        held, room = [], chunk

        def flush():
            data = np.concatenate([h[2] for h in held])
            sizes = np.concatenate([np.diff(h[3]) for h in held])
            rows = list(_map_chunk(np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held]), data, np.concatenate(([0], np.cumsum(sizes))), hasher, buckets, crowded))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array([b for b, _ in rows], pa.int32()), pa.array([p for _, p in rows], pa.list_(pa.binary()))], names=["bucket", "parts"])

        for batch in batches:
            ids, keys = batch.column("id").to_numpy(), batch.column("h").to_numpy().astype(np.int32)
            data, offsets = ta.byte_arrays(batch.column("text"))
            for i, j in ta.slices(offsets):
                held.append((ids[i:j], keys[i:j], data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]))
                room -= int(offsets[j] - offsets[i])
                if room <= 0:
                    yield from flush()
                    held, room = [], chunk
        if held:
            yield from flush()

    return run


def radix_groups(digits, order: np.ndarray, group: np.ndarray, passes: int):
    """Depth-limited most-significant-digit sort. digits(pass, rows) gives the numbers to sort by. Returns rows and groups of those that are equal in all passes to some other."""
    for k in range(passes):
        if not len(order):
            break
        d = digits(k, order)
        by = np.lexsort((d, group))
        order, g, d = order[by], group[by], d[by]
        new = np.ones(len(order), bool)
        new[1:] = (g[1:] != g[:-1]) | (d[1:] != d[:-1])
        group = np.cumsum(new) - 1
        many = np.bincount(group)[group] > 1
        order, group = order[many], group[many]
    return order, group


def _reduce(rows: list):
    """Covered ranges of one bucket: ids and keys, starts and lengths."""
    hasher = ta.Hasher()
    text = np.concatenate([_opened(p[0], np.uint8) for p in rows])
    who = np.stack((np.concatenate([np.cumsum(_opened(p[1], np.int64)) for p in rows]), np.concatenate([_opened(p[2], np.int32) for p in rows])))
    at = np.concatenate([_opened(p[3], np.int32) for p in rows]).astype(np.int64)
    n, ahead = np.concatenate([_opened(p[4], np.uint8).reshape(2, -1) for p in rows], axis=1).astype(np.int64)
    done = np.stack((np.concatenate([np.cumsum(_opened(p[5], np.int64)) for p in rows]), np.concatenate([_opened(p[6], np.int32) for p in rows])))
    out = [(done, np.concatenate([_opened(p[7], np.int32).reshape(2, -1) for p in rows], axis=1).astype(np.int64))]
    length = n + WINDOW - 1
    edge = np.concatenate(([0], np.cumsum(length)))
    begin = edge[:-1]
    if len(n):
        content = np.concatenate([_contents(hasher, text[edge[i] : edge[j]], begin[i:j] - edge[i], length[i:j], ahead[i:j], n[i:j]) for i, j in ta.slices(edge, HASHED)])
        order, covered = _collapsed(content, who[0])
        over, left = order[covered], order[~covered]
        out.append((who[:, over], np.stack((at[over], length[over]))))
        # windows of different pieces of one gram are compared, some grams at a time
        gram = _grams(text, begin[left] + ahead[left])
        by = np.argsort(gram, kind="stable")
        left, gram = left[by], gram[by]
        first = np.flatnonzero(np.concatenate(([True], gram[1:] != gram[:-1])))
        stop = np.append(first[1:], len(left))
        total = np.concatenate(([0], np.cumsum(length[left])))
        for i, j in ta.slices(np.concatenate(([0], total[stop])), SORTED):
            own = left[first[i] : stop[j - 1]]
            number = np.repeat(np.arange(j - i), stop[i:j] - first[i:j])
            classes = -(-int(length[own].sum()) // (2 * SORTED))  # those of one gram may be more: its windows are then parted by their fingerprints
            for k in range(classes):
                out += _repeated_windows(hasher, text, begin[own], number, who[:, own], at[own], n[own], classes, k)
    return np.concatenate([a for a, _ in out], axis=1), np.concatenate([b for _, b in out], axis=1)


def _loaded(text: np.ndarray, place: np.ndarray) -> np.ndarray:
    """The 8 bytes at each place, as numbers."""
    return np.lib.stride_tricks.sliding_window_view(text, 8)[place].view("<u8").ravel()


def _grams(text: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Hash of the gram at each place."""
    return ta.mixed(_loaded(text, place) * np.uint64(0x9E3779B97F4A7C15) + _loaded(text, place + GRAM - 8))


def _repeated_windows(hasher, text, begin, number, who, at, n, classes=1, k=0):
    """Ranges of windows of these pieces of the text (number: their gram, in order) that stand in a document with a smaller id too; of the k-th class of fingerprints."""
    ids, length = who[0], n + WINDOW - 1
    edge = np.concatenate(([0], np.cumsum(length)))
    starts, of, prints = [], [], []
    for i, j in ta.slices(edge, HASHED):
        local, at_piece = ta.ranges(edge[i:j] - edge[i], n[i:j]), np.repeat(np.arange(i, j), n[i:j])
        found = hasher.parts(hasher.prefix(text[ta.ranges(begin[i:j], length[i:j])]), local, local + WINDOW)
        own = slice(None) if classes == 1 else found % np.uint64(classes) == k
        starts.append((local + (begin - edge[:-1])[at_piece] + edge[i])[own])
        of.append(at_piece[own])
        prints.append(found[own])
    start, piece, print_ = (np.concatenate(x) for x in (starts, of, prints))  # windows, by where they stand in the text
    del starts, of, prints
    ordered = np.sort(print_)
    again = ordered[1:][ordered[1:] == ordered[:-1]]
    if not len(again):
        return []
    sieve = np.zeros(1 << 20, bool)
    sieve[(again >> np.uint64(44)).astype(np.int64)] = True
    maybe = np.flatnonzero(sieve[(print_ >> np.uint64(44)).astype(np.int64)])
    near = np.minimum(np.searchsorted(again, print_[maybe]), len(again) - 1)
    maybe = maybe[again[near] == print_[maybe]]
    start, piece = start[maybe], piece[maybe]
    depth = [min(8 * k, WINDOW - 8) for k in range(-(-WINDOW // 8))]
    rows, groups = radix_groups(lambda k, r: _loaded(text, start[r] + depth[k]), np.arange(len(start)), number[piece], len(depth))
    if not len(rows):
        return []
    d = ids[piece[rows]]
    edge = np.flatnonzero(np.concatenate(([True], groups[1:] != groups[:-1])))
    least = np.repeat(np.minimum.reduceat(d, edge), np.diff(np.append(edge, len(d))))
    hit = np.sort(rows[d > least])
    if not len(hit):
        return []
    # neighbouring windows of a piece are one range
    run = np.flatnonzero(np.concatenate(([True], (start[hit[1:]] != start[hit[:-1]] + 1) | (piece[hit[1:]] != piece[hit[:-1]]))))
    count, p = np.diff(np.append(run, len(hit))), piece[hit[run]]
    return [(who[:, p], np.stack((at[p] + start[hit[run]] - begin[p], count + WINDOW - 1)))]


def _resolved(batches):
    """Rows of a bucket come one after another -> (id, h, ranges): sorted, joined ranges of each document, packed."""

    def done(rows):
        who, what = _reduce(rows)
        if not who.shape[1]:
            return None
        order = np.lexsort((what[0], who[1], who[0]))
        who, what = who[:, order], what[:, order]
        new = np.concatenate(([True], (who[:, 1:] != who[:, :-1]).any(0)))
        first = np.flatnonzero(new)
        number = np.cumsum(new) - 1
        # join ranges that touch: the furthest end so far, within the document
        shift = number * (int(what.sum(0).max()) + 1)
        furthest = np.maximum.accumulate(what.sum(0) + shift)
        apart = new.copy()
        apart[1:] |= what[0, 1:] + shift[1:] > furthest[:-1]
        a = np.flatnonzero(apart)
        ends = furthest[np.append(a[1:], len(shift)) - 1] - shift[a]
        ranges = np.stack((what[0, a], ends), 1).astype(np.int32)
        cut = np.searchsorted(a, np.append(first, len(shift)))
        return pa.RecordBatch.from_arrays(
            [pa.array(who[0, first]), pa.array(who[1, first].astype(np.int32)), pa.array([ranges[cut[k] : cut[k + 1]].tobytes() for k in range(len(first))], pa.binary())], names=["id", "h", "ranges"]
        )

    bucket, rows = None, []
    for batch in batches:
        for b, p in zip(batch.column("bucket").to_pylist(), batch.column("parts").to_pylist()):
            if rows and b != bucket:
                if (out := done(rows)) is not None:
                    yield out
                rows = []
            bucket = b
            rows.append(p)
    if rows and (out := done(rows)) is not None:
        yield out


def _short_hash(text):
    """Tells texts of rows with one id apart."""
    return F.shiftright(F.xxhash64(text.cast("string")), 33).cast("int")


def covered_ranges(docs: DataFrame, key: str = "doc_id", text: str = "text", chunk: int = CHUNK) -> DataFrame:
    """id, h (hash of the text), ranges: packed starts and ends of covered bytes; a document may have several rows."""
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    buckets = parts * BUCKETS
    given = docs.where(docs[key].isNotNull()).select(docs[key].cast("bigint").alias("id"), _short_hash(docs[text]).alias("h"), F.coalesce(docs[text].cast("string"), F.lit("")).alias("text")).where(F.octet_length("text") >= WINDOW)
    shipped = given.mapInArrow(_shipped(buckets, chunk, crowded_grams(given, buckets)), "bucket int, parts array<binary>")
    return shipped.repartitionById(parts, F.pmod("bucket", F.lit(parts)).cast("int")).sortWithinPartitions("bucket").mapInArrow(_resolved, "id bigint, h int, ranges binary")


def _joined(blobs: list) -> np.ndarray:
    """Ranges of all blobs as one sorted list of separate ranges that do not touch."""
    r = np.concatenate([np.frombuffer(b, np.int32).reshape(-1, 2) for b in blobs]).astype(np.int64)
    r = r[np.argsort(r[:, 0], kind="stable")]
    furthest = np.maximum.accumulate(r[:, 1])
    apart = np.concatenate(([True], r[1:, 0] > furthest[:-1]))
    a = np.flatnonzero(apart)
    return np.stack((r[a, 0], furthest[np.append(a[1:], len(r)) - 1]), 1)


def _cut(data: bytes, ranges: np.ndarray) -> bytes:
    keep, at = [], 0
    for a, b in ranges.tolist():
        keep.append(data[at:a])
        at = b
    keep.append(data[at:])
    return b"".join(keep)


def _with_ranges(docs: DataFrame, key: str, text: str) -> DataFrame:
    found = covered_ranges(docs, key, text).groupBy("id", "h").agg(F.collect_list("ranges").alias("ml_ranges"))
    own = docs.withColumn("ml_id", docs[key].cast("bigint")).withColumn("ml_h", _short_hash(docs[text]))
    return own.join(found.withColumnsRenamed({"id": "ml_id", "h": "ml_h"}), ["ml_id", "ml_h"], "left").drop("ml_id", "ml_h")


def repeated_passages(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of each row."""

    def run(batches):
        for batch in batches:
            rows = []
            for held, blobs in zip(batch.column("text").cast(pa.large_binary()), batch.column("ml_ranges").to_pylist()):
                data = held.as_py() or b""
                ranges = _joined(blobs) if blobs else np.zeros((0, 2), np.int64)
                rows.append((len(data), int((ranges[:, 1] - ranges[:, 0]).sum()), len(ranges), hashlib.sha256(_cut(data, ranges)).hexdigest()))
            columns = list(zip(*rows)) or [[]] * 4
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(list(c), k) for c, k in zip(columns, kinds))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    given = _with_ranges(docs.select(docs[key].alias("doc_id"), docs[text].cast("string").alias("text")), "doc_id", "text")
    return given.select("doc_id", "text", "ml_ranges").mapInArrow(run, f"doc_id {given.schema['doc_id'].dataType.simpleString()}, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string")


def without_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs with repeated passages cut out of the text; bytes of a character that was cut in two are dropped."""
    names, (given, now) = docs.columns, aside(docs)
    place = names.index(text)

    def run(batches):
        for batch in batches:
            blobs = batch.column(len(names)).to_pylist()
            texts = [t if not b else _cut(t.encode(), _joined(b)).decode("utf-8", "ignore") for t, b in zip(batch.column(place).to_pylist(), blobs)]
            yield pa.RecordBatch.from_arrays([pa.array(texts, c.type) if i == place else c for i, c in enumerate(batch.columns[:-1])], names=names)

    return _with_ranges(given, now[key], now[text]).select(*[F.col(f"`{now[c]}`") for c in names], "ml_ranges").mapInArrow(run, docs.schema)
