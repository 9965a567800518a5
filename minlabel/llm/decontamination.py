"""Benchmark decontamination by suffix arrays of the training text.

The documents are the training text, cut into shards (slices of an Arrow batch). Of each shard the suffixes that begin
at a word are ordered, as far as a test window reaches; suffixes whose first words begin no test window anywhere are
left out beforehand, as no search can end at them. Every test suffix is then found by binary search: the range of
suffixes that begin with its window are the places of verbatim copies, and copies that go on along both texts give the
longest match. The test texts are broadcast in blocks of a fixed size, each loaded in turn by a task, so their total
may be any; documents are read once, without a shuffle.

A window is WINDOW consecutive words of an item, or the whole of a shorter item. Words are compared by 64-bit hashes.

Defined cases: null and empty texts have no words, no hits and are not contaminated; items without words and without id
never match; repeated items count once for each id; repeated rows are judged each.
"""

from __future__ import annotations

import hashlib
import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from minlabel.llm import text_arrays as ta
from minlabel.llm.shared import Shared

WINDOW = 13
#: Contaminated: at least one hit word in so many.
ONE_IN = 20
#: Bytes of test texts in a block, and words of a test window that a training suffix must begin with to be ordered.
BLOCK_BYTES, LEAD = 8 << 20, 4


class TestBlock:
    """Windows of some test items, ready to be searched for."""

    __test__ = False

    def __init__(self, ids: list[str], texts: list[str], window: int):
        hasher, table = ta.Hasher(), ta.class_table("alnum")
        data, offsets = ta.byte_arrays(pa.array(texts, pa.large_string()))
        low = table[data]
        s, e, at = ta.words(low, offsets)
        h = hasher.words(low, s, e)
        self.window, self.ids = window, ids
        self.vocabulary = np.unique(h)
        rank = np.searchsorted(self.vocabulary, h).astype(np.uint32) + 1
        keys, where = {}, {}
        for item in range(len(ids)):
            own = rank[at[item] : at[item + 1]]
            if not len(own):
                continue
            size = min(window, len(own))
            for k in range(len(own) - size + 1):
                keys.setdefault(size, {}).setdefault(own[k : k + size].astype(">u4").tobytes(), []).append((item, at[item] + k))
        self.sizes = {}
        for size, found in keys.items():
            ordered = sorted(found)
            places = [found[x] for x in ordered]
            self.sizes[size] = (np.array(ordered, f"S{4 * size}"), np.cumsum([0, *map(len, places)]), np.array([p[0] for x in places for p in x]), np.array([p[1] for x in places for p in x]))
        self.lead = min([LEAD, *self.sizes]) if self.sizes else LEAD
        self.leads = np.unique(np.concatenate([_grams(_ranks_of(w, size), self.lead)[:, 0] if size >= self.lead else np.zeros(0, np.uint64) for size, (w, *_) in self.sizes.items()])) if self.sizes else np.zeros(0, np.uint64)
        self.filter = np.zeros(1 << 20, bool)
        self.filter[(self.leads >> np.uint64(44)).astype(np.int64)] = True


def _ranks_of(keys: np.ndarray, size: int) -> np.ndarray:
    return np.frombuffer(b"".join(k.ljust(4 * size, b"\0") for k in keys.tolist()), ">u4").reshape(-1, size).astype(np.uint64)


def _grams(ranks: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n ranks from each place on, along the last axis."""
    size = ranks.shape[-1] - n + 1
    out = np.zeros((*ranks.shape[:-1], size), np.uint64)
    for j in range(n):
        out = out * np.uint64(0x9E3779B97F4A7C15) + ranks[..., j : j + size]
    return ta.mixed(out)


def blocks(benchmark: DataFrame, key: str = "item_id", text: str = "text", window: int = WINDOW, size: int = BLOCK_BYTES) -> list:
    """Broadcasts of TestBlock; the driver holds one block of about size bytes at a time."""
    sc, out = benchmark.sparkSession.sparkContext, []
    rows = benchmark.where(F.col(key).isNotNull() & F.col(text).isNotNull()).select(F.col(key).cast("string"), F.col(text).cast("string")).toLocalIterator()

    def cut():
        held, room = [], size
        for k, t in rows:
            held.append((k, t))
            room -= len(t)
            if room <= 0:
                yield held
                held, room = [], size
        if held:
            yield held

    for held in cut():
        out.append(Shared(sc, TestBlock([k for k, _ in held], [t for _, t in held], window)))
    return out


def suffix_search(block: TestBlock, h: np.ndarray, at: np.ndarray):
    """Copies of the block's windows in a shard: arrays of first word, window size, and place in the test text, one for each copy and item place.

    h: word hashes of the shard; at: offsets of the words of each document."""
    none = np.zeros(0, np.int64)
    if not len(h) or not block.sizes:
        return none, none, none, none
    found = np.searchsorted(block.vocabulary, h)
    found[found == len(block.vocabulary)] = 0
    rank = np.where(block.vocabulary[found] == h, found + 1, 0)
    # suffixes that can match: their first words are the first of some window, and lie in one document
    if len(rank) < block.lead:
        return none, none, none, none
    grams = _grams(rank.astype(np.uint64), block.lead)
    maybe = np.flatnonzero(block.filter[(grams >> np.uint64(44)).astype(np.int64)])
    maybe = maybe[np.isin(grams[maybe], block.leads)]
    if not len(maybe):
        return none, none, none, none
    end = at[np.searchsorted(at, maybe, "right")]
    depth = max(block.sizes)
    ahead = maybe[:, None] + np.arange(depth)
    inside = ahead < end[:, None]
    matrix = np.where(inside, rank[np.minimum(ahead, len(rank) - 1)], 0).astype(">u4")
    suffixes = np.ascontiguousarray(matrix).view(f"S{4 * depth}").ravel()
    order = np.argsort(suffixes, kind="stable")
    ordered, places = suffixes[order], maybe[order]
    outs = []
    for size, (keys, first, items, tests) in block.sizes.items():
        padded = keys.astype(f"S{4 * depth}")
        lo = np.searchsorted(ordered, padded, "left")
        top = np.array([k.ljust(4 * size, b"\0") + b"\xff" * (4 * (depth - size)) for k in keys.tolist()], f"S{4 * depth}")
        hi = np.searchsorted(ordered, top, "right")
        n = hi - lo
        which = np.repeat(np.arange(len(keys)), n)
        starts = places[ta.ranges(lo, n)]
        copies = first[which + 1] - first[which]
        pick = ta.ranges(first[which], copies)
        outs.append((np.repeat(starts, copies), np.full(len(pick), size), items[pick], tests[pick]))
    return tuple(np.concatenate(x) for x in zip(*outs))


def _runs(starts: np.ndarray, sizes: np.ndarray, tests: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Copies that go on along both texts, joined: first words and lengths of the longest matches."""
    order = np.lexsort((starts, starts - tests))
    s, t, n = starts[order], (starts - tests)[order], sizes[order]
    new = np.ones(len(s), bool)
    new[1:] = (t[1:] != t[:-1]) | (s[1:] != s[:-1] + 1) | (n[1:] != n[:-1])
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(s)) - 1
    return s[first], s[last] - s[first] + n[last]


def scan(column: pa.Array, held: list, one_in: int = ONE_IN):
    """n_words, n_hit, items (sorted ids), longest (words) and spans (first:end words) of each text of a column."""
    hasher, table = scan.hasher if hasattr(scan, "hasher") else ta.Hasher(), ta.class_table("alnum")
    scan.hasher = hasher
    data, offsets = ta.byte_arrays(column)
    parts = []
    for i, j in ta.slices(offsets):
        low, own = table[data[offsets[i] : offsets[j]]], offsets[i : j + 1] - offsets[i]
        s, e, at = ta.words(low, own)
        parts.append((i, j, hasher.words(low, s, e), at))
    n = len(offsets) - 1
    n_words, n_hit, longest = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, np.int64)
    items: dict[int, set] = {}
    spans: dict[int, str] = {}
    marks = [np.zeros(len(h) + 1, np.int32) for _, _, h, _ in parts]
    for b in held:
        block = b.value
        for (i, j, h, at), mark in zip(parts, marks):
            starts, sizes, which, tests = suffix_search(block, h, at)
            if not len(starts):
                continue
            np.add.at(mark, starts, 1)
            np.add.at(mark, starts + sizes, -1)
            doc = np.searchsorted(at, starts, "right") - 1
            pairs = np.unique(doc * len(block.ids) + which)
            for d, k in zip((pairs // len(block.ids)).tolist(), (pairs % len(block.ids)).tolist()):
                items.setdefault(i + d, set()).add(block.ids[k])
            first, length = _runs(starts, sizes, tests)
            np.maximum.at(longest, i + np.searchsorted(at, first, "right") - 1, length)
        if len(held) > 1:
            b.release()  # one block in memory at a time
    for (i, j, h, at), mark in zip(parts, marks):
        n_words[i:j] = np.diff(at)
        hit = np.cumsum(mark[:-1]) > 0
        if hit.any():
            total = np.concatenate(([0], np.cumsum(hit)))
            n_hit[i:j] = total[at[1:]] - total[at[:-1]]
            edge = hit.copy()
            inner = at[1:-1][at[1:-1] < len(hit)]
            edge[1:] &= ~hit[:-1]
            edge[inner] = hit[inner]
            first = np.flatnonzero(edge)
            stop = hit.copy()
            stop[:-1] &= ~hit[1:]
            stop[inner - 1] = hit[inner - 1]
            for d, group in itertools.groupby(zip((np.searchsorted(at, first, "right") - 1).tolist(), first.tolist(), (np.flatnonzero(stop) + 1).tolist()), key=lambda x: x[0]):
                spans[i + d] = ",".join(f"{x - at[d]}:{y - at[d]}" for _, x, y in group)
    return n_words, n_hit, [sorted(items.get(d, ())) for d in range(n)], longest, [spans.get(d, "") for d in range(n)], (n_hit > 0) & (one_in * n_hit >= n_words)


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, one_in: int = ONE_IN, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row for each document: doc_id, n_words, n_hit, n_items, items, items_sha256, longest_match, spans, contaminated."""
    held = blocks(benchmark, window=window, size=block_bytes)

    def run(batches):
        for batch in batches:
            n_words, n_hit, items, longest, spans, bad = scan(batch.column("text"), held, one_in)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(n_words), pa.array(n_hit), pa.array([len(x) for x in items], pa.int64()), pa.array(items, pa.list_(pa.string())),
                 pa.array([hashlib.sha256(",".join(x).encode()).hexdigest() for x in items]), pa.array(longest), pa.array(spans), pa.array(bad)],
                names=["doc_id", "n_words", "n_hit", "n_items", "items", "items_sha256", "longest_match", "spans", "contaminated"],
            )

    given = docs.select("doc_id", docs["text"].cast("string").alias("text"))
    kind = given.schema["doc_id"].dataType.simpleString()
    return given.mapInArrow(run, f"doc_id {kind}, n_words bigint, n_hit bigint, n_items bigint, items array<string>, items_sha256 string, longest_match bigint, spans string, contaminated boolean")


def decontaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, one_in: int = ONE_IN, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows of docs that are not contaminated, as they are."""
    held, place = blocks(benchmark, window=window, size=block_bytes), docs.columns.index("text")

    def run(batches):
        for batch in batches:
            yield batch.filter(pa.array(~scan(batch.column(place), held, one_in)[-1]))

    return docs.mapInArrow(run, docs.schema)
