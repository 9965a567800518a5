"""Token counts by byte-pair merging with a heap over a linked list.

The merges of a byte-level vocabulary file are broadcast (their number is fixed by the file). Each text is cut by the
vocabulary's pre-token pattern; of each different pre-token the symbols (bytes) stand in a doubly linked list, a heap
holds the ranks of adjacent pairs, and the lowest pair is merged until none is left. Its count is the number of bytes
less the number of merges; no token identifiers are made. Whole texts are read, a batch at a time: one narrow pass
without a shuffle.

Defined cases: a null or empty text has 0 bytes and 0 tokens; a special string of the vocabulary inside a text is one
token; repeated rows are counted each; other columns are ignored.
"""

from __future__ import annotations

import json
from heapq import heapify, heappop, heappush

import pyarrow as pa
import pyarrow.compute  # noqa: F401
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Fixed value: the pre-token pattern of byte-level vocabularies.
PRE_TOKENS = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
POSITION, SYMBOL = 40, 20
#: Different pre-tokens whose counts a task remembers; beyond that it starts anew. Longer ones are not remembered.
REMEMBERED, LONGEST = 400_000, 64


def load_merges(path: str) -> dict:
    """From a byte-level vocabulary file: ids of the bytes, ranks of pairs, ids that merges give, special strings."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    model = spec["model"]
    ids = model["vocab"]
    shown = _shown_bytes()
    ranks, made = {}, []
    for rank, pair in enumerate(model["merges"]):
        a, b = pair.split(" ") if isinstance(pair, str) else pair
        ranks[ids[a] << SYMBOL | ids[b]] = rank
        made.append(ids[a + b])
    return {"bytes": [ids[shown[b]] for b in range(256)], "ranks": ranks, "made": made, "special": sorted((t["content"] for t in spec.get("added_tokens", [])), key=len, reverse=True)}


def _shown_bytes() -> list[str]:
    """The character that stands for each byte in such files: printable Latin-1 ones for themselves, the rest from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


def merged_length(symbols: list[int], ranks: dict[int, int], made: list[int]) -> int:
    """Symbols that are left when no adjacent pair has a rank; the list is used up."""
    n = left = len(symbols)
    if n < 2:
        return n
    get = ranks.get
    current = [get(a << SYMBOL | b, -1) for a, b in zip(symbols, symbols[1:])]
    heap = [r << POSITION | i for i, r in enumerate(current) if r >= 0]
    if not heap:
        return n
    current.append(-1)
    heapify(heap)
    after, before, low = list(range(1, n + 1)), list(range(-1, n - 1)), (1 << POSITION) - 1
    while heap:
        top = heappop(heap)
        i, r = top & low, top >> POSITION
        if current[i] != r:
            continue
        j = after[i]
        k = after[j]
        symbols[i] = s = made[r]
        after[i] = k
        current[j] = -1
        left -= 1
        if k < n:
            before[k] = i
            current[i] = c = get(s << SYMBOL | symbols[k], -1)
            if c >= 0:
                heappush(heap, c << POSITION | i)
        else:
            current[i] = -1
        p = before[i]
        if p >= 0:
            current[p] = c = get(symbols[p] << SYMBOL | s, -1)
            if c >= 0:
                heappush(heap, c << POSITION | p)
    return left


class Counter(dict):
    """pre-token -> its number of tokens; a missing one is merged."""

    def __init__(self, merges: dict):
        super().__init__()
        self.byte_ids, self.ranks, self.made = merges["bytes"], merges["ranks"], merges["made"]

    def __missing__(self, piece: str) -> int:
        ids = self.byte_ids
        n = merged_length([ids[b] for b in piece.encode("utf-8", "replace")], self.ranks, self.made)
        if len(piece) <= LONGEST:
            if len(self) >= REMEMBERED:
                self.clear()
            self[piece] = n
        return n


def counter_of(merges: dict):
    """text -> number of tokens."""
    find, known, special = regex.compile(PRE_TOKENS).findall, Counter(merges), merges["special"]
    cut = regex.compile("|".join(map(regex.escape, special))) if special else None

    def count(text: str) -> int:
        if special and any(s in text for s in special):
            parts = cut.split(text)
            return len(parts) - 1 + sum(sum(map(known.__getitem__, find(p))) for p in parts)
        return sum(map(known.__getitem__, find(text)))

    return count


def token_counts(docs: DataFrame, path: str, text: str = "text", limit: int = 512, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The columns keep, n_bytes, n_tokens and over_limit for each row."""
    held = docs.sparkSession.sparkContext.broadcast(load_merges(path))

    def run(batches):
        count = counter_of(held.value)
        for batch in batches:
            texts = batch.column("__text")
            lengths = texts.cast(pa.binary())
            rows = [("" if t is None else t) for t in texts.to_pylist()]
            counts = [count(t) for t in rows]
            sizes = pa.array([0 if b is None else b for b in pa.compute.binary_length(lengths).to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], sizes, pa.array(counts, pa.int64()), pa.array([c > limit for c in counts], pa.bool_())], names=[*batch.schema.names[:-1], "n_bytes", "n_tokens", "over_limit"])

    given = docs.select(*[F.col(c) for c in keep], _text(docs, text).alias("__text"))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in given.schema[:-1]), "n_bytes bigint, n_tokens bigint, over_limit boolean"])
    return given.mapInArrow(run, schema)


def _text(docs: DataFrame, name: str) -> Column:
    return docs[name].cast("string")
