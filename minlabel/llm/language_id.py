"""Language identification by cross-parsing with suffix automata.

For each language a suffix automaton of a bounded sample of labelled text is built; it knows every string of the sample.
A text is parsed greedily into the longest strings that the automaton knows (phrases); the number of phrases times the
logarithm of the sample's length, for each byte, estimates the cross entropy, and the language with the least wins. Whole
texts are parsed, and phrases run as far as they match: texts are walked in blocks of BLOCK bytes, all blocks of a batch in
step, first each from the root; then those whose block before ended in another state than they began with are walked
again from that state, until none is left. (Parses from different states soon agree, so two walks are the rule.)

Fitting takes a passage of at most SAMPLE_CHARS characters, at a place up to a hash, of each of at most SAMPLE_DOCS
labelled documents a language, which are up to a hash of the id, until they have TRAIN_BYTES bytes. The automata are
broadcast: at most 2 * (TRAIN_BYTES + 4 * SAMPLE_CHARS) states for each of at most MAX_LANGUAGES languages (more are an
error).

Defined cases: a text that is null or has no letter is "und" with score 0, as is any text if nothing was learned; of
equal languages the first by name wins; repeated rows are judged each; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from minlabel.llm import text_arrays as ta
from minlabel.llm.shared import Shared

SAMPLE_DOCS, SAMPLE_CHARS, TRAIN_BYTES, MAX_LANGUAGES = 300, 4000, 60_000, 64
BLOCK, FOLDS, HELD_OUT = 512, 3, 1
#: Parts in which the rows of a language are ranked first.
SALTS = 64
UNKNOWN = "und"


class SuffixAutomaton:
    """All substrings of a sequence of symbols, as states with moves."""

    def __init__(self, sequence: list[int]):
        self.moves: list[dict[int, int]] = [{}]
        link, length, last = [-1], [0], 0
        for c in sequence:
            new = len(length)
            self.moves.append({})
            length.append(length[last] + 1)
            link.append(0)
            p = last
            while p >= 0 and c not in self.moves[p]:
                self.moves[p][c] = new
                p = link[p]
            if p >= 0:
                q = self.moves[p][c]
                if length[q] == length[p] + 1:
                    link[new] = q
                else:
                    copy = len(length)
                    self.moves.append(dict(self.moves[q]))
                    length.append(length[p] + 1)
                    link.append(link[q])
                    link[q] = link[new] = copy
                    while p >= 0 and self.moves[p].get(c) == q:
                        self.moves[p][c] = copy
                        p = link[p]
            last = new


def parse_table(automaton: SuffixAutomaton, symbols: int) -> np.ndarray:
    """Flat table of the greedy parse: at state * (symbols + 1) + symbol stands next state * (symbols + 1), and in the low two bits the phrases that end. The last symbol pads."""
    states, wide = len(automaton.moves), symbols + 1
    table = np.zeros((states, wide), np.int64)
    root = np.full(symbols, -1, np.int64)
    for c, t in automaton.moves[0].items():
        root[c] = t
    # without a move the phrase ends; the symbol begins the next one, or is one of its own where it is unknown
    table[:, :symbols] = np.where(root < 0, 2, (np.maximum(root, 0) * wide) << 2 | 1)
    table[0, :symbols] = np.where(root < 0, 1, (np.maximum(root, 0) * wide) << 2)
    rows = np.repeat(np.arange(states), [len(m) for m in automaton.moves])
    table[rows, [c for m in automaton.moves for c in m]] = np.array([t for m in automaton.moves for t in m.values()], np.int64) * wide << 2
    table[:, symbols] = (np.arange(states) * wide) << 2
    return table.ravel().astype(np.int32 if table.size < 1 << 29 else np.int64)


class Model:
    def __init__(self, samples: dict[str, bytes]):
        self.languages = sorted(k for k, v in samples.items() if v)
        letters = np.zeros(256, bool)
        letters[97:123] = True
        seen = np.zeros(256, bool)
        for v in samples.values():
            seen[np.frombuffer(v, np.uint8)] = True
        lower = np.arange(256)
        lower[65:91] += 32
        self.classes = np.zeros(256, np.uint8)  # all that is no letter is one class
        self.classes[97:123] = np.arange(1, 27)
        high = [b for b in range(128, 256) if seen[b]]
        self.classes[high] = 28 + np.arange(len(high))
        self.classes[[b for b in range(128, 256) if not seen[b]]] = 27
        self.classes = self.classes[lower]
        self.symbols = 28 + len(high)
        own = [self.classes[np.frombuffer(samples[k], np.uint8)] for k in self.languages]
        self.tables = [parse_table(SuffixAutomaton(x.tolist()), self.symbols) for x in own]
        self.bits = np.array([np.log2(max(len(x), 2)) for x in own])

    def phrases(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Phrases of each text (rows) by each language (columns)."""
        size = np.diff(offsets)
        per = -(-size // BLOCK)
        starts = np.repeat(offsets[:-1], per) + BLOCK * ta.ranges(np.zeros(len(per), np.int64), per)
        ends = np.minimum(starts + BLOCK, np.repeat(offsets[1:], per))
        out = np.zeros((len(size), len(self.languages)), np.int64)
        if not len(starts):
            return out
        grid = np.full((BLOCK, len(starts)), self.symbols, np.int32)
        codes = self.classes[data]
        for k in range(BLOCK):
            at = starts + k
            inside = at < ends
            grid[k, inside] = codes[at[inside]]
        used = per > 0
        first = (np.cumsum(per) - per)[used]
        last = (np.cumsum(per) - 1)[used]
        follows = np.ones(len(starts), bool)
        follows[first] = False
        for j, table in enumerate(self.tables):
            began, state, n = np.zeros(len(starts), table.dtype), np.zeros(len(starts), table.dtype), np.zeros(len(starts), np.int32)
            left = np.arange(len(starts))
            while len(left):
                state[left], n[left] = _walked(table, grid, left, began[left])
                after = np.zeros(len(starts), table.dtype)
                after[1:] = state[:-1]
                left = np.flatnonzero(follows & (after != began))
                began[left] = after[left]
            n[last] += state[last] > 0
            out[used, j] = np.add.reduceat(n, first)
        return out


def _walked(table: np.ndarray, grid: np.ndarray, lanes: np.ndarray, state: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """State after each of some blocks, and the phrases that ended in it."""
    grid = grid if len(lanes) == grid.shape[1] else grid[:, lanes]
    n = np.zeros(len(lanes), np.int32)
    for row in grid:
        v = table.take(state + row)
        n += v & 3
        state = v >> 2
    return state, n


def has_letter(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """For each text; letters beyond ASCII are looked for only where there are none within."""
    ascii_letter = np.zeros(256, bool)
    ascii_letter[65:91] = ascii_letter[97:123] = True
    total = np.concatenate(([0], np.cumsum(ascii_letter[data])))
    out = total[offsets[1:]] > total[offsets[:-1]]
    high = np.concatenate(([0], np.cumsum(data > 127)))
    for i in np.flatnonzero(~out & (high[offsets[1:]] > high[offsets[:-1]])):
        out[i] = any(map(str.isalpha, data[offsets[i] : offsets[i + 1]].tobytes().decode("utf-8", "replace")))
    return out


def fold(key: str = "doc_id", folds: int = FOLDS) -> Column:
    return F.crc32(F.col(key).cast("string")) % folds


def fit(docs: DataFrame, key: str = "doc_id", lang: str = "lang") -> Model:
    """From labelled documents outside the fold that is held out."""
    labelled = docs.where((fold(key) != HELD_OUT) & F.col(lang).isNotNull() & F.col("text").isNotNull())
    found = labelled.select(F.col(lang).alias("lang")).distinct().limit(MAX_LANGUAGES + 1).count()
    if found > MAX_LANGUAGES:
        raise ValueError(f"over {MAX_LANGUAGES} languages; the automata are made for {MAX_LANGUAGES} at most")
    ids = labelled.select(F.col(key).alias("key"), F.col(lang).alias("lang"), F.xxhash64(F.col(key)).alias("h")).withColumn("salt", F.pmod(F.xxhash64("h"), F.lit(SALTS)))
    for part in (["lang", "salt"], ["lang"]):  # first in parts, so that a language's rows do not meet in one task
        ids = ids.withColumn("n", F.row_number().over(Window.partitionBy(*part).orderBy("h", "key"))).where(F.col("n") <= SAMPLE_DOCS)
    # ids: SAMPLE_DOCS for each language at most
    text = F.col("text").cast("string")
    begin = F.pmod(F.xxhash64(F.col(key), F.lit("passage")), F.greatest(F.length(text) - SAMPLE_CHARS, F.lit(0)) + 1).cast("int") + 1
    rows = labelled.select(F.col(key).alias("key"), text.substr(begin, F.lit(SAMPLE_CHARS)).alias("text")).join(F.broadcast(ids.select("key", "lang", "h")), "key").select("lang", "h", "key", "text")
    samples: dict[str, list[bytes]] = {}
    size: dict[str, int] = {}
    for r in sorted(rows.distinct().toLocalIterator(), key=lambda r: (r.lang, r.h, r.key, r.text)):
        if size.get(r.lang, 0) < TRAIN_BYTES:
            samples.setdefault(r.lang, []).append(r.text.encode())
            size[r.lang] = size.get(r.lang, 0) + len(samples[r.lang][-1]) + 1
    return Model({k: b"\n".join(v) for k, v in samples.items()})


def languages(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, lang_pred, score, bits_per_byte of each row."""
    held = Shared(docs.sparkSession.sparkContext, model)

    def run(batches):
        m = held.value
        for batch in batches:
            data, offsets = ta.byte_arrays(batch.column("text"))
            names, scores, rates = [], [], []
            for i, j in ta.slices(offsets):
                own = offsets[i : j + 1] - offsets[i]
                known = has_letter(data[offsets[i] : offsets[j]], own)
                if not m.languages:
                    names += [UNKNOWN] * (j - i)
                    scores += [0.0] * (j - i)
                    rates += [0.0] * (j - i)
                    continue
                bits = m.phrases(data[offsets[i] : offsets[j]], own) * m.bits
                best = bits.argmin(1)
                least = bits.min(1)
                p = 1 / np.exp2(-np.minimum(bits - least[:, None], 4000) / 8).sum(1)
                names += [m.languages[b] if k else UNKNOWN for b, k in zip(best.tolist(), known.tolist())]
                scores += np.where(known, p, 0.0).tolist()
                rates += (least / np.maximum(np.diff(own), 1)).tolist()
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(rates, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score", "bits_per_byte"])

    given = docs.select("doc_id", F.coalesce(fold() == HELD_OUT, F.lit(False)).alias("held_out"), docs["text"].cast("string").alias("text"))
    kind = given.schema["doc_id"].dataType.simpleString()
    return given.mapInArrow(run, f"doc_id {kind}, held_out boolean, lang_pred string, score double, bits_per_byte double")
