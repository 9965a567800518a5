"""Personal data: fixed patterns, and candidate spans that boosted trees choose.

The base kinds (email, ip, card, phone) are found by patterns with a check of each match, and always stay. Beyond them
generators with high recall propose spans that may overlap: opaque tokens, values that are assigned, national id
numbers, bank account numbers, local telephone numbers. Gradient-boosted trees on features of the format and of the
text around give each a probability, calibrated on a part of the training spans that the trees have not seen; for each
kind the threshold is the lowest that keeps the wished precision there. Of overlapping spans the likelier one stays.
The trees are trained on the driver from a seeded generator of labelled spans, of a fixed number (TRAIN_SPANS).

Texts are worked on one by one in a narrow pass, without a shuffle; all patterns take time in proportion to the text.

Defined cases: null and empty texts have no spans; repeated rows are judged each; other columns pass through.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from minlabel.llm.shared import Shared

BASE_KINDS, MORE_KINDS = ("email", "ip", "card", "phone"), ("iban", "secret", "ssn", "tel")
TRAIN_SPANS, SEED, PRECISION = 6000, 20, 0.98

_DIGIT = re.compile("[0-9]")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_HOST = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        x = ord(d) - 48
        if i % 2:
            x = 2 * x - 9 * (x > 4)
        total += x
    return total % 10 == 0


def _emails(text: str):
    """Each match has one @ with all it needs on both sides, so the places of @ are enough."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _HOST.match(text, at + 1)):
            yield start, m.end()
            done = m.end()
        at = text.find("@", max(at + 1, done))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    out = [("email", a, b) for a, b in _emails(text)] if "@" in text else []
    if _DIGIT.search(text):
        if "." in text:
            out += [("ip", m.start(), m.end()) for m in _IP.finditer(text) if all(len(x.lstrip("0")) < 3 or len(x.lstrip("0")) == 3 and int(x) < 256 for x in m[0].split("."))]
        for m in _CARD.finditer(text):
            if m.end() - m.start() >= 16 and 16 <= len(d := m[0].replace(" ", "").replace("-", "")) <= 19 and luhn(d):
                out.append(("card", m.start(), m.end()))
        if "+" in text:
            out += [("phone", m.start(), m.end()) for m in _PHONE.finditer(text) if 8 <= len(_DIGIT.findall(m[0])) <= 15]
    return out


# Generators of candidates, with the kind that each proposes.
_OPAQUE = re.compile(r"(?<![A-Za-z0-9_/+=-])[A-Za-z0-9_/+=-]{16,}")
_ASSIGNED = re.compile(r"""[:=] {0,2}["']?([^\s"',;]{6,})""")
_SSN = re.compile(r"(?<![0-9A-Za-z-])[0-9]{3}[- ][0-9]{2}[- ][0-9]{4}(?![0-9-])")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
_TEL = re.compile(r"(?<![0-9+.-])(?:\([0-9]{2,5}\)|[0-9]{2,5})[ ./-][0-9]{3,4}[ .-][0-9]{3,4}(?![0-9-])")
GENERATORS = ((_OPAQUE, 0, "secret"), (_ASSIGNED, 1, "secret"), (_SSN, 0, "ssn"), (_IBAN, 0, "iban"), (_TEL, 0, "tel"))


def candidates(text: str) -> list[tuple[int, str, int, int]]:
    """generator, kind, start, end of every proposed span."""
    digits = bool(_DIGIT.search(text))
    out = []
    for g, (pattern, group, kind) in enumerate(GENERATORS):
        if (g < 2 or digits) and (g != 1 or "=" in text or ":" in text):
            out += [(g, kind, m.start(group), m.end(group)) for m in pattern.finditer(text)]
    return out


# Words before a span that speak for a kind.
_SECRET_WORDS = re.compile(r"passw|passwd|pwd|token|secret|api.?key|access.?key|auth|credential|bearer|private", re.I)
_ID_WORDS = re.compile(r"ssn|social|security|national|tax", re.I)
_TEL_WORDS = re.compile(r"tel|phone|call|mobile|fax|cell|contact", re.I)
_BANK_WORDS = re.compile(r"iban|bank|account|konto|compte|cuenta", re.I)
_KNOWN = re.compile(r"AKIA|ASIA|ghp_|gho_|sk[-_]|pk[-_]|xox[bap]-|eyJ|AIza")


def features(text: str, generator: int, start: int, end: int) -> list[float]:
    span, before, after = text[start:end], text[max(0, start - 30) : start], text[end : end + 2]
    n = len(span)
    kinds = ["d" if c.isdigit() else "u" if "A" <= c <= "Z" else "l" if c.islower() else "o" for c in span]
    counts, classes = Counter(span.lower()), Counter(kinds)
    letters = sum(c.isalpha() for c in span)
    return [
        *(float(generator == g) for g in range(len(GENERATORS))),
        float(min(n, 100)), classes["d"] / n, classes["u"] / n, classes["l"] / n, classes["o"] / n,
        sum(c in "0123456789abcdefABCDEF" for c in span) / n,
        -sum(v / n * math.log2(v / n) for v in counts.values()),
        sum(c in "aeiouyAEIOUY" for c in span) / letters if letters else 0.0,
        sum(a != b for a, b in zip(kinds, kinds[1:])) / n,
        max(counts.values()) / n,
        float(bool(_SECRET_WORDS.search(before))), float(bool(_ID_WORDS.search(before))), float(bool(_TEL_WORDS.search(before))), float(bool(_BANK_WORDS.search(before))),
        float(before[-1:] in ("=", ":") or before[-2:] in ("= ", ": ", '="', ':"', '"')), float(before[-1:] in "\"'" and after[:1] in "\"'" and bool(before) and bool(after)),
        float(bool(_KNOWN.match(span))), float(_mod97(span) if generator == 3 else 0),
        span.count("/") + span.count("-") + span.count("_") + 0.0,
    ]


def _mod97(span: str) -> bool:
    s = span.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def training_spans(n: int = TRAIN_SPANS, seed: int = SEED) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """Features, labels and kinds of the candidates in n made-up sentences with a known thing in each."""
    r = random.Random(seed)
    pick = lambda s, a, b: "".join(r.choice(s) for _ in range(r.randint(a, b)))
    hexes, upper, digits = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    base64 = upper + upper.lower() + digits + "+/"
    syllables = "th er on an re ed in ha or en ti ve sch ung keit lich tion ment eur que cion mente ado ble ing ly st".split()
    word = lambda a, b: "".join(r.choice(syllables) for _ in range(r.randint(a, b)))

    def iban() -> str:
        body, country = pick(digits, 16, 20), pick(upper, 2, 2)
        check = 98 - int("".join(str(int(c, 36)) for c in body + country + "00")) % 97
        s = f"{country}{check:02d}{body}"
        return " ".join(s[i : i + 4] for i in range(0, len(s), 4)) if r.random() < 0.5 else s

    tel = lambda: r.choice(["({}) {}-{}", "{}-{}-{}", "{} {} {}", "{}.{}.{}", "{}/{} {}"]).format(pick(digits, 3, 3), pick(digits, 3, 3), pick(digits, 4, 4))
    true = [
        lambda: (r.choice(["password=", "password: ", "pwd=", "passwd = ", 'secret = "', "token=", 'token = "', "api_key=", "API-KEY: "]), pick(r.choice([hexes, base64, base64 + "!%$#"]), 8, 48), r.choice(["", '"'])),
        lambda: (r.choice(["", "token ", 'token = "', "key "]), pick(hexes, 32, 64), ""),
        lambda: ("", r.choice(["AKIA", "ASIA"]) + pick(upper + digits, 16, 16), ""),
        lambda: ("", r.choice(["ghp_", "sk-", "xoxb-", "AIza", "eyJ"]) + pick(base64, 24, 50), ""),
        lambda: ("", pick(base64, 32, 64), ""),
        lambda: (r.choice(["SSN ", "ssn: ", "social security number ", "", "tax id "]), f"{r.randint(1, 899):03d}-{r.randint(1, 99):02d}-{r.randint(1, 9999):04d}", ""),
        lambda: (r.choice(["IBAN ", "account ", "", "bank: "]), iban(), ""),
        lambda: (r.choice(["tel ", "phone: ", "call ", "mobile ", "fax ", "contact "]), tel(), ""),
    ]
    false = [
        lambda: ("", word(6, 14), ""), lambda: ("", "-".join(word(2, 4) for _ in range(r.randint(2, 5))), ""),
        lambda: ("", "/".join(word(1, 3) for _ in range(r.randint(3, 7))), ""), lambda: ("", "_".join(word(1, 3) for _ in range(r.randint(3, 6))), ""),
        lambda: ("", r.choice("=-_+") * r.randint(16, 60), ""), lambda: ("", word(3, 5).title() + word(3, 5).title() + word(2, 4).title(), ""),
        lambda: (r.choice(["a: ", "note: ", "see: ", "x=", "n = ", "the: "]), word(2, 5), ""), lambda: (word(1, 3) + ": ", word(2, 6), r.choice([".", ","])),
        lambda: (r.choice(["total: ", "x=", "page=", "width: "]), pick(digits, 6, 8), ""), lambda: (r.choice(["note: ", "url: ", ""]), "https://" + word(2, 4) + "/" + word(3, 6), ""),
        lambda: (r.choice(["order ", "no. ", ""]), f"{pick(digits, 2, 5)} {pick(digits, 3, 4)} {pick(digits, 3, 4)}", ""),
        lambda: (r.choice(["", "from "]), f"{r.randint(1900, 2100)}-{r.randint(1000, 9999)}-{r.randint(1000, 9999)}", ""),
        lambda: ("", f"{pick(upper, 2, 2)}{pick(digits, 2, 2)}{pick(upper + digits, 8, 16)}", ""), lambda: ("part ", f"{pick(upper, 2, 2)}{pick(digits, 2, 2)} {pick(upper, 4, 4)} {pick(upper, 4, 4)}", ""),
        lambda: ("ratio ", f"{pick(digits, 3, 3)} {pick(digits, 2, 2)} {pick(digits, 4, 4)}", ""), lambda: ("", word(3, 6) + pick(digits, 1, 3) + word(2, 4), ""),
    ]
    rows, labels, kinds = [], [], []
    for i in range(n):
        real = i % 2 == 0
        lead, thing, tail = r.choice(true if real else false)()
        head = " ".join(word(1, 3) for _ in range(r.randint(0, 6)))
        text = f"{head} {lead}{thing}{tail} {word(1, 3)}"
        start = len(head) + 1 + len(lead)
        for g, kind, a, b in candidates(text):
            inside = real and a >= start - 2 and b <= start + len(thing) + len(tail) and (b - a) >= 0.8 * len(thing)
            rows.append(features(text, g, a, b))
            labels.append(inside)
            kinds.append(kind)
    return np.array(rows), np.array(labels, float), kinds


class BoostedTrees:
    """Trees of a fixed depth on the logistic loss, split at quantiles; each tree is an array of (feature, cut) and leaf values."""

    def __init__(self, rounds: int = 60, depth: int = 3, rate: float = 0.25, bins: int = 32):
        self.rounds, self.depth, self.rate, self.bins = rounds, depth, rate, bins

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        cuts = [np.unique(np.quantile(c, np.linspace(0, 1, self.bins + 1)[1:-1])) for c in x.T]
        binned = np.stack([np.searchsorted(c, v, "left") for c, v in zip(cuts, x.T)], 1)
        self.start = float(np.log(y.mean() / (1 - y.mean())))
        score, self.trees = np.full(len(y), self.start), []
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-score))
            gradient, weight = y - p, p * (1 - p)
            node, splits = np.zeros(len(y), int), {}
            for level in range(self.depth):
                for k in range((1 << level) - 1, (1 << (level + 1)) - 1):
                    rows = np.flatnonzero(node == k)
                    f, cut = self._split(binned[rows], gradient[rows], weight[rows])
                    splits[k] = (f, float(cuts[f][cut]) if cut < len(cuts[f]) else math.inf)
                    node[rows] = 2 * k + 1 + (binned[rows, f] > cut)
            first = (1 << self.depth) - 1
            leaves = [self.rate * float(gradient[node == k].sum() / (weight[node == k].sum() + 1.0)) for k in range(first, 2 * first + 1)]
            self.trees.append(([splits[k] for k in range(first)], leaves))
            score += np.array(leaves)[node - first]
        return self

    def _split(self, binned, gradient, weight):
        best = (0.0, 0, 1 << 30)
        for f in range(binned.shape[1]):
            g = np.cumsum(np.bincount(binned[:, f], gradient, self.bins + 1))
            w = np.cumsum(np.bincount(binned[:, f], weight, self.bins + 1))
            gain = g**2 / (w + 1) + (g[-1] - g) ** 2 / (w[-1] - w + 1) - g[-1] ** 2 / (w[-1] + 1)
            k = int(np.argmax(gain))
            if gain[k] > best[0] + 1e-9:
                best = (float(gain[k]), f, k)
        return best[1], best[2]

    def score(self, row: list[float]) -> float:
        s = self.start
        for splits, leaves in self.trees:
            k = 0
            while k < len(splits):
                f, cut = splits[k]
                k = 2 * k + 1 + (row[f] > cut)
            s += leaves[k - len(splits)]
        return s


class Chooser:
    """Trees, calibration and thresholds."""

    def __init__(self):
        x, y, kinds = training_spans()
        fold = np.arange(len(y)) % 3
        self.trees = BoostedTrees().fit(x[fold < 2], y[fold < 2])
        s, t, k = np.array([self.trees.score(r) for r in x[fold == 2].tolist()]), y[fold == 2], np.array(kinds)[fold == 2]
        self.a, self.b = 1.0, 0.0
        for _ in range(200):  # logistic calibration of the scores
            p = 1 / (1 + np.exp(-(self.a * s + self.b)))
            self.a += 0.1 * float(np.mean((t - p) * s))
            self.b += 0.1 * float(np.mean(t - p))
        p = 1 / (1 + np.exp(-(self.a * s + self.b)))
        self.thresholds = {}
        for kind in MORE_KINDS:
            own = np.sort(p[k == kind])
            good = [c for c in own if t[(k == kind) & (p >= c)].mean() >= PRECISION]
            self.thresholds[kind] = float(max(0.5, min(good))) if good else 2.0

    def probability(self, text: str, g: int, a: int, b: int) -> float:
        return 1 / (1 + math.exp(-(self.a * self.trees.score(features(text, g, a, b)) + self.b)))

    def spans(self, text: str, base: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
        """Chosen spans that overlap neither a base span nor a likelier chosen one."""
        found = [(self.probability(text, g, a, b), a, b, kind) for g, kind, a, b in candidates(text)]
        taken, out = sorted((a, b) for _, a, b in base), []
        for p, a, b, kind in sorted(found, key=lambda x: (-x[0], x[1], -x[2], x[3])):
            if p >= self.thresholds[kind] and all(b <= x or a >= y for x, y in taken):
                taken.append((a, b))
                out.append((kind, a, b))
        return out


def found(text: str | None, chooser: Chooser) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
    """Base spans, and all spans; by kind in the order of BASE_KINDS and MORE_KINDS, then by start."""
    if not text:
        return [], []
    base = base_spans(text)
    more = sorted(chooser.spans(text, base))
    return base, base + more


def written(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def personal_data(docs: DataFrame) -> DataFrame:
    """doc_id, numbers of base spans, base_sha256, n_more and spans of each row."""
    held = Shared(docs.sparkSession.sparkContext, Chooser())

    def run(batches):
        chooser = held.value
        for batch in batches:
            rows = []
            for text in batch.column("text").to_pylist():
                base, spans = found(text, chooser)
                n = Counter(k for k, _, _ in base)
                rows.append((*(n[k] for k in BASE_KINDS), hashlib.sha256(written(base).encode()).hexdigest(), len(spans) - len(base), written(spans)))
            columns = list(zip(*rows)) or [[]] * 7
            kinds = [pa.int64()] * 4 + [pa.string(), pa.int64(), pa.string()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(list(c), k) for c, k in zip(columns, kinds))], names=["doc_id", *(f"n_{k}" for k in BASE_KINDS), "base_sha256", "n_more", "spans"])

    given = docs.select("doc_id", docs["text"].cast("string").alias("text"))
    kind = given.schema["doc_id"].dataType.simpleString()
    return given.mapInArrow(run, f"doc_id {kind}, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, n_more bigint, spans string")


def redacted_text(text: str | None, chooser: Chooser) -> str | None:
    """The text with each span, or run of overlapping spans, as [KIND] of its first."""
    _, spans = found(text, chooser)
    if not spans:
        return text
    parts, at, stop = [], 0, -1
    for a, b, kind in sorted((a, b, k) for k, a, b in spans):
        if a >= stop:
            parts += text[at:a], f"[{kind.upper()}]"
        stop = max(stop, b)
        at = stop
    return "".join([*parts, text[at:]])


def redacted(docs: DataFrame) -> DataFrame:
    """docs with personal data replaced in text; n_chars, if there, follows the text."""
    held, names = Shared(docs.sparkSession.sparkContext, Chooser()), docs.columns
    place = names.index("text")

    def run(batches):
        chooser = held.value
        for batch in batches:
            texts = [redacted_text(t, chooser) for t in batch.column(place).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(texts, c.type) if i == place else c for i, c in enumerate(batch.columns)], schema=batch.schema)

    out = docs.mapInArrow(run, docs.schema)
    return out.withColumn("n_chars", F.coalesce(F.length("text").cast("bigint"), F.col("n_chars"))) if "n_chars" in names else out
