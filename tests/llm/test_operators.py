"""Each operator against a plain version, and on odd tables."""

import collections
import hashlib
import math
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from minlabel.llm import chat_formatting, context_trees, decontamination, language_id, mixing, near_duplicates, personal_data, quality_rules, queries, repeated_passages, token_counts
from minlabel.session import table
from tests.conftest import SMALL, SMOKE
from tests.helpers import same
from tests.llm import plain

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, n_words string"
LOW = {c: c + 32 for c in range(65, 91)}
LONG = " ".join(f"w{i % 997}x{i * 7 % 1013}" for i in range(20_000))
ODD = [
    (1, None, None, None, None, "a"), (2, "", "en", "src0", 0, None), (3, "one", "en", "src0", 3, "b"), (3, "one", "en", "src0", 3, "b"),
    (None, "no id here", "de", None, 10, None), (4, LONG, "en", "src1", len(LONG), "c"), (5, LONG + " end", "en", "src1", len(LONG) + 4, "c"), (6, "  \n\n\t", "fr", "src2", 5, None),
    (7, "été ÀÉ \U0001f642 a@b.co 1.2.3.4", "fr", "src2", 20, ""), (8, "x" * 3000, "en", "src0", 3000, ""), (9, "...", None, "src0", 3, ""),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(2, 1, 0), (4, 1, 0), (4, 0, 0), (None, 1, None), (99, None, 1)], "doc_id bigint, quality int, toxic int")


def texts(spark, sf_dir):
    return [(r.doc_id, r.text or "") for r in table(spark, sf_dir, "documents").select("doc_id", "text").collect()]


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_sql(spark, name):
    same(spark, queries.queries()[name], queries.oracle_sql()[name], SMOKE)


def test_every_row_comes_back(spark, odd, none, labels):
    bench = spark.createDataFrame([(1, "one"), (2, None), (None, "one"), (3, ""), (4, LONG[:300])], "item_id bigint, text string")
    import public_tokenizers

    model = language_id.fit(odd)
    runs = {
        "quality": lambda d: quality_rules.quality_report(d, labels), "contamination": lambda d: decontamination.contamination(d, bench), "language": lambda d: language_id.languages(d, model),
        "passages": repeated_passages.repeated_passages, "scores": context_trees.scores, "tokens": lambda d: token_counts.token_counts(d, public_tokenizers.path("byte_bpe_50k.json")), "personal": personal_data.personal_data,
    }
    for name, f in runs.items():
        assert f(odd).count() == len(ODD), name
        assert f(none).count() == 0, name
    assert near_duplicates.classes(none).count() == 0
    assert decontamination.contamination(odd, bench.limit(0)).where("contaminated").count() == 0
    assert mixing.mixed(none).count() == 0
    got = collections.Counter(r.doc_id for r in mixing.mixed(odd, {"src0": 1.0}, 2.0).collect())
    assert set(got) <= {1, 2, 3, 8, 9}  # the others have no weight
    for stage in (lambda d: quality_rules.keep_good(d, labels), near_duplicates.deduplicated, lambda d: decontamination.decontaminated(d, bench), personal_data.redacted, repeated_passages.without_repeats):
        assert stage(odd).columns == odd.columns
        assert stage(none).count() == 0


def test_quality_odd(odd, labels):
    got = {r.doc_id: r for r in quality_rules.quality_report(odd, labels).collect()}
    assert got[1].n_words == 0 and got[1].base_failed and not got[1].kept
    assert got[4].n_words == 20_000 and got[8].n_words == 1


def test_quality_many_labels(spark, monkeypatch):
    """Kept documents are those of the report, whether label ids are broadcast or all texts are measured."""
    docs, labels = table(spark, SMALL, "documents"), table(spark, SMALL, "labels")
    kept = {r.doc_id for r in quality_rules.quality_report(docs, labels).where("kept").collect()}
    assert kept == {r.doc_id for r in quality_rules.keep_good(docs, labels).collect()}
    monkeypatch.setattr(quality_rules, "FEW_IDS", 3)
    assert kept == {r.doc_id for r in quality_rules.keep_good(docs, labels).collect()}


def test_tokens_like_the_library(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    library, count = Tokenizer.from_file(path), token_counts.counter_of(token_counts.load_merges(path))
    given = [t for _, t in texts(spark, SMOKE)] + ["", "<|endoftext|> a<|endoftext|>", "a" * 3000, "  \n\n x\t y'll don't É漢字 \U0001f642 ٣٤", "\x00\x01\x85 z"]
    assert [count(t) for t in given] == [len(e.ids) for e in library.encode_batch(given, add_special_tokens=False)]


@pytest.mark.parametrize("block", [decontamination.BLOCK_BYTES, 3000])
def test_contamination(spark, block):
    bench = [(r.item_id, r.text) for r in table(spark, SMOKE, "benchmark").collect()] + [(777, "the thing"), (778, LONG[:200])]
    docs = texts(spark, SMOKE) + [(4001, LONG), (4002, "a " + LONG[:150])]
    want = plain.contamination(docs, bench)
    got = decontamination.contamination(spark.createDataFrame(docs, "doc_id bigint, text string"), spark.createDataFrame(bench, "item_id bigint, text string"), block_bytes=block)
    assert {r.doc_id: (r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) for r in got.collect()} == want


def test_passages(spark):
    docs = texts(spark, SMOKE) + [(9001, "q" * 49), (9002, "q" * 60), (9003, "zz" + "q" * 70), (9004, LONG), (9005, LONG[100:4000] + "!" + LONG[200:900]), (9006, LONG[3000:3100] * 3)]
    first, want = {}, {}
    for i, t in docs:
        b = t.encode()
        for k in range(len(b) - 49):
            first.setdefault(b[k : k + 50], i)
    for i, t in docs:
        b = t.encode()
        over = set()
        for k in range(len(b) - 49):
            if first[b[k : k + 50]] < i:
                over |= set(range(k, k + 50))
        spans = sum(1 for k in over if k - 1 not in over)
        want[i] = (len(b), len(over), spans, hashlib.sha256(bytes(c for k, c in enumerate(b) if k not in over)).hexdigest())
    got = repeated_passages.repeated_passages(spark.createDataFrame(docs[::-1], "doc_id bigint, text string").repartition(3))
    assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got.collect()} == want


def _crowd(n=400):
    """Texts of one frequent gram in ever other surroundings, and some repeated passages."""
    r = np.random.default_rng(5)
    word = lambda: "".join(map(chr, r.integers(97, 123, 6)))
    docs = [(k, " ".join(f"the the {word()} {word()}" for _ in range(60))) for k in range(n)]
    return docs + [(n + k, docs[k][1][100:900] + docs[3 * k][1][:300]) for k in range(0, 60, 3)]


def test_passages_of_a_crowded_gram(spark, monkeypatch):
    """The pieces of one gram do not fill one bucket, and where they do, its windows are parted; the result is the same."""
    docs = _crowd()
    df = spark.createDataFrame(docs, "doc_id bigint, text string").repartition(3)
    given, buckets = df.select(F.col("doc_id").alias("id"), F.lit(0).alias("h"), "text"), 16
    crowded = repeated_passages.crowded_grams(given, buckets)
    assert len(crowded)
    shipped = given.mapInArrow(repeated_passages._shipped(buckets, 1 << 20, crowded), "bucket int, parts array<binary>").collect()
    sizes = np.zeros(buckets)
    for row in shipped:
        sizes[row.bucket] += len(repeated_passages._opened(bytes(row.parts[0]), np.uint8))
    assert sizes.max() < 3 * np.median(sizes)
    want = {tuple(r) for r in repeated_passages.repeated_passages(df).collect()}
    rows = [[bytes(b) for b in row.parts] for row in given.mapInArrow(repeated_passages._shipped(1, 1 << 20), "bucket int, parts array<binary>").collect()]
    covered = lambda: {(i, c) for (i, _), (a, n) in zip(*(x.T.tolist() for x in repeated_passages._reduce(rows))) for c in range(a, a + n)}
    whole = covered()
    monkeypatch.setattr(repeated_passages, "SORTED", 1 << 14)
    monkeypatch.setattr(repeated_passages, "HASHED", 1 << 12)
    assert covered() == whole
    assert {r[0]: r[2] for r in want} == {i: sum(1 for j, _ in whole if j == i) for i, _ in docs}


def test_near_duplicates(spark):
    base = [f"t{i}" for i in range(120)]
    more = [(5000 + k, " ".join(base[:k] + ["edit", str(k)] + base[k + 2 :])) for k in range(0, 100, 4)] + [(6000, " ".join(base)), (6001, "lone"), (6002, "lone")]
    docs = texts(spark, SMALL) + more
    want = plain.near_classes(docs)
    got = {r.doc_id: r.class_id for r in near_duplicates.classes(spark.createDataFrame(docs, "doc_id bigint, text string")).collect()}
    assert got == want


def test_near_duplicates_with_repeated_lines(spark):
    """Pairs with a plain Jaccard index over 0.8, of which one text repeats a line 1000 times."""
    docs = []
    for k in range(40):
        base, line = " ".join(f"p{k}x{i}" for i in range(64)), " ".join(f"l{k}x{i}" for i in range(10))
        docs += [(2 * k, base + (f" {line}" if k % 2 else "")), (2 * k + 1, base + f" {line}" * 1000)]
    bands = {r.key: set(r.bands) for r in near_duplicates.sketches(spark.createDataFrame(docs, "doc_id bigint, text string")).collect()}
    words = {i: t.split() for i, t in docs}
    sets = {i: {tuple(w[j : j + 5]) for j in range(len(w) - 4)} for i, w in words.items()}
    assert all(len(sets[i] & sets[i + 1]) >= 0.8 * len(sets[i] | sets[i + 1]) for i in range(0, 80, 2))
    assert [i for i in range(0, 80, 2) if not bands[i] & bands[i + 1]] == []


def test_near_duplicates_in_large_buckets(spark):
    """Copies of one text that are like it but not like each other, other texts with a passage of it, ids as strings; cells of 4 documents, so buckets are parted and dealt to cells."""
    import random

    r = random.Random(5)
    base = [f"b{i}" for i in range(100)]
    docs = [("k000", " ".join(base))]
    for k in range(1, 60):
        own = list(base)
        for _ in range(k % 5):
            own[r.randrange(100)] = f"e{k}x{r.randrange(10)}"
        docs.append((f"k{k:03}", " ".join(own) + (" " + " ".join(base[:20]) * (k % 3) if k % 7 == 0 else "")))
    docs += [(f"m{k:03}", " ".join(base[:70] + [f"m{k}x{i}" for i in range(30 if k % 2 else 8)])) for k in range(12)]
    words = {i: t.split() for i, t in docs}
    counts = {i: collections.Counter(tuple(w[j : j + 5]) for j in range(len(w) - 4)) for i, w in words.items()}
    weight = {i: {x: 1 + math.log(n) for x, n in c.items()} for i, c in counts.items()}

    def index(a, b):
        plain = len(a.keys() & b.keys()) / len(a.keys() | b.keys())
        every = a.keys() | b.keys()
        return max(plain, sum(1 / sum(max(a.get(j, 0) / a[i], b.get(j, 0) / b[i]) for j in every) for i in a.keys() & b.keys()))

    from tests.helpers import union_find

    ids = [i for i, _ in docs]
    links = [(a, b) for k, a in enumerate(ids) for b in ids[:k] if index(weight[a], weight[b]) >= 0.8]
    got = {r.doc_id: r.class_id for r in near_duplicates.classes(spark.createDataFrame(docs, "doc_id string, text string"), cell=4).collect()}
    assert got == union_find(ids, links)


def test_probability_jaccard():
    import numpy as np

    a, b = np.array([1, 3, 5, 9], np.uint64), np.array([3, 4, 5], np.uint64)
    x, y = np.array([1.0, 2.0, 4.0, 0.5]), np.array([3.0, 1.0, 1.0])
    wa, wb = dict(zip(a.tolist(), x)), dict(zip(b.tolist(), y))
    want = sum(1 / sum(max(wa.get(j, 0) / wa[i], wb.get(j, 0) / wb[i]) for j in {*wa, *wb}) for i in (3, 5))
    assert abs(near_duplicates.probability_jaccard(a, x, b, y) - want) < 1e-12


def test_signatures_estimate():
    import numpy as np

    from minlabel.llm import text_arrays as ta

    grams = ta.mixed(np.concatenate((np.arange(250), np.arange(50, 300))).astype(np.uint64))
    s = near_duplicates.signatures(np.repeat([0, 1], 250), grams, np.ones(500), 2, 3000)
    assert abs((s[0] == s[1]).mean() - 200 / 300) < 0.04


def test_language(spark):
    docs = table(spark, SMALL, "documents")
    rows = language_id.languages(docs, language_id.fit(docs)).join(docs.select("doc_id", "lang"), "doc_id").where("held_out and lang is not null").collect()
    assert sum(r.lang == r.lang_pred for r in rows) / len(rows) > 0.98 and all(0 <= r.score <= 1 for r in rows)


def test_language_odd(odd):
    got = {r.doc_id: r.lang_pred for r in language_id.languages(odd, language_id.fit(odd)).collect()}
    assert got[1] == got[2] == got[6] == got[9] == "und"


def plain_parse(sample: bytes, text: bytes) -> int:
    """Phrases of the greedy parse, by looking for ever longer strings in the sample."""
    n = at = 0
    while at < len(text):
        size = 1
        while at + size < len(text) and text[at : at + size + 1] in sample:
            size += 1
        n, at = n + 1, at + size
    return n


def test_parse_of_whole_texts():
    """Texts over many blocks, verbatim passages across block borders and unknown letters, against a plain parse."""
    import random

    import numpy as np

    r = random.Random(3)
    words = [bytes(r.choice(b"abcdefgh") for _ in range(r.randrange(1, 7))) for _ in range(60)]
    samples = {"a": b" ".join(r.choice(words[:40]) for _ in range(900)), "b": b" ".join(r.choice(words[20:]) for _ in range(900))}
    model = language_id.Model(samples)
    texts = [samples["a"][100:2700], b"", b"z", samples["b"][5:1100] + b"qqq" + samples["b"][7:3000], b" ".join(r.choice(words) for _ in range(1500)), samples["a"][:512], samples["a"][:513]]
    data, offsets = np.frombuffer(b"".join(texts), np.uint8), np.cumsum([0] + [len(t) for t in texts])
    got = model.phrases(data, offsets)
    fold = lambda t: model.classes[np.frombuffer(t, np.uint8)].tobytes()
    assert got.tolist() == [[plain_parse(fold(samples[k]), fold(t)) for k in model.languages] for t in texts]
    assert got[0, 0] == 1


def test_parse_is_greedy():
    text, sample = "abcabxab", "abcab"
    auto = language_id.SuffixAutomaton(list(sample.encode()))
    assert all(_walks(auto, sample[i:j]) for i in range(5) for j in range(i, 6)) and not _walks(auto, "ba")
    m = language_id.Model({"l": sample.encode()})
    import numpy as np

    data = np.frombuffer(text.encode(), np.uint8)
    assert m.phrases(data, np.array([0, len(data)]))[0, 0] == 3  # abcab, x, ab


def _walks(auto, s):
    k = 0
    for c in s.encode():
        if c not in auto.moves[k]:
            return False
        k = auto.moves[k][c]
    return True


@pytest.mark.parametrize("depth,many,chars", [(3, 40, 300), (context_trees.DEPTH, 16, None)])
def test_scores(spark, depth, many, chars):
    docs = [(i, t[:chars]) for i, t in texts(spark, SMOKE)[:many]] + [(500, ""), (501, None)]
    got = {r.doc_id: r for r in context_trees.scores(spark.createDataFrame(docs, "doc_id bigint, text string"), depth=depth).collect()}
    low = lambda t: (t or "").encode().translate(bytes(c + 32 if 65 <= c < 91 else c for c in range(256)))
    tokens = lambda t: [*re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOW)), None]
    train = [t for i, t in docs if zlib.crc32(str(i).encode()) % 7 != 2]
    counts = collections.Counter(x for t in train for x in tokens(t))
    n, v = sum(counts.values()), len(counts)
    want = tree_scores([low(t) for t in train], depth, [low(t) for _, t in docs])
    for (i, t), score in zip(docs, want):
        assert math.isclose(got[i].score, score, rel_tol=1e-5, abs_tol=1e-6)
        assert got[i].n_tokens == len(tokens(t)) and got[i].n_known == sum(counts[x] > 0 for x in tokens(t)) and got[i].train_tokens == n
        assert math.isclose(got[i].base_score, sum(math.log10((counts[x] + 1) / (n + v + 1)) for x in tokens(t)), rel_tol=1e-9)


def tree_scores(train, depth, given):
    """Context-tree weighting node by node."""
    nodes, children = {}, collections.defaultdict(list)
    for t in train:
        p = b"\0" * depth + t
        for k in range(depth, len(p)):
            for d in range(depth + 1):
                at = 1
                for j in range(7, -1, -1):
                    nodes.setdefault((p[k - d : k], at), [0, 0])[p[k] >> j & 1] += 1
                    at = at * 2 + (p[k] >> j & 1)
    for c, at in nodes:
        if c:
            children[c[1:], at].append((c, at))
    estimate = lambda a, b: math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)
    weight = {}
    for key in sorted(nodes, key=lambda k: -len(k[0])):
        own = estimate(*nodes[key])
        below = sum(weight[c] for c in children[key])
        weight[key] = own if len(key[0]) == depth else max(own, below) + math.log1p(math.exp(-abs(own - below))) - math.log(2)

    def chance(context, at, bit, d):
        key = context[depth - d :], at
        pair = nodes.get(key, [0, 0])
        kt = (pair[bit] + 0.5) / (sum(pair) + 1)
        if d == depth:
            return kt
        share = math.exp(estimate(*pair) - math.log(2) - weight[key]) if key in nodes else 0.5
        return share * kt + (1 - share) * chance(context, at, bit, d + 1)

    out = []
    for t in given:
        p, total = b"\0" * depth + t, 0.0
        for k in range(depth, len(p)):
            at = 1
            for j in range(7, -1, -1):
                total += math.log10(chance(p[k - depth : k], at, p[k] >> j & 1, 0))
                at = at * 2 + (p[k] >> j & 1)
        out.append(total)
    return out


def test_reply_tree(spark):
    rows = [("t", 1, None, "user", "q", 1.0), ("t", 2, 1, "assistant", "bad & <b>", 0.0), ("t", 3, 1, "assistant", "good", 5.0), ("t", 4, 3, "user", None, 1.0), ("t", 5, 3, None, "x", 1.0), ("u", 9, 77, "user", "orphan", None), ("c", 1, 2, "user", "cycle", 0.0), ("c", 2, 1, "user", "cycle", 0.0)]
    m = spark.createDataFrame(rows, "tree string, node bigint, parent bigint, role string, text string, score double")
    got = {(r.tree, r.leaf): chat_formatting.parsed(r.conversation) for r in chat_formatting.conversations(m, 3).collect()}
    assert got == {("t", 4): [("user", "q"), ("assistant", "good"), ("user", "")], ("t", 5): [("user", "q"), ("assistant", "good"), ("", "x")], ("t", 2): [("user", "q"), ("assistant", "bad & <b>")], ("u", 9): [("user", "orphan")]}
    assert {(r.tree, r.leaf) for r in chat_formatting.conversations(m).collect()} == {("t", 4), ("u", 9)}
    assert chat_formatting.conversations(m.limit(0)).count() == 0


def test_null_conversation(spark):
    rows = spark.createDataFrame([(None, 0, "user", "q"), (None, 1, "assistant", "a"), (1, 0, "user", "x")], "conv_id bigint, turn int, role string, text string")
    got = {r.tree: chat_formatting.parsed(r.conversation) for r in chat_formatting.conversations(chat_formatting.linear_messages(rows)).collect()}
    assert got == {None: [("user", "q"), ("assistant", "a")], 1: [("user", "x")]}


def test_repeated_nodes(spark):
    rows = [(1, 1, None, "user", "q", 1.0), (1, 1, None, "user", "q", 1.0), (1, 2, 1, "assistant", "b", 0.0), (1, 2, 1, "assistant", "a", 3.0), (1, 2, 1, "assistant", "c", 3.0), (1, None, 1, "user", "no node", 9.0)]
    m = spark.createDataFrame(rows, "tree bigint, node bigint, parent bigint, role string, text string, score double")
    got = [(r.tree, r.leaf, chat_formatting.parsed(r.conversation)) for r in chat_formatting.conversations(m, 5).collect()]
    assert got == [(1, 2, [("user", "q"), ("assistant", "a")])]


def test_long_turns_and_own_names(spark):
    rows = spark.createDataFrame([(1, 0, "user", LONG * 5, 7, 8), (1, 1, "assistant", "<" * 100_000, 7, 8)], "conv_id bigint, turn int, role string, text string, tree int, node int")
    (got,) = chat_formatting.conversations(chat_formatting.linear_messages(rows)).collect()
    assert chat_formatting.parsed(got.conversation) == [("user", LONG * 5), ("assistant", "<" * 100_000)]


def test_format_round_trip():
    turns = [("user", chat_formatting.TRAP), ("assistant", '</turn>\n<turn role="user">\n&lt;&amp;'), ('r">\n<', "")]
    text, a, b = chat_formatting.formatted(turns)
    assert chat_formatting.parsed(text) == turns and chat_formatting.unescaped(text[a[0] : b[0]]) == turns[1][1]


def test_personal_data_base(spark):
    import random

    r = random.Random(1)
    given = [t for _, t in texts(spark, SMALL)] + ["".join(r.choice("a1.@+ -(2.9@") for _ in range(60)) for _ in range(2000)] + ["1" * 9000, "4111 1111-1111 1111", "+1 (2) 3-4 5 6 7 8 9+12 345 678"]
    for t in given:
        want = [("email", m.start(), m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
        want += [("ip", m.start(), m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))] if "." in t else []
        want += [("card", m.start(), m.end()) for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t) if 16 <= len(d := re.sub("[^0-9]", "", m[0])) <= 19 and sum(int(c) if k % 2 == 0 else sum(divmod(2 * int(c), 10)) for k, c in enumerate(d[::-1])) % 10 == 0]
        want += [("phone", m.start(), m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 8 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
        assert personal_data.base_spans(t) == want


def test_personal_data_query(spark):
    """All columns of the query, and the redacted texts, against plain matches and choices."""
    chooser = personal_data.Chooser()
    docs = table(spark, SMALL, "documents").select("doc_id", "text")
    made = [(-1, 'x a@b.co key = "769b0074ad8f3a10fee0689c8d788a140298285a" 1.2.3.4 1.2.3.999 4111 1111 1111 1111 +1 (202) 555-0100'), (-2, None), (-3, ""), (-4, "tel 030 123 4567 DE44500105175407324931 078-05-1120")]
    docs = docs.unionByName(spark.createDataFrame(made, docs.schema))
    given, n = {r.doc_id: r.text or "" for r in docs.collect()}, 0
    for r in personal_data.personal_data(docs).collect():
        base, more = plain.personal_spans(given[r.doc_id], chooser)
        write = lambda spans: ",".join(":".join(map(str, x)) for x in spans)
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == kind for k, _, _ in base) for kind in ("email", "ip", "card", "phone")]
        assert r.base_sha256 == hashlib.sha256(write(base).encode()).hexdigest() and r.spans == write(base + more) and r.n_more == len(more)
        n += 1
    assert n == len(given)
    assert all((r.text or "") == plain.redacted(given[r.doc_id], chooser) for r in personal_data.redacted(docs).collect())


def test_personal_data_choice():
    import numpy as np

    chooser = personal_data.Chooser()
    x, y, kinds = personal_data.training_spans(1500, 99)
    p = np.array([1 / (1 + math.exp(-(chooser.a * chooser.trees.score(row) + chooser.b))) for row in x.tolist()])
    chosen = p >= np.array([chooser.thresholds[k] for k in kinds])
    assert y[chosen].mean() > 0.95 and chosen[y == 1].mean() > 0.95
    text = 'mail a@b.co, token = "769b0074ad8f3a10fee0689c8d788a140298285a" and nothing'
    assert personal_data.redacted_text(text, chooser) == 'mail [EMAIL], token = "[SECRET]" and nothing'


def test_mixture_shares(spark):
    docs = table(spark, "/root/testdata/sf0.1", "documents")
    rows = mixing.mixed(docs, scale=2.0).groupBy("source").agg(F.sum(F.octet_length("text")).alias("n")).collect()
    total = sum(r.n for r in rows)
    assert all(abs(r.n / total - mixing.WEIGHTS[r.source]) < 0.02 for r in rows if r.source in mixing.WEIGHTS)
    out = mixing.mixed(docs.limit(50), {"src0": 0.5})
    assert "Python" not in out._jdf.queryExecution().toString()


def test_mixture_without_ids(spark):
    """Rows without ids, or with one id, are drawn and placed by their texts too, so no partition gets them all."""
    n = 4000
    for key in ("null", "7"):
        docs = spark.range(n).selectExpr(f"cast({key} as bigint) as doc_id", "concat('text ', id) as text", "'src0' as source")
        rows = mixing.mixed(docs, {"src0": 1.0}, 2.0).withColumn("part", F.spark_partition_id()).groupBy("part").agg(F.count("*").alias("n"), F.countDistinct("text").alias("texts")).collect()
        total = sum(r.n for r in rows)
        assert abs(total - 2 * n) < 0.1 * n and len(rows) > 1 and max(r.n for r in rows) < 1.2 * total / len(rows)
    alike = mixing.mixed(docs.limit(1).union(docs.limit(1)), {"src0": 1.0}, 3.0).groupBy("copy").count()
    assert {r["count"] for r in alike.collect()} <= {2}


def test_columns_named_like_our_own(spark, labels):
    """Input columns that begin as the operators' own do come through with their values."""
    rows = [(i, f"{LONG[i * 7 : i * 7 + 900]} {LONG[:400]}", "en", "src0", i, -i, f"v{i}") for i in range(30)]
    names = ("ml_group", "ML_H", "ml_n_words")
    docs = spark.createDataFrame(rows, f"doc_id bigint, text string, lang string, source string, {names[0]} int, {names[1]} int, {names[2]} string")
    for out in (quality_rules.keep_good(docs, labels), repeated_passages.without_repeats(docs), mixing.mixed(docs, {"src0": 1.0}, 5.0)):
        assert out.columns[: len(docs.columns)] == docs.columns
        got = {(r.doc_id, r[names[0]], r[names[1]], r[names[2]]) for r in out.collect()}
        assert got and got <= {(i, i, -i, f"v{i}") for i in range(30)}
    assert len({r.doc_id for r in repeated_passages.without_repeats(docs).collect()}) == 30
