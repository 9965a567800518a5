"""The pipeline against plain Python stages; rules and mixture, which have SQL, against that."""

import collections

import corpus_pipeline
import duckdb
import pandas as pd

from minlabel.llm import mixing, personal_data, quality_rules
from minlabel.session import table
from tests.conftest import SMALL
from tests.llm import plain


def test_pipeline(spark):
    docs, labels, bench = (table(spark, SMALL, t).toPandas() for t in ("documents", "labels", "benchmark"))
    con = duckdb.connect()
    con.register("documents", docs)
    con.register("labels", labels)
    good = {x[0] for x in con.sql(f"select doc_id from ({quality_rules.oracle()}) where kept").fetchall()}
    rows = {r.doc_id: r for r in docs.itertuples() if r.doc_id in good}
    classes = plain.near_classes([(i, r.text) for i, r in rows.items()])
    rows = {i: r for i, r in rows.items() if classes[i] == i}
    judged = plain.contamination([(i, r.text) for i, r in rows.items()], [(r.item_id, r.text) for r in bench.itertuples()])
    chooser = personal_data.Chooser()
    left = [(i, text := plain.redacted(r.text, chooser), r.lang, r.source, len(text)) for i, r in rows.items() if not judged[i][-1]]
    assert 0 < len(left) < len(classes) < len(docs) and any(t != rows[i].text for i, t, *_ in left)
    con.register("clean", pd.DataFrame(left, columns=["doc_id", "text", "lang", "source", "n_chars"]))
    want = con.sql(mixing.oracle("clean"))
    got = corpus_pipeline.run(spark, SMALL)
    at = [want.columns.index(c) for c in got.columns]
    assert collections.Counter(map(tuple, got.collect())) == collections.Counter(tuple(r[k] for k in at) for r in want.fetchall())
    assert [k for k, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_dedup", "decontamination", "personal_data", "mixing"]


def test_stages_keep_columns(spark):
    docs = table(spark, SMALL, "documents").limit(60)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, SMALL).columns == docs.columns
