"""The pipeline's stages against brute force, one after the other."""

from test_dedup import brute_lines, check_near
from test_text import _check_pieces

import corpus_pipeline
from cutfield.llm import passage_quality, secret_scan
from cutfield.llm.queries import ORACLE_SQL, QUERIES


def test_names():
    assert {f"op{n}" for n in range(1, 11)} == {q.split("_")[0] for q in QUERIES} and set(ORACLE_SQL) <= set(QUERIES)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality classifier", "line dedup", "simhash near-dedup", "secret scans", "packing"]


def test_stages(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    first, second, third, fourth, last = (f for _, f in corpus_pipeline.STAGES)
    a = first(spark, docs, data)
    model = passage_quality.fit(docs, spark.read.parquet(f"{data}/labels.parquet"))
    good = {x["doc_id"] for x in passage_quality.quality_scores(docs, model).where("predicted = 1").collect()}
    assert a.columns == docs.columns and {x["doc_id"] for x in a.collect()} == good
    b = second(spark, a, data)
    texts = [(x["doc_id"], x["text"]) for x in a.collect()]
    want = {i: t for i, _, _, t in brute_lines(texts)}
    got = {x["doc_id"]: x for x in b.collect()}
    assert b.columns == docs.columns and {i: x["text"] for i, x in got.items()} == want
    assert all(x["n_chars"] == len(x["text"]) for x in got.values())
    c = third(spark, b, data)
    kept = {x["doc_id"] for x in c.collect()}
    check_near(want, kept)
    assert c.columns == docs.columns
    d = fourth(spark, c, data)
    assert d.columns == docs.columns and d.count() == c.count()
    spans = {x["doc_id"]: x["spans"] for x in secret_scan.scan(c).collect()}
    for x in d.collect():
        text, at, out = want[x["doc_id"]], 0, ""
        for s in spans[x["doc_id"]]:
            if s["start"] >= at:
                out += text[at : s["start"]] + "[SECRET]"
            at = max(at, s["end"])
        assert x["text"] == out + text[at:]
    _check_pieces(last(spark, d, data).collect(), [(x["doc_id"], x["text"]) for x in d.collect()])


def test_run(spark, data):
    assert corpus_pipeline.run(spark, data).count() > 0


def test_stages_on_odd_tables(spark, data):
    """Null, empty, repeated and very long texts, a null id, extra columns, and an empty table, through every stage."""
    long = " ".join(f"word{i % 997}" for i in range(20_000))
    rows = [(1, "a b c"), (2, None), (3, ""), (4, "x\n" * 9), (5, long), (5, long), (None, "no id here"), (6, "token=abcdef123456 end")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "'en' AS lang", "'s' AS source", "cast(length(text) AS bigint) AS n_chars", "1 AS body", "2 AS c0", "3 AS label")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        for frame in (df, df.limit(0)):
            out = stage(spark, frame, data)
            n = out.count()
            assert out.columns == df.columns and n <= frame.count(), name
    assert corpus_pipeline.STAGES[-1][1](spark, df, data).select("doc_id").distinct().count() == 7
    assert corpus_pipeline.STAGES[-1][1](spark, df.limit(0), data).count() == 0
