import re

import duckdb
from pyspark.sql import functions as F

import corpus_pipeline
from bucketseed.llm import factorization, identifiers, poisson_mix
from bucketseed.tables import load

SF = "/root/testdata/sf0.001"


def test_stages_pass_on_what_they_keep(spark):
    docs = load(spark, SF, "documents")
    columns, rows = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF).cache()
        if name != "mixing":
            assert docs.columns == columns and docs.count() <= rows
            rows = docs.count()
    assert docs.count() > 0 and set(columns) <= set(docs.columns)


def test_run(spark):
    assert corpus_pipeline.run(spark, SF).count() > 0


def test_stages_on_odd_rows(spark):
    rows = [(None, None, None, None, None), (1, "", "en", "a", 0), (2, "word " * 5000, "en", None, 25000), (2, "word " * 5000, "en", None, 25000)]
    docs = spark.createDataFrame(rows, load(spark, SF, "documents").schema)
    for _, stage in corpus_pipeline.STAGES[1:]:
        stage(spark, docs, SF).collect()
    assert corpus_pipeline.deduplication(spark, docs, SF).count() == 3
    none = docs.filter("doc_id = -1")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, SF).count() == 0


LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def kept_ids(stage, spark, docs):
    return sorted(r["doc_id"] for r in stage(spark, docs, SF).select("doc_id").collect())


def test_stages_are_the_definition(spark):
    docs = load(spark, SF, "documents")
    texts = {r["doc_id"]: r["text"] or "" for r in docs.select("doc_id", "text").collect()}

    # toxicity: the model's score of each whole text decides
    model = factorization.fit(docs, load(spark, SF, "labels"), F.lit(True))
    scores = {r["doc_id"]: r["score"] for r in factorization.score(docs, model).collect()}
    assert kept_ids(corpus_pipeline.toxicity, spark, docs) == sorted(i for i, s in scores.items() if s < 0.5)

    # deduplication: all pairs, then the least id that each document reaches
    sets = {}
    for i, t in texts.items():
        w = re.findall(r"[^\x20\x09-\x0D]+", t.translate(LOW))
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(len(w) - 4, 1))} if w else set()
    least = {i: i for i in texts}
    ids = sorted(texts)
    links = [(a, b) for a in ids for b in ids if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    for _ in ids:
        for a, b in links:
            least[a] = least[b] = min(least[a], least[b])
    assert links and kept_ids(corpus_pipeline.deduplication, spark, docs) == sorted(i for i in ids if least[i] == i)

    # decontamination: every window of every item, looked up in every document
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOW))
    windows = set()
    for r in load(spark, SF, "benchmark").collect():
        w = words(r["text"])
        n = min(len(w), 10)
        windows |= {tuple(w[k : k + n]) for k in range(len(w) - n + 1)} if n else set()
    clean = []
    for i, t in texts.items():
        w = words(t)
        if not any(tuple(w[k : k + n]) in windows for n in {len(x) for x in windows} for k in range(len(w) - n + 1)):
            clean.append(i)
    assert len(clean) < len(texts) and kept_ids(corpus_pipeline.decontamination, spark, docs) == sorted(clean)

    # personal data: base spans, as no pattern of this table is confident
    assert not identifiers.fit(docs).kinds
    out = {r["doc_id"]: (r["text"], r["n_chars"]) for r in corpus_pipeline.personal_data(spark, docs, SF).collect()}
    for i, t in texts.items():
        spans = [(identifiers.KINDS[k], s, e) for s, e, k in identifiers.base_spans(t)[0]]
        want = identifiers.masked(t, spans)
        assert (out[i][0] or "") == want and (not spans or out[i][1] == len(want))

    # mixing: the distribution inverted in SQL
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    want = sorted(con.execute(f"SELECT doc_id, copy FROM ({poisson_mix.ORACLE})").fetchall())
    assert sorted((r["doc_id"], r["copy"]) for r in corpus_pipeline.mixing(spark, docs, SF).collect()) == want
