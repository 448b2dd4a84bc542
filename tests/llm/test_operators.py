"""Corpus operators against brute force, and on nulls, empty texts, repeats and clashing columns."""

import hashlib
import math
import re
import zlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from bucketseed.llm import (
    context_tree,
    factorization,
    identifiers,
    line_frequency,
    nbsvm,
    near_duplicates,
    poisson_mix,
    url_templates,
    winnowing,
    wordpiece,
)
from bucketseed.llm.components import components
from bucketseed.llm.hashing import shingle_hashes, word_hashes
from bucketseed.llm.labelled import crc_fold
from bucketseed.tables import load

SF = "/root/testdata/sf0.001"
PLAIN = re.compile(r"[^\x20\x09-\x0D]+")
LONG = "lorem ipsum dolor sit amet consectetur " * 3000
ODD = [
    (1, None, None, "src0"), (2, "", "en", None), (3, "one", "en", "src0"), (3, "one", "en", "src0"), (None, "a b c d e f", "en", "src1"),
    (5, LONG, "en", "src1"), (6, "\x0b\t\n ", "de", "src1"), (7, "Ünïcode wörds ß 漢字 \U0001f600 here again and again", "de", "src1"), (8, None, None, None),
]


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(*r, "x", 0.5, 1) for r in ODD]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, kept string, rate double, n_words int").repartition(3)


@pytest.fixture(scope="module")
def empty(odd):
    return odd.filter("doc_id = -1")


@pytest.fixture(scope="module")
def docs(spark):
    return load(spark, SF, "documents").cache()


@pytest.fixture(scope="module")
def texts(docs):
    return {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}


@pytest.mark.parametrize("module", [line_frequency, winnowing, poisson_mix, near_duplicates])
def test_query_equals_sql(spark, module):
    con = duckdb.connect()
    for name in ("documents", "benchmark"):
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{SF}/{name}.parquet'")
    a, b = module.query(spark, SF).toPandas(), con.execute(module.ORACLE).df()
    cols = sorted(a.columns)
    assert cols == sorted(b.columns)
    rows = lambda df: sorted(map(str, df[cols].itertuples(index=False, name=None)))
    assert rows(a) == rows(b)


def test_word_hashes_are_of_words():
    given = ["one two  one", "", "TWO\tthree", "éa é"]
    data = np.frombuffer("".join(given).encode(), np.uint8)
    offs = np.cumsum([0] + [len(t.encode()) for t in given])
    h, first = word_hashes(data, offs)
    assert first.tolist() == [0, 3, 3, 5, 7]
    assert h[0] == h[2] and h[1] == h[3] and len(set(h.tolist())) == 5
    g, at = shingle_hashes(h, first, 2)
    assert at.tolist() == [0, 2, 2, 3, 4]


def test_lines(spark, odd, empty):
    got = line_frequency.line_frequency(odd, cleaned=True).collect()
    assert len(got) == len(ODD)
    assert all(not r["kept"] for r in got if r["doc_id"] in (1, 2, 6, 8))
    assert line_frequency.line_frequency(empty).count() == 0
    text = "shared boiler plate line of this host\n"
    letters = lambda n: "".join(chr(97 + int(c)) for c in str(n))
    rows = [(i, text + " ".join(letters(i * 100 + j) for j in range(40)), "h") for i in range(30)] + [(99, text * 3 + "few words " * 2, "h")]
    table = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    out = {r["doc_id"]: r for r in line_frequency.line_frequency(table, cleaned=True, min_left=0.5).collect()}
    assert out[3]["kept"] and "boiler" not in out[3]["cleaned_text"]
    copied = spark.createDataFrame([(i, "one line that is in every copy\n" + "word " * 30, "h") for i in range(30)], "doc_id bigint, text string, source string")
    assert line_frequency.line_frequency(copied).agg(F.sum("words_left")).first()[0] == 0
    assert line_frequency.line_frequency(copied, copies="once").filter("words_left = n_words").count() == 30
    assert not out[99]["kept"] and out[99]["words_left"] == 4


def test_base_identifiers(docs, texts):
    for text in list(texts.values()) + ["a@b.c@d.e x@y", "1.2.3.4.5.6.7.8 300.1.1.1", "+1 (2) 3-4.5 6 7 8 9 0", "4111 1111 1111 1111", "a" * 50_000, "1" * 50_000, "@" * 1000]:
        good, _ = identifiers.base_spans(text)
        want = [(m.start(), m.end(), 0) for m in re.finditer(r"[A-Za-z0-9._%+-]{1,400}@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)] if len(text) < 50_000 else []
        assert [g for g in good if g[2] == 0] == want
        ips = [m for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text)] if len(text) < 50_000 else []
        assert [g[:2] for g in good if g[2] == 1] == [m.span() for m in ips if all(int(p) <= 255 for p in m.group().split("."))]


def test_bootstrap_finds_keys_by_context(spark, odd, empty):
    keys = [hashlib.sha1(str(i).encode()).hexdigest() for i in range(12)]
    rows = [(i, f"some prose word{i} token = \"{k}\" more of it") for i, k in enumerate(keys)]
    rows += [(50, 'yet another token = "ab12cd34ef56" here'), (51, "clean prose with build 20240101 in it")]
    table = spark.createDataFrame(rows, "doc_id bigint, text string")
    out = {r["doc_id"]: r for r in identifiers.find_identifiers(table, identifiers.fit(table), redacted=True).collect()}
    assert [s["kind"] for s in out[50]["spans"]] == ["secret"] and "ab12cd34ef56" not in out[50]["text"]
    assert out[51]["spans"] == [] and out[51]["text"] == rows[-1][1]
    got = identifiers.find_identifiers(odd, identifiers.fit(odd), redacted=True).collect()
    assert len(got) == len(ODD) and sorted(r["text"] or "" for r in got) == sorted(r[1] or "" for r in ODD)
    assert identifiers.find_identifiers(empty, identifiers.fit(empty)).count() == 0


def test_tokens_without_digits_join_by_slots(spark):
    keys = [hashlib.sha1(str(i).encode()).hexdigest() for i in range(12)]
    rows = [(i, f'some prose token = "{k}" more of it') for i, k in enumerate(keys)]
    rows += [(50, 'yet another token = "correcthorse" more'), (51, "a token = plain and more words"), (52, "x" * 5000 + ' token = "' + "9z" * 400 + '" more')]
    table = spark.createDataFrame(rows, "doc_id bigint, body string").withColumn("text", F.lit("another column"))
    model = identifiers.fit(table, "body")
    out = {r["doc_id"]: r for r in identifiers.find_identifiers(table, model, "body", redacted=True).collect()}
    assert out[50]["body"] == 'yet another token = "<secret>" more' and out[50]["text"] == "another column"
    assert out[51]["spans"] == [] and out[52]["body"].endswith('token = "<secret>" more')


def test_cards_and_phones_are_the_definition(texts):
    rng = np.random.default_rng(4)
    made = ["".join(rng.choice(list("0123456789 -+().ab"), 60)) for _ in range(3000)] + ["4111 1111 1111 1111 4111-1111-1111-1112", "+49 (30) 123-456.7 +1 2"]
    for text in made + list(texts.values()):
        good, _ = identifiers.base_spans(text)
        cards, phones = [], []
        for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
            digits = [int(c) for c in m.group() if c.isdigit()]
            double = sum(sum(divmod(2 * d, 10)) if i % 2 else d for i, d in enumerate(reversed(digits)))
            if 12 <= len(digits) <= 19 and double % 10 == 0:
                cards.append(m.span())
        for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text):
            if 9 <= sum(c.isdigit() for c in m.group()) <= 15:
                phones.append(m.span())
        assert [g[:2] for g in good if g[2] == 2] == cards and [g[:2] for g in good if g[2] == 3] == phones


def test_pattern_scores_are_the_definition(spark):
    keys = [hashlib.sha1(str(i).encode()).hexdigest() for i in range(30)]
    rows = [f'id {i} has token = "{k if i % 5 else k[:9]}" or key: {k[::-1] if i % 7 else "v" + k[:6]} and mail a{i}@b.cd end' for i, k in enumerate(keys)]
    rows += [f"and mail c{i}@d.ef end" for i in range(9)] + ["and mail x9.y8 end", "key: word1 and"]
    docs = spark.createDataFrame([(r,) for r in rows], "text string")
    edges, known = {}, set()
    for text in rows:
        for s, e, seed, _, keys, _, _ in identifiers.instances(text or "", *identifiers.base_spans(text or "")):
            value = (text[s:e]).lower()
            for k in keys:
                edges.setdefault(k, set()).add(value)
            if seed:
                known.add((value, seed))
    while True:
        sure = {}
        for k, values in edges.items():
            for kind in {c for _, c in known}:
                hits = sum((v, kind) in known for v in values)
                if hits >= 2 and hits / (len(values) + 0.2) >= 0.4:
                    sure[k, kind] = hits / (len(values) + 0.2)
        doubt = {}
        for (k, kind), x in sure.items():
            for v in edges[k]:
                doubt[v, kind] = doubt.get((v, kind), 1.0) * (1 - x)
        joined = {vk for vk, d in doubt.items() if 1 - d >= 0.6} - known
        if not joined:
            break
        known |= joined
    model = identifiers.fit(docs, support=2, confident=0.4, accepted=0.6)
    got = {(k, kind): s for k, (kind, s) in model.kinds.items() if k in edges}
    assert got == pytest.approx(sure) and sure


def brute_tree(train: list[bytes], depth: int, least: int):
    """log10 probabilities by the recursive definition over explicit counts."""
    counts: dict[bytes, dict[int, int]] = {}
    for t in train:
        line = b"\n" * depth + t + b"\xff"
        for i in range(depth, len(line)):
            for d in range(depth + 1):
                node = counts.setdefault(line[i - d : i], {})
                node[line[i]] = node.get(line[i], 0) + 1
    live = {c for c, n in counts.items() if sum(n.values()) >= least}

    def bits(n, prefix, level):
        zero = sum(v for x, v in n.items() if x >> (8 - level) == prefix and not (x >> (7 - level)) & 1)
        one = sum(v for x, v in n.items() if x >> (8 - level) == prefix and (x >> (7 - level)) & 1)
        return zero, one

    def kt(a, b):
        return math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)

    def rest(c):
        own = dict(counts[c])
        for child in live:
            if len(child) == len(c) + 1 and child[1:] == c:
                for x, v in counts[child].items():
                    own[x] -= v
        return own

    def weighted(c, prefix, level):
        own = kt(*bits(counts[c], prefix, level))
        if len(c) == depth:
            return own
        parts = kt(*bits(rest(c), prefix, level)) + sum(weighted(k, prefix, level) for k in live if len(k) == len(c) + 1 and k[1:] == c)
        return math.log(0.5) + np.logaddexp(own, parts)

    def one(c, ahead, prefix, level):
        a, b = bits(counts[c], prefix, level)
        p = (b + 0.5) / (a + b + 1)
        if len(c) == depth:
            return p
        own = kt(a, b)
        parts = kt(*bits(rest(c), prefix, level)) + sum(weighted(k, prefix, level) for k in live if len(k) == len(c) + 1 and k[1:] == c)
        share = math.exp(own - np.logaddexp(own, parts))
        deeper = ahead[-1:] + c
        if ahead and deeper in live:
            q = one(deeper, ahead[:-1], prefix, level)
        else:
            ra, rb = bits(rest(c), prefix, level)
            q = (rb + 0.5) / (ra + rb + 1)
        return share * p + (1 - share) * q

    def score(t):
        line, out = b"\n" * depth + t + b"\xff", 0.0
        for i in range(depth, len(line)):
            for level in range(8):
                p = one(b"", line[i - depth : i], line[i] >> (8 - level), level)
                out += math.log10(p if (line[i] >> (7 - level)) & 1 else 1 - p)
        return out

    return score


@pytest.mark.parametrize("depth, least, hot", [(1, 1, 100), (2, 3, 0), (3, 2, 5), (4, 1, 0), (4, 2, 100)])
def test_context_tree_is_the_definition(spark, depth, least, hot):
    train = ["abracadabra", "abba cab", "", "cabbage", "é è é"]
    rows = [(i, t) for i, t in enumerate(train)] + [(10, "abca"), (11, None), (12, "zé"), (13, "abracabbage")]
    table = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = context_tree.context_tree_scores(
        table, F.col("doc_id") >= 10, depth=depth, least=least, hot_share=3, part_tokens=2, hot_codes=hot, shard_codes=7
    ).collect()
    score = brute_tree([t.encode() for t in train], depth, least)
    assert len(got) == len(rows)
    for r in got:
        text = dict(rows)[r["doc_id"]] or ""
        assert r["score"] == pytest.approx(score(text.encode()), abs=1e-6)


def test_base_score(docs, texts):
    got = {r["doc_id"]: r for r in context_tree.context_tree_scores(docs, crc_fold("doc_id", 10) == 0, hot_share=500, part_tokens=20_000).collect()}
    held = {i for i in texts if zlib.crc32(str(i).encode()) % 10 == 0}
    low = lambda t: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t)
    words = {i: [*PLAIN.findall(low(t)), "\0"] for i, t in texts.items()}
    counts: dict[str, int] = {}
    for i, ws in words.items():
        for w in ws if i not in held else ():
            counts[w] = counts.get(w, 0) + 1
    n, v = sum(counts.values()), len(counts)
    for i, ws in words.items():
        want = sum(math.log10((counts.get(w, 0) + 0.1) / (n + 0.1 * (v + 1))) for w in ws)
        assert got[i]["base_score"] == pytest.approx(want, rel=1e-9)
        assert (got[i]["n_tokens"], got[i]["n_known"], got[i]["train_tokens"]) == (len(ws), sum(w in counts for w in ws), n)
        assert got[i]["held_out"] == (i in held)


def test_context_tree_edges(odd, empty):
    got = context_tree.context_tree_scores(odd, F.lit(False)).collect()
    assert len(got) == len(ODD) and all(r["n_tokens"] == 1 for r in got if r["doc_id"] in (1, 2, 6, 8))
    assert all(r["score"] == pytest.approx(8 * math.log10(0.5)) for r in context_tree.context_tree_scores(odd.filter("doc_id = 2"), F.lit(True)).collect())
    assert context_tree.context_tree_scores(empty, F.lit(False)).count() == 0


@pytest.mark.parametrize("module, label", [(nbsvm, "quality"), (factorization, "toxic")])
def test_classifiers(spark, odd, empty, module, label):
    out = module.query(spark, "/root/testdata/sf0.01").toPandas().merge(load(spark, "/root/testdata/sf0.01", "labels").toPandas(), on="doc_id")
    held = out[out.held_out]
    rank, pos = held.score.rank(), held[label] == 1
    auc = (rank[pos].sum() - pos.sum() * (pos.sum() + 1) / 2) / (pos.sum() * (~pos).sum())
    assert auc > 0.75 and (held.predicted == held[label]).mean() > 0.85
    labels = spark.createDataFrame([(3, 1), (5, 0), (7, None), (None, 1)], f"doc_id bigint, {label} int")
    model = module.fit(odd, labels, F.lit(True), label=label)
    assert module.score(odd, model).filter("score BETWEEN 0 AND 1").count() == len(ODD)
    none = module.fit(odd, labels.filter("doc_id = -1"), F.lit(True), label=label)
    assert {round(r["score"], 6) for r in module.score(odd, none).collect()} == {0.5}
    assert module.score(empty, model).count() == 0


def test_dual_descent_is_the_optimum():
    rng = np.random.default_rng(3)
    x = rng.integers(0, 2, (40, 12))
    y = np.where(x[:, 0] + x[:, 1] + rng.random(40) > 1.4, 1.0, -1.0)
    scale = rng.normal(0, 1, 12)
    rows = [np.flatnonzero(r) for r in x]
    w = nbsvm.dual_descent(rows, y, scale, 1.0, 400)
    dense = x * scale
    dense = dense / np.maximum(np.sqrt((dense**2).sum(1, keepdims=True)), 1e-12)
    share = (y > 0).mean()
    cost = np.where(y > 0, 0.5 / share, 0.5 / (1 - share))
    # brute force: projected gradient on the dual of the hinge loss with squared norm
    kernel, alpha = (dense @ dense.T) * np.outer(y, y), np.zeros(40)
    for _ in range(100_000):
        alpha = np.clip(alpha + 0.02 * (1 - kernel @ alpha), 0, cost)
    assert np.allclose(w, (alpha * y) @ dense, atol=1e-3)


def test_quality_scores_are_the_definition(spark, docs, texts):
    labels = load(spark, SF, "labels")
    model = nbsvm.fit(docs, labels, F.lit(True))
    got = {r["doc_id"]: r["score"] for r in nbsvm.score(docs, model).collect()}
    for i, text in list(texts.items())[:40]:
        raw = np.frombuffer((text or "").encode(), np.uint8)
        there = np.zeros(1 << nbsvm.BITS)
        for x in nbsvm.indicators(raw, np.array([0, len(raw)])):
            there[x] = 1
        scaled = there * np.sqrt(model.scale2.astype(float))
        margin = (model.weight * there).sum() / max(np.linalg.norm(scaled), 1e-300) if there.any() else 0.0
        assert got[i] == pytest.approx(1 / (1 + math.exp(-(model.slope * margin + model.shift))), abs=1e-4)
    named = docs.withColumn("doc_id", F.concat(F.lit("d"), "doc_id"))
    as_text = nbsvm.fit(named, labels.withColumn("doc_id", F.concat(F.lit("d"), "doc_id")), F.lit(True))
    assert nbsvm.score(named, as_text).count() == len(texts)


def test_pairs_of_terms_count_beyond_their_sum():
    rng = np.random.default_rng(1)
    x = rng.integers(0, 2, (600, 4)).astype(np.float32)
    y = np.where((x[:, 0] == 1) & (x[:, 1] == 1), 1.0, -1.0)
    bias, w, v = factorization.descend(x, y, 4, 400, 0.0)
    raw = bias + x @ w + 0.5 * (((x @ v) ** 2).sum(1) - x @ (v**2).sum(1))
    assert ((raw > 0) == (y > 0)).mean() == 1.0


def test_pure_interactions_are_learnt(spark):
    rng = np.random.default_rng(5)
    rows, labels = [], []
    for i in range(1200):
        one, two = rng.integers(0, 2, 2)
        words = [f"noise{k}" for k in rng.integers(0, 400, 20)] + ["insult"] * one + ["group"] * two
        rows.append((f"id{i}", " ".join(rng.permutation(words))))
        labels.append((f"id{i}", int(one != two)))
    table = spark.createDataFrame(rows, "doc_id string, text string")
    model = factorization.fit(table, spark.createDataFrame(labels, "doc_id string, toxic int"), F.col("doc_id") < "id8")
    held = {i: y for i, y in labels if i >= "id8"}
    got = {r["doc_id"]: r["score"] for r in factorization.score(table, model).collect()}
    assert np.mean([(got[i] >= 0.5) == y for i, y in held.items()]) > 0.95
    # brute force: every pair of the terms that a text holds
    index = {t: k for k, t in enumerate(model.terms.tolist())}
    for i, text in rows[:30]:
        raw = np.frombuffer(text.encode(), np.uint8)
        terms = sorted({index[t] for t in factorization.term_hashes(raw, np.array([0, len(raw)]))[0].tolist() if t in index})
        total = model.bias + sum(model.weight[a] for a in terms)
        total += sum(float(model.factors[a] @ model.factors[b]) for k, a in enumerate(terms) for b in terms[k + 1 :])
        assert got[i] == pytest.approx(1 / (1 + math.exp(-total)), abs=1e-6)


def test_winnowing_on_edges(spark, odd, empty):
    span = "alpha beta gamma delta epsilon zeta eta theta iota kappa"
    items = spark.createDataFrame([(1, span + " lambda mu"), (2, "Two Words"), (3, None), (4, "!!"), (2, "Two Words"), (5, "again and again")], "item_id bigint, text string")
    rows = [(1, f"x y {span.upper()} z"), (2, span[:-3]), (3, "two, words two"), (4, None), (4, "two words")]
    table = spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("n_hit", F.lit("clash"))
    out = {(r["doc_id"], r["n_words"]): (r["n_hit"], r["item_ids"]) for r in winnowing.decontaminate(table, items).collect()}
    assert out[(1, 13)] == (10, ["1"]) and out[(2, 10)] == (0, []) and out[(3, 3)] == (2, ["2"])
    assert out[(4, 0)] == (0, []) and out[(4, 2)] == (2, ["2"])
    same = spark.createDataFrame([(1, span + " other"), (1, "one two"), (1, None)], "doc_id bigint, text string")
    assert sorted(r["n_hit"] for r in winnowing.decontaminate(same, items).collect()) == [0, 0, 10]
    nameless = spark.createDataFrame([(None, span), (None, "one two"), (None, "three")], "doc_id string, text string")
    assert sorted(r["text"] for r in winnowing.uncontaminated(nameless, items).collect()) == ["one two", "three"]
    assert winnowing.decontaminate(odd, items).filter("contaminated").count() == 1
    assert winnowing.decontaminate(odd, items.filter("item_id = 99")).filter("contaminated").count() == 0
    assert winnowing.decontaminate(empty, items).count() == 0
    assert winnowing.uncontaminated(odd, items).count() == len(ODD) - 1


def test_poisson_counts(spark, odd, empty):
    rows = spark.range(20_000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 2 == 0, "a").otherwise("b").alias("source"))
    out = poisson_mix.replicate(rows, {"a": 3.0, "b": 1.0}, total=40_000, shuffled=False)
    n = {r["source"]: r["count"] for r in out.groupBy("source").count().collect()}
    assert abs(n["a"] - 30_000) < 900 and abs(n["b"] - 10_000) < 500
    large = poisson_mix.replicate(rows.filter("doc_id < 200"), {}, total=200 * 50, shuffled=False).groupBy("doc_id").count().toPandas()["count"]
    assert abs(large.mean() - 50) < 3 and 30 < large.var() < 75
    assert poisson_mix.replicate(rows, {"a": 1.0}, others=0.0).filter("source = 'b'").count() == 0
    assert poisson_mix.replicate(rows, {"a": 0.0}, others=0.0).count() == 0
    assert poisson_mix.replicate(rows, {"a": 0.0}).filter("source = 'a'").count() == 0
    with pytest.raises(ValueError):
        poisson_mix.replicate(rows, {"a": -1.0})
    got = poisson_mix.replicate(odd, {})
    assert set(odd.columns) <= set(got.columns) and got.count() >= 0
    assert poisson_mix.replicate(empty, {}).count() == 0
    key = [r["shuffle_key"] for r in poisson_mix.replicate(rows, {"a": 2.0}).collect()]
    assert key == sorted(key)


def test_mix_moves_whole_documents(spark, texts, monkeypatch):
    kept = []
    monkeypatch.setattr(poisson_mix, "staged", lambda df, name: kept.append(df.cache()) or kept[0], raising=False)
    out = poisson_mix.query(spark, SF).select("doc_id", "copy", "shuffle_key").collect()
    assert [r["shuffle_key"] for r in out] == sorted(r["shuffle_key"] for r in out)
    moved = kept[0].select("doc_id", "copy", "text", "lang", "n_chars").collect()
    assert sorted((r["doc_id"], r["copy"]) for r in moved) == sorted((r["doc_id"], r["copy"]) for r in out)
    assert all(r["text"] == texts[r["doc_id"]] for r in moved)


def test_near_duplicates_on_edges(spark, odd, empty):
    got = near_duplicates.near_duplicates(odd).collect()
    assert len(got) == len(ODD)
    assert all(r["kept"] and r["component_id"] == r["doc_id"] for r in got)
    assert near_duplicates.near_duplicates(empty).count() == 0
    assert near_duplicates.one_of_each(odd).count() == len(ODD) - 1
    base = [f"w{i}" for i in range(100)]
    rows = [(9, " ".join(base)), (4, " ".join(base).upper()), (7, " ".join(base[:90])), (8, " ".join(base[:60])), (2, "w1 w2"), (3, "w1 w2"), (1, "w2 w1")]
    # a chain: each neighbour is similar, the ends are not
    rows += [(100 + k, " ".join(f"c{i}" for i in range(k * 12, k * 12 + 104))) for k in range(6)]
    out = {r["doc_id"]: r["component_id"] for r in near_duplicates.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert (out[9], out[4], out[7], out[8], out[2], out[3], out[1]) == (4, 4, 4, 8, 2, 2, 1)
    assert {out[100 + k] for k in range(6)} == {100}


def test_near_duplicates_after_a_dry_round(spark):
    # two texts share a passage with a crowd and resemble each other alone: no centre of their buckets is alike
    passage = [f"t{i}" for i in range(120)]
    rows = [(i, " ".join(passage + [f"u{i}x{j}" for j in range(60)])) for i in range(1500)]
    rows += [(2000 + k, " ".join(passage + [f"v{k}x{j}" for j in range(8)])) for k in range(2)]
    out = {r["doc_id"]: r["component_id"] for r in near_duplicates.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert out.pop(2001) == out.pop(2000) == 2000
    assert all(i == c for i, c in out.items())


@pytest.mark.parametrize("others, families", [(150, 1), (300, 1), (150, 4)])
def test_crowded_buckets_lose_no_link(spark, others, families):
    rows = []
    for f in range(families):
        core = [f"f{f}c{i}" for i in range(1000)]
        rows += [(f * 10_000 + i, " ".join(core + [f"f{f}o{i}x{j}" for j in range(350)])) for i in range(others)]
        rows += [(f * 10_000 + 5000 + k, " ".join(core + [f"f{f}v{k}x{j}" for j in range(120)])) for k in range(2)]
    out = {r["doc_id"]: r["component_id"] for r in near_duplicates.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    for f in range(families):
        assert out.pop(f * 10_000 + 5001) == out.pop(f * 10_000 + 5000) == f * 10_000 + 5000
    assert all(i == c for i, c in out.items())


def test_near_duplicates_by_row_and_with_other_ids(spark):
    base = " ".join(f"w{i}" for i in range(50))
    rows = [(1, base), (1, "another text of its own kind here"), (None, base + " end"), (0, base), (None, "alone and without any id at all"), (None, None), (None, None)]
    table = spark.createDataFrame(rows, "doc_id bigint, text string")
    left = [(r["doc_id"], r["text"]) for r in near_duplicates.one_of_each(table).collect()]
    assert sorted(left, key=str) == sorted([(0, base), rows[1], rows[4], rows[5], rows[6]], key=str)
    named = spark.createDataFrame([("b", base), ("a", base + " x"), ("c", "nothing in common with these two"), (None, base)], "doc_id string, text string")
    got = {r["doc_id"]: (r["component_id"], r["kept"]) for r in near_duplicates.near_duplicates(named).collect()}
    assert got == {"b": ("a", False), "a": ("a", True), "c": ("c", True), None: (None, True)}


def test_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 102), (102, 101), (7, 7)], "a bigint, b bigint")
    got = {r["node"]: r["comp"] for r in components(links).collect()}
    assert {got[i] for i in range(41)} == {0} and {got[i] for i in (100, 101, 102)} == {100}
    assert components(links.filter("a = -1")).count() == 0


def test_wordpieces_are_greedy(odd, empty):
    vocabulary = wordpiece.read_vocabulary(wordpiece.VOCABULARY)
    auto, known = wordpiece.Automaton(vocabulary), set(vocabulary)

    def greedy(word):
        at = n = 0
        while at < len(word):
            end = next((e for e in range(len(word), at, -1) if word[at:e] in known), None)
            if end is None:
                return 1
            at, n = end, n + 1
        return n

    for word in ("hello", "antidisestablishmentarianism", "Ünïcode", "漢字", "zzzzqqqq", "x" * 300, "thereaanonhe"):
        raw = b" " + word.encode()
        assert auto.count(raw) == greedy(raw)
    small = wordpiece.Automaton([b"ab", b"a", b"bc"])
    assert [small.count(w) for w in (b"ab", b"abc", b"abbc", b"aab", b"")] == [1, 1, 2, 2, 0]
    got = wordpiece.token_counts(odd).collect()
    assert len(got) == len(ODD) and all(r["n_tokens"] == 0 for r in got if r["doc_id"] in (1, 2, 6, 8))
    assert wordpiece.token_counts(empty).count() == 0


def brute_verdicts(urls, rules, least=0.8, min_labelled=5, weight=5.0, critical=6.63, max_children=50, min_share=0.01):
    """Verdicts by the definition, over a tree of plain dictionaries."""
    parsed, rows = [], {}
    for u in urls:
        rest = (u or "").split("://", 1)[1] if "://" in (u or "") else ""
        host = re.match(r"[^/?#]*", rest).group()
        path = re.match(r"[^?#]*", rest[len(host) :]).group()
        host = host.lower()
        fits = [(len(h + p), h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        typed = tuple(re.sub(r"[0-9]+", "<n>", x) for x in path.split("/")[1:])
        parsed.append((host, typed, max(fits)[2] if fits else None))
        if host:
            rows.setdefault((host, typed), []).append(max(fits)[2] if fits else "free")
    count = lambda keys: [sum(rows[k].count(o) for k in keys) for o in ("block", "allow", "free")]
    found = {}

    def walk(keys, level, purity, support):
        b, a, _ = count(keys)
        if b + a:
            purity, support = (b + weight * purity) / (b + a + weight), b + a
        kids = {}
        for k in keys:
            if len(k[1]) > level:
                kids.setdefault(k[1][level], []).append(k)
            else:
                found[k] = (purity, support)
        shape = {c: frozenset(k[1][level + 1] if len(k[1]) > level + 1 else "" for k in ks) for c, ks in kids.items()}
        total, groups = sum(sum(count(ks)) for ks in kids.values()), {}
        for c, ks in kids.items():
            same = [d for d in kids if shape[d] == shape[c]]
            pb, pa, _ = count([k for d in same for k in kids[d]])
            cb, ca, cf = count(ks)
            share = pb / (pb + pa) if pb + pa else 0
            differs = (cb - (cb + ca) * share) ** 2 / ((cb + ca) * share * (1 - share)) if cb + ca and pb and pa else 0.0
            if len(kids) > max_children and cb + ca + cf < min_share * total:
                name = "*"
            else:
                name = ("*", shape[c]) if len(same) > 1 and differs <= critical else c
            groups.setdefault(name, []).extend(ks)
        for ks in groups.values():
            walk(ks, level + 1, purity, support)

    for host in {k[0] for k in rows}:
        walk([k for k in rows if k[0] == host], 0, 0.5, 0)
    return [
        v or ("block" if h and found[h, t][0] >= least and found[h, t][1] >= min_labelled else "allow") for h, t, v in parsed
    ]


def test_templates_are_the_definition(spark):
    rng = np.random.default_rng(9)
    rules = (("a.io", "/ads", "block"), ("a.io", "/ok", "allow"), ("b.io", "/x/ads", "block"), ("b.io", "/x/ok", "allow"), ("c.io", "/", "allow"), ("d.io", "/news", "block"))
    parts = ["ads", "adsense", "ok", "okay", "x", "y", "news", "1", "22", "p9"]
    urls = ["http://{}/{}".format(rng.choice(["a.io", "w.b.io", "c.io", "d.io"]), "/".join(rng.choice(parts, rng.integers(1, 6)))) for _ in range(900)]
    urls += [f"http://a.io/k{'abcdefgh'[i % 8]}{'qrstuvwx'[i // 8]}/z" for i in range(64)]
    table = spark.createDataFrame(list(enumerate(urls)), "page_id bigint, url string")
    out = {r["page_id"]: r["verdict"] for r in url_templates.judge_urls(table, rules).collect()}
    want = brute_verdicts(urls, rules)
    assert [out[i] for i in range(len(urls))] == want
    free = [w for u, w in zip(urls, want, strict=True) if not any(x in u for x in ("a.io/ads", "a.io/ok", "b.io/x/ads", "b.io/x/ok", "c.io", "d.io/news"))]
    assert {"block", "allow"} <= set(free)


def test_merged_branches_decide(spark):
    # /de/ is blocked by rule; its unlabelled sibling with the same children goes with it, /about is of its own
    rules = (("s.io", "/de/", "block"), ("s.io", "/home/", "allow"))
    urls = [f"http://s.io/de/item/{i}" for i in range(30)] + [f"http://s.io/en/item/{i}" for i in range(3)] + ["http://s.io/home/x"] * 30 + ["http://s.io/about"]
    table = spark.createDataFrame(list(enumerate(urls)), "page_id bigint, url string")
    out = [r["verdict"] for r in url_templates.judge_urls(table, rules).orderBy("page_id").collect()]
    assert out == ["block"] * 33 + ["allow"] * 31


def test_urls(spark):
    urls = [
        None, "", "no scheme/x", "http://A.Example.NET/en/1?q", "https://x.org/fr/2#f", "http://x.org", "http://notnet/", "ftp://de.example.com/de/9",
        "http://example.com/DE/9", "http://s.io/a/1", "http://s.io/a/2", "http://b.net",
    ]
    pages = spark.createDataFrame([(i, u, "z") for i, u in enumerate(urls)], "page_id bigint, url string, host string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_templates.judge_urls(pages).collect()}
    assert got[0] == got[1] == got[2] == ("", "", None, "allow")
    assert got[3] == ("a.example.net", "/en/1", "example.net/en/", "allow") and got[4][2:] == ("org/fr/", "allow")
    assert got[5][2:] == (None, "allow") and got[6] == ("notnet", "/", None, "allow")
    assert got[7][2:] == ("example.com/de/", "block") and got[8][2:] == (None, "allow") and got[11][2:] == (None, "allow")
    assert url_templates.judge_urls(pages.filter("page_id = -1")).count() == 0
    # most labelled urls of a template are blocked: the rest of it goes too; another template of the host, whose
    # labelled urls are not mostly blocked, stays
    rules = (("t.io", "/ads/1", "block"), ("t.io", "/ok", "allow"))
    more = [f"http://t.io/ads/1{i}" for i in range(60)] + ["http://t.io/ads/2", "http://t.io/other/2", *[f"http://t.io/ok/{i}" for i in range(30)]]
    table = spark.createDataFrame(list(enumerate(more)), "page_id bigint, url string")
    out = {r["page_id"]: r["verdict"] for r in url_templates.judge_urls(table, rules).collect()}
    assert out[60] == "block" and out[61] == "allow" and out[65] == "allow"
