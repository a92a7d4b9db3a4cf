"""Classifiers by held-out accuracy, archives by round trip and brute force, the pipeline by its stages."""

import random
import zlib
from collections import defaultdict

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline
from ucqlearn.llm import queries
from ucqlearn.llm.cotrain import score_quality, train_quality
from ucqlearn.llm.linear import DenseRows, SparseRows, fit_logistic
from ucqlearn.llm.toxicity import GramSpec, score_toxicity, train_toxicity
from ucqlearn.llm.warc import LoserTree, build_record, capture_histories, members, parse_record, payload_digest, url_key

from .oracle import check
from .test_similar import brute

SF, LARGE = "/root/testdata/sf0.01", "/root/testdata/sf0.1"


def test_logistic_meets_its_optimum():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(400, 5))
    y = (x @ np.array([1, -2, 0.5, 0, 0]) + 0.3 + rng.logistic(size=400) > 0).astype(float)
    w, b = fit_logistic(DenseRows(x), y, 5, 1e-3)
    g = 1 / (1 + np.exp(-(x @ w + b))) - y
    assert np.abs(g @ x / 400 + 1e-3 * w).max() < 1e-5 and abs(g.mean()) < 1e-5
    ids = [np.flatnonzero(r > 0) for r in x]
    scale = np.array([1.0, 2.0, 0.5, 1.0, 3.0])
    dense = (x > 0) * scale
    assert np.allclose(fit_logistic(SparseRows.of(ids, scale), y, 5, 1e-2)[0], fit_logistic(DenseRows(dense), y, 5, 1e-2)[0], atol=1e-4)


def test_gram_buckets_by_definition():
    spec = GramSpec(2, 3, 12)
    a, b = spec.buckets("Ab  c"), spec.buckets("ab c")
    assert [len(x) for x in a] == [5, 4] and all((p == q).all() for p, q in zip(a, b)) and spec.buckets("") is not None
    assert max(x.max() for x in a) < 1 << 12


def _labelled(spark, rows, column):
    labels = {r.doc_id: r[column] for r in spark.read.parquet(f"{LARGE}/labels.parquet").collect()}
    return [(labels[r.doc_id], r) for r in rows if r.held_out and r.doc_id in labels]


def test_toxicity_held_out(spark):
    rows = queries.op5_toxicity(spark, LARGE).collect()
    assert len(rows) == 10000 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in rows)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    pairs = [(y, r.predicted) for y, r in _labelled(spark, rows, "toxic")]
    tp, fp, fn = (sum(p == q for p in pairs) for q in ((1, 1), (0, 1), (1, 0)))
    print("toxicity", tp, fp, fn)
    assert 2 * tp / (2 * tp + fp + fn) > 0.9


def test_quality_held_out(spark):
    rows = queries.op6_quality_cotraining(spark, LARGE).collect()
    assert len(rows) == 10000
    pairs = [(y, r.predicted) for y, r in _labelled(spark, rows, "quality")]
    for r in rows:
        assert all(0 <= p <= 1 for p in (r.text_score, r.meta_score, r.score)) and r.predicted == (r.score >= 0.5)
    print("quality", sum(a == b for a, b in pairs) / len(pairs), sum(a == b == 0 for a, b in pairs), sum(a == 0 for a, _ in pairs))
    assert sum(a == b for a, b in pairs) / len(pairs) > 0.93


def test_views_label_for_each_other(spark):
    """Text and source both tell the class; few rows are labelled, and a fifth of the texts tells nothing."""
    rng = random.Random(8)
    docs, labels = [], []
    for i in range(3000):
        good = rng.random() < 0.6
        text = " ".join(rng.choice(["plain", "sound", "clear"] if good else ["junk###", "spam$$", "zz%%%"]) for _ in range(30)) if i < 2400 else "neutral words only"
        docs.append((i, text, "en", f"{'good' if good else 'bad'}{rng.randrange(3)}", len(text)))
        if i < 300:
            labels.append((i, int(good)))
    df = spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long")
    model = train_quality(spark, df, spark.createDataFrame(labels, "doc_id long, quality int"))
    assert all(sum(map(sum, turn)) > 2000 for turn in model.handed)  # of 2700 and more without a label, from both views
    got = {r.row.doc_id: r for r in score_quality(spark, df, model).collect()}
    for i, text, _, source, _ in docs:
        assert (got[i].meta_score >= 0.5) == source.startswith("good") and (i >= 2400 or (got[i].score >= 0.5) == source.startswith("good"))
    only = train_quality(spark, df, spark.createDataFrame(labels, "doc_id long, quality int"), rounds=0)
    assert only.handed == [] and any((a != b).any() for a, b in zip(only.tables, model.tables))


def test_models_on_odd_tables(spark):
    df = spark.createDataFrame([(1, None, None, None, None, 1.0), (2, "", "en", "s", 0, 1.0), (None, "some text", "en", "s", 9, 1.0), (3, "x" * 50000, "fr", "t", 50000, 1.0), (3, "x", "fr", "t", 1, 2.0)], "doc_id long, text string, lang string, source string, n_chars long, score double")
    for labels in (spark.createDataFrame([], "doc_id long, toxic int, quality int"), spark.createDataFrame([(1, 1, 1), (1, 1, 1), (None, 0, 0), (3, 0, 0), (2, None, None)], "doc_id long, toxic int, quality int")):
        assert score_toxicity(spark, df, train_toxicity(spark, df, labels)).where("score between 0 and 1").count() == 5
        assert score_quality(spark, df, train_quality(spark, df, labels)).where("score between 0 and 1").count() == 5
        none = df.where("false")
        assert score_toxicity(spark, none, train_toxicity(spark, none, labels)).count() == 0
        assert score_quality(spark, none, train_quality(spark, none, labels)).count() == 0


# archives


def test_op7_sql(spark):
    check(queries.op7_warc(spark, SF), queries.ORACLES["op7_warc"], SF)


def test_records_round_trip():
    rng = random.Random(4)
    payloads = [b"", b"x", "é\r\n\r\nWARC/1.1".encode(), bytes(rng.randrange(256) for _ in range(300_000))]
    data = []
    for i, p in enumerate(payloads):
        for ref in (None, 7):
            d = zlib.compressobj(6, zlib.DEFLATED, 31)
            data.append((i, p, ref, d.compress(build_record(i, "http://a b\n/", p, payload_digest(p), ref)) + d.flush()))
    at = 0
    for (i, p, ref, z), (offset, length, raw) in zip(data, members(b"".join(x[3] for x in data)), strict=True):
        r = parse_record(raw)
        assert (offset, length) == (at, len(z)) and r["page_id"] == i and r["url"] == "http://a%20b%0A/" and r["refers_to"] == ref
        assert r["payload_bytes"] == len(p) and r["payload_digest"] == payload_digest(p) and r["payload"] == (p if ref is None else b"")
        at += length
    assert url_key("HTTPS://www.Example.org:80/A?b=C") == "org,example)/a?b=c" and url_key("") == ")/"


def test_loser_tree():
    rng = random.Random(6)
    for k in (0, 1, 2, 3, 5, 8, 13):
        runs = [sorted((rng.randrange(9), rng.random()) for _ in range(rng.randrange(12))) for _ in range(k)]
        assert list(LoserTree(runs, lambda x: x)) == sorted(x for r in runs for x in r)


def test_histories_in_global_order(spark):
    rows = [(i, f"http://h{i % 7}.org/{i % 3}", f"body {i % 11}") for i in range(500)] + [(900, None, None), (901, "http://www.h1.org/1", ""), (None, "u", "body 1"), (499, "http://h2.org/1", "body 4")]
    df = spark.createDataFrame([(*r, 5) for r in rows], "page_id long, url string, html string, refers_to int").repartition(7)
    from ucqlearn.llm import warc
    from ucqlearn.llm.common import Workspace

    work = Workspace(spark, "t")
    assert warc.write_archives(warc.resolve_revisits(df), work.path("a"), most_bytes=2000) > 7
    out = sorted(warc.merge_runs(work.put(warc.index_runs(spark, work.path("a")), "r"), each=60).collect(), key=lambda r: r.history_order)
    keys = [(r.urlkey, r.timestamp, -1 if r.page_id is None else r.page_id) for r in out]
    assert len(out) == len(rows) and keys == sorted(keys) and len({r.history_order for r in out}) == len(rows)
    head = defaultdict(int)
    for i, _, h in rows:
        head[h or ""] = max(head[h or ""], i or 0)
    digest = {payload_digest(h.encode()): i for h, i in head.items()}
    assert all(r.refers_to == (None if r.page_id == digest[r.payload_digest] else digest[r.payload_digest]) and (r.refers_to is None) == (r.record_type == "response") for r in out)
    assert capture_histories(spark, df.where("false")).count() == 0
    short = warc.resolve_revisits(df, least_bytes=7).where("refers_to is not null").collect()
    assert all(len(r.html) >= 7 for r in short) and short


# pipeline


def test_pipeline_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, kept = docs.columns, docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = kept
        kept = stage(spark, before, SF).persist()
        assert kept.columns == columns and dict(kept.dtypes) == dict(docs.dtypes)
        a, b = {r.doc_id: r for r in before.collect()}, {r.doc_id: r for r in kept.collect()}
        assert set(b) <= set(a)
        if name == "toxicity":
            toxic = {r.doc_id for r in spark.read.parquet(f"{SF}/labels.parquet").where("toxic = 1").collect()}
            print("toxic left", len(toxic & set(b)), "of", len(toxic), "dropped", len(a) - len(b))
            assert len(toxic & set(b)) <= 0.3 * len(toxic) and len(set(a) - set(b)) < 0.25 * len(a)
        if name == "near_duplicates":
            want, linked = brute([(r.doc_id, r.text) for r in a.values()])
            assert {want[i] for i in b} == set(want.values())  # of each group one stays at least
            assert sum(i in b and j in b for i, j in linked) <= 0.1 * len(linked) and all(any(want[j] == want[i] for j in b) for i in set(a) - set(b))
        if name == "decontamination":
            from ucqlearn.llm.decontaminate import BenchmarkIndex, normal_words

            index = BenchmarkIndex([(r.item_id, normal_words(r.text.encode())) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()], 10)
            assert sum(bool(index.scan(normal_words(r.text.encode()))[1]) for r in b.values()) == 0
            assert all(b[i].text == a[i].text for i in b if not index.scan(normal_words(a[i].text.encode()))[1])
        if name == "secrets":
            from ucqlearn.llm.secrets import SecretScanner

            assert set(a) == set(b) and not any(SecretScanner().scan(r.text)[1] for r in b.values())
        assert all(r.n_chars == len(r.text) for i, r in b.items() if r.text != a[i].text)
    pieces = corpus_pipeline.run(spark, SF)
    assert {r.doc_id for r in pieces.select("doc_id").distinct().collect()} == {r.doc_id for r in kept.select("doc_id").collect()}
    assert pieces.where(F.length("ids") != 4 * F.col("length")).count() == 0


def test_near_copies_by_fingerprint_and_by_similarity(spark, tmp_path):
    words = [f"w{i}" for i in range(3000)]
    turned = words[:]
    for i in range(0, 3000, 20):  # five-word runs mostly differ, three-word fingerprints may not
        turned[i] = f"x{i}"
    swapped = words[:40] + ["other"] + words[41:]
    rows = [(5, " ".join(words)), (3, " ".join(words)), (7, " ".join(swapped)), (9, " ".join(f"z{i}" for i in range(500))), (None, "loose"), (11, " ".join(turned))]
    spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).write.parquet(str(tmp_path / "d"))
    docs = spark.read.parquet(str(tmp_path / "d"))
    kept = {r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, SF).collect()}
    prints = {r.doc_id: r.component_id for r in corpus_pipeline.near_duplicates(spark, docs).collect()}
    alike = {r.doc_id: r.component_id for r in corpus_pipeline.similar_groups(spark, docs).collect()}
    assert {None, 3, 9} <= kept and not {5, 7} & kept
    assert all(prints[d] == alike[d] == d for d in kept - {None})
