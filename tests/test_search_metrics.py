import numpy as np
import pytest

from compresslab.operators import analysis, calibrate, codecs, corpus, metrics, runs, search, significance
from compresslab.plans import harness
from compresslab.sources.synthetic import synthetic_vectors


@pytest.fixture(scope="module")
def vectors(spark, sf):
    return spark.read.parquet(f"{sf}/embeddings.parquet").cache()


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_paths_agree_for_any_partitioning(spark, vectors):
    q = corpus.planted_queries(vectors)
    want = rows(search.topk_sql(q, vectors.selectExpr("vec_id item_id", "embedding vec"), 20).select("query_id", "rank", "item_id", "score"))
    matrix = search.collect_queries(q)
    for n in (1, 4, 16):
        assert rows(search.topk_arrow(matrix, vectors.repartition(n), 20).select("query_id", "rank", "item_id", "score")) == want


def test_fused_and_tiered_equal_separate_scans(spark, vectors):
    q = search.collect_queries(corpus.planted_queries(vectors))
    items = vectors.withColumn("tier", vectors.vec_id % 3 + 1)
    variants = [(c, calibrate.quantiles(vectors, c.levels() or (0.5,))) for c in (codecs.identity(), codecs.percentile_bins(2), codecs.binary("zero"))]
    fused = search.topk_fused(q, items, variants, 10, 3, tier_col="tier")
    for codec, c in variants:
        for t in (1, 3):
            want = rows(search.topk_arrow(q, items.where(f"tier <= {t}"), 10, codec, c).select("query_id", "rank", "item_id"))
            assert rows(fused.where(f"variant = '{codec.name}' AND tier = {t}").select("query_id", "rank", "item_id")) == want


def test_per_batch_calibration(vectors):
    q = search.collect_queries(corpus.planted_queries(vectors))
    codec = codecs.binary("median")
    batched = vectors.selectExpr("*", "cast(vec_id % 2 as int) batch")
    learned = calibrate.batch_quantiles(batched, "batch", (0.5,))
    got = search.topk_fused(q, batched, [(codec, learned)], 5, batch_col="batch")
    parts = [search.topk_arrow(q, batched.where(f"batch = {b}"), 5, codec, learned[b]) for b in (0, 1)]
    best = {}
    for r in parts[0].unionByName(parts[1]).collect():
        best.setdefault(r["query_id"], []).append((-r["score"], r["item_id"]))
    assert {(r["query_id"], r["item_id"]) for r in got.collect()} == {(k, i) for k, v in best.items() for _, i in sorted(v)[:5]}


def test_hamming_is_the_order_of_signed_bits(spark, sf):
    from compresslab.queries import QUERIES

    hamming = {(r["query_id"], r["rank"]): r["item_id"] for r in QUERIES["packed_hamming_topk"](spark, sf).collect()}
    v = spark.read.parquet(f"{sf}/embeddings.parquet")
    signed = search.topk_arrow(search.collect_queries(corpus.planted_queries(v)), v, 100, codecs.binary("zero"))
    assert hamming == {(r["query_id"], r["rank"]): r["item_id"] for r in signed.collect()}


def test_no_cartesian_product_on_the_arrow_path_and_one_scan(vectors, spark, sf):
    v = spark.read.parquet(f"{sf}/embeddings.parquet")
    q = (np.array([0]), np.zeros((1, 64)))
    plan = search.topk_fused(q, v, [(codecs.identity(), calibrate.Calibration())] * 3, 5)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and plan.count("FileScan") == 1 and "WindowGroupLimit" in plan


def test_an_evaluation_reads_its_items_once(spark, sf):
    v = spark.read.parquet(f"{sf}/embeddings.parquet")
    q, rel = search.collect_queries(corpus.planted_queries(v)), corpus.planted_qrels(v)
    variants = [(codecs.identity(), calibrate.Calibration()), (codecs.truncate(16), calibrate.Calibration())]
    values = harness.evaluate(q, v, rel, variants)
    assert values._jdf.queryExecution().executedPlan().toString().count("MapInArrow") == 1
    assert {r["variant"] for r in values.collect()} == {"identity", "truncate_16"}


def test_held_rows_are_the_k_best_with_ties_to_smaller_ids():
    g = np.random.default_rng(5)
    score, ids = np.round(g.normal(size=(7, 900)), 1), g.permutation(900)
    held = search._Held(7, 10)
    for at in range(0, 900, 60):
        held.add(score[:, at : at + 60], ids[at : at + 60])
    qi, found, _ = held.cut()
    for i in range(7):
        assert found[qi == i].tolist() == ids[np.lexsort((ids, -score[i]))[:10]].tolist()


def test_metrics_by_hand(spark):
    run = spark.createDataFrame([(1, 10, 1), (1, 11, 2), (1, 12, 3), (2, 20, 1)], "query_id long, item_id long, rank int")
    rel = spark.createDataFrame([(1, 11, 1), (1, 12, 2), (1, 99, 1), (3, 30, 1)], "query_id long, item_id long, grade int")
    got = {(r["query_id"], r["metric"], r["k"]): r["value"] for r in metrics.evaluate(run, rel, (2, 3)).collect()}
    assert got[1, "recall", 2] == pytest.approx(1 / 3) and got[1, "recall", 3] == pytest.approx(2 / 3) and got[1, "mrr", 3] == 0.5
    ideal = 2 + 1 / np.log2(3) + 0.5
    assert got[1, "ndcg", 3] == pytest.approx((1 / np.log2(3) + 2 / 2) / ideal, abs=1e-8)
    assert got[3, "recall", 3] == 0 and got[3, "mrr", 3] == 0 and (2, "recall", 3) not in got


def test_fusion_by_hand_and_one_run_keeps_its_order(spark):
    r = spark.createDataFrame([("a", 1, 10, 1), ("a", 1, 11, 2), ("b", 1, 11, 1), ("b", 1, 12, 2)], "run_id string, query_id long, item_id long, rank int")
    got = [(x["item_id"], x["rank"]) for x in sorted(runs.fuse(r).collect(), key=lambda x: x["rank"])]
    assert got == [(11, 1), (10, 2), (12, 3)]
    one = runs.fuse(r.where("run_id = 'a'"))
    assert [(x["item_id"], x["rank"]) for x in sorted(one.collect(), key=lambda x: x["rank"])] == [(10, 1), (11, 2)]


def test_ladder_is_nested_exact_and_partition_free(spark):
    items = spark.range(1000).selectExpr("id item_id")
    core = spark.range(40).selectExpr("id item_id", "'relevant' role")
    a = corpus.ladder(items.repartition(7), core, [100, 400, 1000])
    assert rows(a) == rows(corpus.ladder(items.coalesce(1), core, [100, 400, 1000]))
    n = {r["tier"]: r["count"] for r in a.groupBy("tier").count().collect()}
    assert n == {1: 100, 2: 300, 3: 600} and a.select("item_id").distinct().count() == 1000
    with pytest.raises(ValueError):
        corpus.ladder(items, core, [10])


def test_exact_qrels(spark):
    q = spark.createDataFrame([(1, i, 1) for i in range(12)] + [(2, i, 1) for i in range(3)], "query_id long, item_id long, grade int")
    got = corpus.select_qrels(q)
    assert got.count() == 10 and got.select("query_id").distinct().count() == 1


def brute_tail(d):
    d = [x for x in d if x]
    size = sorted(abs(x) for x in d)
    rank = {v: np.mean([i + 1 for i, s in enumerate(size) if s == v]) for v in size}
    ranks = [rank[abs(x)] for x in d]
    w = sum(r for r, x in zip(ranks, d) if x > 0)
    n = len(d)
    return n, w, sum(sum(r for i, r in enumerate(ranks) if m >> i & 1) <= w + 1e-9 for m in range(2**n)) / 2**n


@pytest.mark.parametrize("d", [[-3, -1, -2, -4, 5, -6], [0, -1, -2, 3, -4, 5, 0, -6, -7, -8, -9], [-1, -2, -3, -4, -5, -6, -7, -8, -9, 10, -11, -12]])
def test_signed_ranks_against_enumeration(spark, d):
    pairs = spark.createDataFrame([("x", 10.0, 10.0 + v) for v in d], "k string, base double, other double")
    r = significance.wilcoxon_less(pairs, ("k",)).first()
    n, w, p = brute_tail(d)
    assert (r["n"], r["w_plus"]) == (n, w) and r["p"] == pytest.approx(p)


def test_equal_samples_get_no_star(spark):
    pairs = spark.createDataFrame([("x", 0.5, 0.5)] * 5, "k string, base double, other double")
    s = significance.with_z(significance.statistic(pairs, ("k",))).first()
    assert s["n"] == 0 and not s["star"] and significance.wilcoxon_less(pairs, ("k",)).first()["p"] == 1.0
    assert significance.holm([0.01, 0.04, 0.03]) == pytest.approx([0.03, 0.06, 0.06])


def test_synthetic_vectors_depend_on_ids_alone(spark):
    a, b = (sorted(map(lambda r: (r["vec_id"], tuple(r["embedding"])), synthetic_vectors(spark, 5000, 8, slices=s).collect())) for s in (1, 5))
    assert a == b and len(a) == 5000 and abs(np.linalg.norm(a[4999][1]) - 1) < 1e-5


def test_recall_falls_with_the_corpus_and_quantization_beats_truncation(spark, sf):
    """Two of the reported findings on a small ladder with generated filler."""
    v = spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", "embedding")
    q, rel = search.collect_queries(corpus.planted_queries(v)), corpus.planted_qrels(v)
    items = v.selectExpr("*", "1 tier").unionByName(synthetic_vectors(spark, 8000).selectExpr("*", "case when vec_id < 1000001500 then 2 else 3 end tier"))
    wanted = [codecs.identity(), codecs.truncate(16), codecs.percentile_bins(8), codecs.binary("zero")]
    variants = [(c, calibrate.quantiles(v, c.levels() or (0.5,))) for c in wanted]
    run = search.topk_fused(q, items, variants, 100, 3, tier_col="tier")
    got = {(r["variant"], r["tier"]): r["value"] for r in metrics.summary(metrics.recall(run, rel, (100,), ("variant", "tier")), ("variant", "tier")).collect()}
    assert got["identity", 1] >= got["identity", 2] >= got["identity", 3]
    for t in (1, 2, 3):
        assert got["percentile_8", t] > got["truncate_16", t]
    assert got["identity", 3] > got["bits_zero", 3]
