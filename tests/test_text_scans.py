"""Scans of texts by token numbers against plain versions."""

import numpy as np
import pyarrow as pa

from compresslab.functions import tokens
from compresslab.operators import calibrate, codecs, corpus, encoders, runs, search

TEXTS = ["The Cat sat", "", None, "a", "über Ärger, 2x über", "the cat", "ßab\U0001f600cd", "x" * 1000]


def test_counts_equal_a_plain_loop():
    for e in encoders.ENCODERS:
        got = encoders.counts(pa.array(TEXTS), e.dims, e.unit)
        for row, text in enumerate(TEXTS):
            want = np.zeros(e.dims)
            for t in encoders.tokens(text or "", e.unit):
                h = encoders._digest(t)
                want[h % e.dims] += 1 if h // e.dims % 2 == 0 else -1
            assert (got[row] == want).all()


def test_pieces_cover_a_column_once():
    column = pa.array(TEXTS * 5)
    found = [t for _, p in tokens.pieces(column, rows=3, size=20) for t in p.to_pylist()]
    assert found == column.to_pylist()


def test_containment_and_passages(spark):
    docs = spark.createDataFrame(list(enumerate([*TEXTS, "say über Ärger, 2x über", "über Ärger, 2x"])), "item_id long, text string")
    asked = spark.createDataFrame([(1, "über Ärger, 2x über"), (2, "a"), (3, None), (4, "über Ärger, 3")], "query_id long, text string")
    got = {(r["query_id"], r["item_id"]) for r in corpus.containment(docs, asked).collect()}
    assert got == {(q, i) for q, t in asked.collect() if t for i, text in docs.collect() if text and t in text}
    cut = corpus.passages(docs.withColumnRenamed("item_id", "doc_id"), 7).collect()
    assert {(r["doc_id"], r["i"]): r["text"] for r in cut} == {(i, j // 7): t[j : j + 7] for i, t in docs.collect() if t for j in range(0, len(t), 7)}


def test_lexical_runs_equal_a_plain_sum(spark):
    texts = ["a b c", "a a b", "c d", "", "b b b b a", None, "e"]
    items = spark.createDataFrame(list(enumerate(texts)), "item_id long, text string").repartition(3)
    asked = spark.createDataFrame([(7, "a b"), (9, "d zzz a")], "query_id long, text string")
    got = {(r["run_id"], r["query_id"], r["item_id"]): r["score"] for r in runs.bm25_runs(asked, items, {"x": (0.9, 0.4), "y": (2.0, 1.0)}, 3).collect()}
    words = [(t or "").split() for t in texts]
    mean = sum(map(len, words)) / 6
    for r, (k1, b) in {"x": (0.9, 0.4), "y": (2.0, 1.0)}.items():
        for q, asks in ((7, "ab"), (9, "da")):
            want = {}
            for i, ws in enumerate(words):
                for w in asks:
                    df = sum(w in x for x in words)
                    if w in ws:
                        want[i] = want.get(i, 0) + np.log(1 + (7 - df + 0.5) / (df + 0.5)) * ws.count(w) * (k1 + 1) / (ws.count(w) + k1 * (1 - b + b * len(ws) / mean))
            best = sorted(((-round(v, 9), i) for i, v in want.items()))[:3]
            assert {i: s for (a, c, i), s in got.items() if (a, c) == (r, q)} == {i: -v for v, i in best}


def test_known_items_equal_the_top_k(spark, sf):
    e = spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", "embedding")
    e = e.unionByName(e.where("vec_id < 60").selectExpr("vec_id + 1000 vec_id", "embedding")).repartition(5)  # equal scores
    ids, x = search.collect_queries(e.where("vec_id % 10 = 0").selectExpr("vec_id query_id", "embedding vec"))
    q = x + np.random.default_rng(1).normal(0, 0.25, x.shape)
    variants = [(c, calibrate.quantiles(e, c.levels() or (0.5,))) for c in (codecs.identity(), codecs.binary("zero"), codecs.truncate(8), codecs.percentile_bins(2))]
    got = {(r["variant"], r["query_id"]) for r in search.known_items((ids, q), x, e, variants, 5).where("found").collect()}
    run = search.topk_fused((ids, q), e, variants, 5).where("query_id = item_id")
    assert got == {(r["variant"], r["query_id"]) for r in run.collect()} and 20 < len(got) < 4 * len(ids)
