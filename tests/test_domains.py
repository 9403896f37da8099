"""Searches of known items over stored counts: equal to plain versions, and no work done again for each encoder, task or copy."""

import functools
import hashlib

import numpy as np
import pyarrow as pa

from compresslab import queries_corpus as Q
from compresslab.functions import tokens
from compresslab.functions import vectors as V
from compresslab.operators import calibrate, codecs, encoders, search


def _texts(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 150").selectExpr("doc_id item_id", "substr(text, 1, 1500) text")
    return docs.unionByName(docs.where("item_id < 20").selectExpr("item_id + 1000 item_id", "text")).repartition(3)  # equal scores


def test_known_items_of_every_codec_equal_the_top_k(spark, sf):
    for e in Q._DOMAIN_ENCODERS:
        tallies = encoders.tallied(_texts(spark, sf), 256, e.unit).localCheckpoint()
        read = functools.partial(Q._finished, e)
        ids, counts = search.collect_queries(tallies.where("item_id % 4 = 0").selectExpr("item_id query_id", "vec"))
        own = encoders.finish(e, counts)
        q = own + np.random.default_rng(1).normal(0, 1.5, own.shape)
        base = calibrate.counted_batch_quantiles(tallies.selectExpr("0 one", "vec"), "one", (0.025, 0.5, 0.975), [functools.partial(encoders.finish, e)], "vec")[0][0]
        variants = []
        for c in [*Q._DOMAIN_FULL, codecs.pq(32, 4, symmetric=False), codecs.lsh(300, hashed=True)]:
            if isinstance(c, codecs.Pq) and c.width == 8 and c.m > 32:
                continue
            variants.append((c, calibrate.principal(tallies, "vec", read) if isinstance(c, codecs.Pca) else codecs.train_pq(tallies, c.m, c.width, 3, "item_id", "vec", read=read) if isinstance(c, codecs.Pq) else base))
        got = {(r["variant"], r["query_id"]) for r in search.known_items((ids, q), own, tallies, variants, 3, "item_id", "vec", read).where("found").collect()}
        run = search.topk_fused((ids, q), tallies, variants, 3, id_col="item_id", vec_col="vec", read=read).where("query_id = item_id")
        assert got == {(r["variant"], r["query_id"]) for r in run.collect()} and len(got) > 50


def test_many_queries_take_several_slices_and_tiles():
    e = np.random.default_rng(0).normal(size=(700, 16))
    ids, q, c = np.arange(700), e + np.random.default_rng(1).normal(0, 0.5, e.shape), calibrate.Calibration()
    members = [(0, codecs.lsh(100), c), (1, codecs.lsh(200), c)]
    known = search._Known(members, ids, q, *search._Known.made(members, q, e))
    before = np.zeros((2, 700), np.int64)
    for at in range(0, 700, 90):
        known.count(e[at : at + 90], ids[at : at + 90], before, 10)
    for v, codec, _ in members:
        dots = (codec.space(codec.encode(q, c), c) @ codec.space(codec.encode(e, c), c).T).astype(int)
        mark = dots[ids, ids][:, None]
        want = ((dots > mark) | ((dots == mark) & (ids[None, :] < ids[:, None]))).sum(axis=1)
        assert ((before[v] < 10) == (want < 10)).all() and (before[v] == want)[want < 10].all()


def test_prefixes_of_one_family_only():
    for small, large in ((512, 1024), (1024, 2048)):
        assert codecs.family(codecs.lsh(small), 256) == codecs.family(codecs.lsh(large), 256) is not None
        assert (codecs.lsh(large).frame(256)[:small] == codecs.lsh(small).frame(256)).all()
    assert codecs.family(codecs.lsh(256), 256) is None and codecs.family(codecs.lsh(512, thresholds="median"), 256) is None
    assert codecs.family(codecs.lsh(512, seed=2), 256) != codecs.family(codecs.lsh(512), 256) and codecs.family(codecs.identity(), 256) is None


def test_counted_quantiles_equal_those_of_all_values(spark, sf):
    tallies = encoders.tallied(_texts(spark, sf), 256, "word").selectExpr("cast(item_id % 3 as int) own", "vec").localCheckpoint()
    for e in (Q.DOMAIN_ENCODER, encoders.HashedEncoder("cubed", 256, "word", cubed=True, offset=0.5)):
        got = calibrate.counted_batch_quantiles(tallies, "own", (0.025, 0.5, 0.9), [functools.partial(encoders.finish, e)], "vec")[0]
        for batch in range(3):
            x = encoders.finish(e, search.collect_queries(tallies.where(f"own = {batch}").selectExpr("own query_id", "vec"))[1])
            assert (got[batch].low == x.min(axis=0)).all() and (got[batch].high == x.max(axis=0)).all()
            for level in (0.025, 0.5, 0.9):
                assert np.allclose(got[batch].at(level), np.quantile(x, level, axis=0), rtol=0, atol=1e-9)


def test_lloyd_of_equal_points_equals_the_plain_loop():
    rng = np.random.default_rng(3)
    for points in (rng.integers(-2, 3, (3000, 2)).astype(float), rng.normal(size=(500, 4))):
        start = points[rng.permutation(len(points))[:32]]  # with equal centres, of which some stay empty
        want = start
        for _ in range(5):
            far = (points**2).sum(axis=1)[:, None] - 2 * points @ want.T + (want**2).sum(axis=1)[None, :]
            near = far.argmin(axis=1)
            fresh = np.array([points[near == i].mean(axis=0) if (near == i).any() else want[i] for i in range(32)])
            empty = np.flatnonzero(np.bincount(near, minlength=32) == 0)
            fresh[empty] = points[np.argsort(-far[np.arange(len(points)), near], kind="stable")[: len(empty)]]
            want = fresh
        assert np.allclose(codecs.lloyd(points, start, 5), want, atol=1e-9)
    assert len(codecs._distinct(np.repeat(np.eye(3), 50, axis=0))[0]) == 3  # equal points are measured once


def test_digests_equal_the_library():
    words = ["", "a", "x" * 55, "x" * 56, "é" * 27, "é" * 28, "漢字", "y" * 200] + [chr(97 + i % 26) * (i % 60) for i in range(9000)]
    for column in (pa.array(words), pa.array(words).slice(3), pa.array([], pa.string()), pa.array(["z" * 99])):
        assert tokens.digests(column).tolist() == [int(hashlib.md5(w.encode()).hexdigest()[:8], 16) for w in column.to_pylist()]


def test_encoders_of_the_same_tokens_share_a_scan_of_the_texts(spark, sf, monkeypatch):
    read = []
    monkeypatch.setattr(encoders, "tallied", lambda items, dims, unit, f=encoders.tallied: read.append(unit) or f(items, dims, unit))
    found = Q._domain_values(spark, sf, Q._DOMAIN_ENCODERS, [codecs.identity(), codecs.equal_width(2, scoring="centred")])
    assert read == ["word"] * 2 + ["gram"] * 2  # items and questions
    assert {r["encoder"] for r in found.select("encoder").distinct().collect()} == {e.name for e in Q._DOMAIN_ENCODERS}
    assert V.matrix(pa.array([[1, 2]], pa.list_(pa.int32()))).dtype == np.float64
