"""The pipeline against a plain version that goes document by document."""

import hashlib
import random

import numpy as np
import pyarrow as pa

from compresslab.llm import secrets, toxicity
from tests.llm.test_operators import DOCS, brute_classes, plain_codec, words


def test_pipeline_is_its_stages(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(11)
    texts = [words(rng, 80) + (" zidiot " if i % 5 == 0 else " zfriend ") + words(rng, 30) for i in range(200)]
    item = words(rng, 25)
    texts += [texts[1], texts[2] + " tail", words(rng, 50) + " " + item, f'{words(rng, 50)} token = "{hashlib.sha1(b"k").hexdigest()}" {words(rng, 9)}', None, "", "..."]
    frame = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in enumerate(texts)], DOCS)
    frame.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, int(i % 5 == 0)) for i in range(200)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {r["doc_id"]: r for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}

    model = toxicity.fit(spark, frame, spark.read.parquet(f"{tmp_path}/labels.parquet"))
    score = toxicity.score_texts(pa.array(texts, pa.large_string()), model)
    left = [i for i in range(len(texts)) if score[i] < 0.5]
    classes = brute_classes([texts[i] for i in left])
    left = [left[k] for k in sorted(set(classes))]
    left = [i for i in left if item not in (texts[i] or "")]
    plain, forest = plain_codec(), secrets.train()
    assert sorted(got) == left
    for i in left:
        t = texts[i] or ""
        for _, b, e, _, _, s in reversed(secrets.judge(pa.array([t]), forest)):
            if s >= 0.5:
                t = t[:b] + "[SECRET]" + t[e:]
        ids = plain.encode_ordinary(t)
        assert (got[i]["n_tokens"], got[i]["ids_sha256"]) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())
        assert got[i]["decoded_sha256"] == hashlib.sha256(t.encode()).hexdigest()


def test_stages():
    import corpus_pipeline

    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_copies", "decontamination", "secrets", "encoding"]
