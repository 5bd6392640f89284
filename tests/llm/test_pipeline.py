import random

import corpus_pipeline


def test_stages_take_effect(spark, tmp_path):
    rng = random.Random(2)
    good, bad = [f"w{i}" for i in range(300)], [f"J{i}!!" for i in range(50)]
    text = lambda words, n=80: " ".join(rng.choice(words) for _ in range(n))
    passage = text(good, 60)
    rows = [(i, text(bad if i % 10 == 0 else good) + (f"\n{passage}" if i % 7 == 1 else ""), "en", f"s{i % 3}", 1) for i in range(150)]
    rows += [(200, rows[2][1] + " tail", "en", "s1", 1), (201, None, "en", "s1", 0)]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, int(i % 10 != 0), 0) for i in range(100)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs, kept = spark.read.parquet(f"{tmp_path}/documents.parquet"), []
    for n, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, str(tmp_path))
        out.write.parquet(f"{tmp_path}/{n}")
        docs = spark.read.parquet(f"{tmp_path}/{n}")
        kept.append(docs.collect())
        if n < 4:
            assert docs.columns == [c.split()[0] for c in schema.split(", ")], name
    ids = [{r["doc_id"] for r in k} for k in kept]
    assert not ids[0] & {i for i in range(150) if i % 10 == 0}
    assert ids[0] >= {i for i in range(150) if i % 10}
    assert sum(passage in (r["text"] or "") for r in kept[1]) == 1
    assert 200 not in ids[2]
    assert ids[2] >= {i for i in range(150) if i % 10}
    assert len(kept[3]) == len(kept[4])
    assert ids[4] <= ids[2]
