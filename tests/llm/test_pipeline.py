import random

import corpus_pipeline


def test_stages_on_a_small_corpus(spark, tmp_path):
    r = random.Random(4)
    vocab = [f"{a}{b}{c}" for a in "bdgklm" for b in "aeiou" for c in ("n", "st", "r", "th", "x")]
    line = lambda n: " ".join(r.choice(vocab) for _ in range(n))
    item = line(40)
    docs, labels = [], []
    for i in range(60):
        t = line(120) + (" grumbo " + line(5) + " grumbo" if i % 5 == 0 else "")
        docs.append((i, f"Share this page\n{t}", "en", "s", 1))
        labels.append((i, 1, int(i % 5 == 0)))
    docs += [(100, docs[1][1], "en", "s", 1), (101, docs[2][1] + " extra", "en", "s", 1), (102, f"{line(50)} {item} {line(50)}", "en", "s", 1), (103, None, None, None, None), (104, "grumbo you " + line(60), "en", "s", 1)]
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    own = spark.read.parquet(f"{tmp_path}/documents.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        own = stage(spark, own, str(tmp_path))
        own.write.parquet(f"{tmp_path}/out/{name}")
        own = spark.read.parquet(f"{tmp_path}/out/{name}")
        kept[name] = sorted({x["doc_id"] for x in own.collect()})
        if name != "packing":
            assert own.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    clean = [i for i in range(60) if i % 5]
    assert kept["toxicity"] == [*clean, 100, 101, 102, 103]
    assert kept["line_dedup"] == kept["toxicity"]
    assert kept["near_duplicates"] == [*clean, 102, 103]
    assert kept["decontamination"] == kept["packing"] == [*clean, 103]
    lines = spark.read.parquet(f"{tmp_path}/out/line_dedup").filter("doc_id = 1").first()
    assert not lines["text"].startswith("Share") and lines["n_chars"] == len(lines["text"])
    assert sorted({x["doc_id"] for x in corpus_pipeline.run(spark, str(tmp_path)).collect()}) == kept["packing"]


def test_empty_tables(spark, tmp_path):
    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
