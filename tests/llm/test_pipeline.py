"""The pipeline: what each stage keeps, on a small corpus with planted cases."""

import random

from pyspark.sql import functions as F

import corpus_pipeline


def test_stages_decide(spark, tmp_path):
    rng = random.Random(5)
    words = ["the", "and", "of", "to", "in", "that", *("".join(rng.choice("aeinorst") for _ in range(5)) for _ in range(150))]
    text = lambda n: " ".join(rng.choices(words, k=n))
    item = text(30)
    rows = [(i, text(60), "en", f"s{i % 3}", None) for i in range(40)]
    near = rows[0][1].split()
    near[30] = "changed"
    rows += [(50, rows[1][1], "en", "s0", None), (51, " ".join(near + near[-1:]), "en", "s0", None), (52, text(20) + " " + item, "en", "s1", None), (53, "12 34 !!", "en", "s1", None), (54, None, "en", "s1", None), (55, text(30) + " mail me@here.org now", "en", "s1", 5)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs, seen = spark.read.parquet(f"{tmp_path}/documents.parquet"), []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, str(tmp_path))
        out.write.parquet(f"{tmp_path}/out{k}")
        docs, before = spark.read.parquet(f"{tmp_path}/out{k}"), docs
        if k < 4:
            assert docs.columns == before.columns
        seen.append({r.doc_id for r in docs.collect()})
    everything = {r[0] for r in rows}
    assert everything - seen[0] == {53, 54}
    assert seen[0] - seen[1] == {50, 51}
    assert seen[1] - seen[2] == {52} and seen[2] == seen[3] == seen[4]
    last = {r.doc_id: r for r in docs.collect()}
    assert "[EMAIL]" in last[55].text and last[55].n_chars == len(last[55].text)
    assert all(r.taken <= 3 * r["size"] for r in last.values())
    assert {r.doc_id for r in corpus_pipeline.run(spark, str(tmp_path)).collect()} == seen[4]


def test_stages_on_odd_tables(spark, tmp_path):
    """Empty tables, null and repeated ids, and columns that are called like those of the stages."""
    rng = random.Random(6)
    words = ["the", "and", "of", "to", "in", *("".join(rng.choice("aeinorst") for _ in range(5)) for _ in range(90))]
    text = lambda n: " ".join(rng.choices(words, k=n))
    rows = [(i, text(40), "en", f"s{i % 2}", None) for i in range(12)] + [(None, text(40), "en", None, 7), (None, None, None, None, None)]
    rows += [(rows[2][0], rows[2][1], "en", "s0", None)]
    names = ["score", "Terms", "size", "items", "class", "text_key", "a.b"]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    for k, data in enumerate((rows, [])):
        d = f"{tmp_path}/{k}"
        spark.createDataFrame(data, schema).withColumns({c: F.lit(f"own {c}") for c in names}).write.parquet(f"{d}/documents.parquet")
        spark.createDataFrame([], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
        out = corpus_pipeline.run(spark, d)
        got = out.collect()
        assert sorted((r.doc_id is None, r.doc_id) for r in got) == sorted((r[0] is None, r[0]) for r in data if r[1])
        assert all(r[c] == f"own {c}" for r in got for c in names if c != "size") and "taken" in out.columns
