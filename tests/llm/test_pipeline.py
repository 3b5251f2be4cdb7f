"""The pipeline: each stage against a brute-force version of what it keeps."""

from collections import Counter

import corpus_pipeline as pipe
from pyspark.sql import functions as F
from test_decontamination import ITEMS, brute
from test_native_operators import ODD, KIND
from test_similar_documents import roots

from redgraph.llm import toxicity
from redgraph.session import staged


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = dict(docs.select("doc_id", "text").collect())
    model = toxicity.fit(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    score = {r.doc_id: r.score for r in toxicity.score_documents(docs, model).collect()}
    kept = []
    for k, (name, stage) in enumerate(pipe.STAGES):
        docs = staged(stage(spark, docs, sf), f"test-{name}")
        kept.append([r.doc_id for r in docs.select("doc_id").collect()])
        if k < len(pipe.STAGES) - 1:
            assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        assert all(r.text == texts[r.doc_id] for r in docs.select("doc_id", "text").collect())
    assert sorted(kept[0]) == sorted(i for i, s in score.items() if s < 0.5)
    order = sorted(kept[0])
    near, _ = roots([texts[i] for i in order])
    assert sorted(kept[1]) == [i for k, i in enumerate(order) if near[k] == k]
    bench = spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").collect()
    hit = brute([(i, texts[i]) for i in kept[1]], bench)
    assert sorted(kept[2]) == sorted(i for i in kept[1] if not hit[i][1])
    assert max(Counter(kept[3]).values()) <= 2 and set(kept[3]) <= set(kept[2])
    assert Counter(kept[4]) == Counter(kept[3])
    sizes = Counter(r.shard for r in docs.select("shard").collect())
    assert max(sizes.values()) - min(sizes.values()) <= 1


def test_odd_rows_pass_all_stages(spark, tmp_path):
    d = str(tmp_path)
    docs = spark.createDataFrame([(i, t, "en", s, n) for i, t, s, n in ODD], "doc_id long, text string, lang string, source string, n_chars long")
    for name, table in (("documents", docs), ("none", docs.where(F.lit(False)))):
        folder = f"{d}/{name}"
        table.write.parquet(f"{folder}/documents.parquet")
        spark.createDataFrame([(1, 0, 0), (5, 0, 1)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
        spark.createDataFrame(ITEMS, "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
        out = pipe.run(spark, folder)
        assert out.columns == ["doc_id", "text", "lang", "source", "n_chars", "shard", "slot"]
        assert out.count() <= 2 * table.count()
    assert KIND
