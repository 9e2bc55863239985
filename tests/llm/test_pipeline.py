from pyspark.sql import functions as F

import corpus_pipeline as P
from tilerank.llm import decontaminate, toxicity


def test_stages_and_run(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    bench = spark.read.parquet(f"{sf}/benchmark.parquet").collect()
    columns, seen = docs.columns, docs
    texts = {r.doc_id: r.text for r in docs.collect()}
    kept = []
    for name, stage in P.STAGES[:-1]:
        seen = stage(spark, seen, sf).cache()
        assert seen.columns == columns, name
        kept.append([r.doc_id for r in seen.select("doc_id").collect()])
    toxic, near, clean, mixed = kept
    model = toxicity.train(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    scorer = toxicity.Scorer(model)
    assert sorted(toxic) == sorted(i for i, t in texts.items() if scorer.score(t) < 0.5)
    assert len(set(near)) == len(near) and set(near) <= set(toxic) and len({texts[i] for i in near}) == len(near)
    finder = decontaminate.Finder(decontaminate.ItemIndex([(r.item_id, r.text) for r in bench]))
    assert sorted(clean) == sorted(i for i in near if not finder.of(texts[i])) and len(clean) > 0.8 * len(toxic)
    assert set(mixed) <= set(clean)
    last = P.run(spark, sf)
    assert sorted(r.doc_id for r in last.select("doc_id").collect()) == sorted(mixed) and last.columns[: len(columns)] == columns


def test_odd_rows_and_names_pass_all_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(40)
    odd = [(None, None, None, None, None), (None, "", "en", "s", 0), (70_001, None, "en", None, None), (70_001, None, "en", None, None), (70_002, "word " * 150_000, "en", "s", 1), (70_003, "\n\n", None, "s", 2)]
    docs = docs.union(spark.createDataFrame(odd, docs.schema))
    names = ["n__", "k__", "id__", "score", "leaked_items", "held", "shard_run", "shard_tier", "arrival__", "rep", "key", "rate", "n", "hot"]
    docs = docs.select("*", *[F.lit(i).alias(x) for i, x in enumerate(names)])
    for some in (docs, docs.limit(0)):
        seen = some
        for name, stage in P.STAGES[:-1]:
            seen = stage(spark, seen, sf).cache()
            assert seen.columns == docs.columns, name
            assert all(r[x] == i for r in seen.select(*names).collect() for i, x in enumerate(names)), name
        last = P.STAGES[-1][1](spark, seen, sf)
        assert last.columns[: len(docs.columns)] == docs.columns and last.count() == seen.count()
        assert some is not docs or seen.where("doc_id = 70002").count() == 1
