"""Box search over vectors: which vectors are asked for, and the arm of 16 components."""

from apcube.queries import experiments


def test_queries_are_the_ids_divisible_by_20(spark, sf):
    want = {r[0] for r in spark.read.parquet(f"{sf}/embeddings.parquet").where("vec_id % 20 = 0").select("vec_id").collect()}
    assert {r["id"] for r in experiments.vec_boxes(spark, sf)[2].select("id").collect()} == want


def test_sixteen_components(spark, sf):
    row = experiments.vec_quality(spark, sf, ("plain",), dims=experiments.VEC_DIMS_16).first()
    assert (row["components"], row["precision"]) == (16, 1.0) and row["wanted"] > 0 and 0 <= row["recall"] <= 1
