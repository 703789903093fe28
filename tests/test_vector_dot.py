"""The query over all vectors."""

import __spark_entry__ as entry_module


def test_every_vector_has_its_product(spark, sf):
    got = entry_module.queries()["op_vector_dot"](spark, sf)
    given = spark.read.parquet(f"{sf}/embeddings.parquet")
    assert got.count() == given.filter("label is not null").select("vec_id", "label").distinct().count() > 40
