"""A survivor for every near-duplicate cluster."""

from assetmill.operators import dedup


def test_representative(spark):
    rows = [(1, 10, 8, 8, 2), (1, 11, 8, 16, 1), (1, 12, 16, 8, 3), (1, 13, 16, 8, 3), (2, 20, 8, 8, 1)]
    got = dedup.representative(spark.createDataFrame(rows, "cluster long, doc_id long, width int, height int, quality_tier int").repartition(3))
    assert sorted(map(tuple, got.collect())) == [(1, 12, 4), (2, 20, 1)]
