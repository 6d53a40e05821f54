"""The folded average of a user with more events than a million."""

from assetmill import workloads


def test_fold_takes_the_latest_events(spark, tmp_path):
    rows = spark.range(1_000_002).selectExpr("id AS event_id", "timestamp_micros(id) AS ts", "1L AS user_id", "IF(id = 1000001, 10D, 0D) AS value")
    rows.write.parquet(str(tmp_path / "events.parquet"))
    r = workloads.queries()["w19_shadow_equivalence"](spark, str(tmp_path)).first()
    assert (r.folded, r.unrolled) == (1.0, 1.0)
