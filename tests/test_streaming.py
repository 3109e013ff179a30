"""Streams against the same rows at rest."""

from pyspark.sql import functions as F

from pushwave.streaming import arcs as A

SF = "/root/testdata/sf0.001"


def test_windows_and_state_equal_the_static_twin(spark):
    events = spark.read.parquet(f"{SF}/events.parquet")
    got = A.run(A.successive_types(A.source(spark, SF)))
    assert got.count() == events.count() - events.select("user_id").distinct().count()
    top = events.agg(F.max("ts")).first()[0]
    daily = A.run(A.daily_counts(A.source(spark, SF)))
    static = events.groupBy(F.date_trunc("day", "ts").alias("day"), "user_id").count()
    assert daily.join(static, ["day", "user_id"]).filter("n <> count").count() == 0
    assert daily.count() == static.filter(F.col("day") + F.expr("interval 25 hours") <= F.lit(top)).count()
    assert A.run(A.distinct_pairs(A.source(spark, SF))).count() == events.select("user_id", "event_type").distinct().count()


def test_joins_and_batches(spark):
    answers = spark.createDataFrame([(1, 0.5), (2, 0.25)], "v long, score double")
    events = spark.read.parquet(f"{SF}/events.parquet")
    assert A.run(A.with_answers(A.source(spark, SF), answers)).count() == events.filter("user_id in (1, 2)").count()
    seen = []
    A.run_batches(A.source(spark, SF), lambda df, i: seen.append(df.count()))
    assert sum(seen) == events.count()
    assert A.run(A.sessions(A.source(spark, SF))).agg(F.sum("n")).first()[0] <= events.count()
    assert A.run(A.sliding_counts(A.source(spark, SF))).count() > 0
