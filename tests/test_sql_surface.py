from gossipkit.functions import sql
from gossipkit.functions.columns import uniform
from pyspark.sql import functions as F


def test_sql_functions(spark):
    sql.register(spark)
    r = spark.sql("SELECT soft_threshold(-0.7D, 0.5D) AS z, dither(42, 1, 3, 9) AS u, level_of(0.5D, 0D, 1D, 4, 0.2D) AS k, level_of(0D, 0D, 1D, 4, 0.2D) AS zero").first()
    assert abs(r.z + 0.2) < 1e-12 and (r.k, r.zero) == (2, -1)
    assert r.u == spark.range(1).select(uniform(42, 1, F.lit(3), F.lit(9)).alias("u")).first().u
    back = spark.sql("SELECT levelset_decode(levelset_encode(array(0, 0, 2, -1, 1, 0), 2)) AS s").first().s
    assert list(back) == [0, 0, 2, -1, 1, 0]


def test_table_functions(spark):
    sql.register(spark)
    assert spark.sql("SELECT * FROM topology('ring', 10)").count() == 30
    hand = [0, 0, 2, 0, 1, 0, 0, 2, 0, 0, 1, 0]
    spark.createDataFrame([(0, i, s) for i, s in enumerate(hand)], "site int, coord int, sym int").createOrReplaceTempView("hand")
    rows = spark.sql("SELECT * FROM level_runs(TABLE(hand) PARTITION BY site ORDER BY coord)").collect()
    assert sorted((r["rank"], r.seq, r.gap) for r in rows) == [(1, 1, 4), (1, 2, 5), (2, 1, 2), (2, 2, 3)]
