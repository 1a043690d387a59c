from pyspark.sql import functions as F

from locpref.functions import sqlface
from locpref.operators import factorization, predict
from locpref.sources.planted import PlantedSource


def test_planted_source_as_table_and_stream(spark, tmp_path):
    spark.dataSource.register(PlantedSource)
    opts = {"users": "60", "items": "24", "rank": "2", "density": "0.6", "users_per_task": "17"}
    df = spark.read.format("planted_preferences").options(**opts).load()
    assert df.select("user_id").distinct().count() == 60
    assert df.count() == df.select("user_id", "item_id").distinct().count()
    assert abs(df.agg(F.avg((F.col("rating") != F.col("truth")).cast("double"))).first()[0] - 0.05) < 0.03
    q = spark.readStream.format("planted_preferences").options(users_per_batch="25", **opts).load().writeStream.format("parquet").option("path", f"{tmp_path}/o").option("checkpointLocation", f"{tmp_path}/c").start()
    q.processAllAvailable()
    q.stop()
    assert sorted(spark.read.parquet(f"{tmp_path}/o").collect()) == sorted(df.collect())
    m = factorization.fit_plain(df, factorization.FitConfig(d=3, rounds=40))
    right = predict.decide(predict.score(df, m.X, m.Z, 3), predict.mean_threshold(m.X, m.Z, 3)).agg(F.avg((F.col("decision") == F.col("truth")).cast("double"))).first()[0]
    assert right > 0.75


def test_sql_functions(spark):
    sqlface.register(spark)
    r = spark.sql("SELECT time_slot(timestamp'2019-02-01 14:00:00', 6) AS s, flip_probability(0.0D) AS p, bit_weight(1, 0.5D) AS w, dot(array(1D, 2D), array(3D, 4D)) AS d").first()
    assert tuple(r) == (2, 1.0, 1.5, 11.0)
    ladder = spark.sql("SELECT * FROM time_ladder(14)").collect()
    assert {(x.width, x.slot) for x in ladder} == {(w, 14 // w) for w in (1, 2, 3, 4, 6, 8, 12, 24)}
    m = spark.sql("SELECT mean_vector(v) AS m FROM VALUES (array(1D, 2D)), (array(3D, 6D)) t(v)").first().m
    assert m == [2.0, 4.0]
