from graphwave.functions.udfs import bfs_sql, register
from graphwave.sources.kronecker import edge_of


def test_sql_functions(spark):
    register(spark)
    spark.range(0, 1000, 7).createOrReplaceTempView("members")
    got = spark.sql("SELECT wah_positions(p, 1000L) AS s FROM (SELECT wah_build(id, 1000L) AS p FROM members)").first()["s"]
    assert got == list(range(0, 1000, 7))
    assert spark.sql("SELECT size(wah_words(array(0L, 500L), 1000L)) AS n").first()["n"] == 5
    assert bytes(spark.sql("SELECT inflate(deflate(cast('some text' AS binary), 6)) AS t").first()["t"]) == b"some text"
    assert sorted(tuple(r) for r in spark.sql("SELECT * FROM kronecker(4, 2, 42)").collect()) == sorted(edge_of(i, 4, 42) for i in range(32))
    got = spark.sql("SELECT slot FROM (SELECT wah_build(id, 1000L) AS p FROM members), LATERAL wah_members(p, 1000)").collect()
    assert sorted(r[0] for r in got) == list(range(0, 1000, 7))


def test_search_of_a_view(spark):
    spark.createDataFrame([(0, 1), (1, 2), (4, 5)], "u long, v long").createOrReplaceTempView("links")
    bfs_sql(spark, "links", 0, "found", p=2, method="wah_sieved")
    assert sorted(tuple(r) for r in spark.sql("SELECT vid, level, parent FROM found").collect()) == [(0, 0, 0), (1, 1, 0), (2, 2, 1)]
