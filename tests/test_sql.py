from sitereach.sql import register

SF = "/root/testdata/sf0.001"


def test_sql_surface(spark):
    register(spark, SF)
    assert spark.sql("select count(*) from city_users").first()[0] == 150
    assert spark.sql("select coin32('a|1')").first()[0] >= 0
    assert spark.read.format("reach_city").option("side", 3).load().count() == 24
    rows = spark.sql("select * from reverse_walk(1, 5L, map(5L, array(6L)), 1)").collect()
    assert (rows[0]["step"], rows[0]["usr"]) == (0, 5) and len(rows) == 2
