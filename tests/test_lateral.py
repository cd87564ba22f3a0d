"""The last order of every customer, whatever the exchanges do to the order of rows."""

import duckdb
from pyspark.sql import functions as F

from hybridrec import operators


def test_last_order_of_a_customer_in_a_large_table(spark, tmp_path):
    """The rows come in the order that the exchange mixes up."""
    orders = spark.range(200_000, numPartitions=16).select(F.col("id").alias("o_orderkey"), (F.col("id") % 50).alias("o_custkey"), F.timestamp_seconds(F.pmod(F.hash("id"), F.lit(100_000)).cast("long")).cast("timestamp_ntz").alias("o_orderdate"))
    orders.coalesce(1).write.parquet(f"{tmp_path}/orders.parquet")
    spark.range(60).select(F.col("id").alias("c_custkey")).coalesce(1).write.parquet(f"{tmp_path}/customer.parquet")
    con = duckdb.connect()
    for t in ("orders", "customer"):
        con.execute(f"create view {t} as select * from '{tmp_path}/{t}.parquet/*.parquet'")
    run, sql = operators.OPS["op_subquery_lateral"]
    got = run(spark, str(tmp_path))
    assert sorted(map(tuple, got.select("c_custkey", "o_orderkey").collect())) == sorted(con.execute(sql).fetchall())
    assert "rangepartitioning" not in got._jdf.queryExecution().executedPlan().toString()
