from __future__ import annotations

import pyarrow as pa
from pyspark.sql import functions as F

from gramdist.llm.common import BATCH_BYTES, batch, driver_gives_back, join_groups, map_batches


def test_hot_keys_join_whole(spark):
    rows = spark.range(6000).select(F.when(F.col("id") < 3500, 0).otherwise(F.col("id") % 50).alias("k"), "id")
    groups = rows.groupBy("k").agg(F.count("*").alias("n"), F.max("id").alias("top"))
    got = join_groups(rows, groups, "k", "n", 6000)
    want = rows.join(groups, "k")
    assert got.count() == 6000 and got.select(sorted(got.columns)).exceptAll(want.select(sorted(want.columns))).isEmpty()


def test_nothing_is_broadcast_where_no_key_is_hot(spark):
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        rows = spark.range(6000).select((F.col("id") % 50).alias("k"), "id")
        got = join_groups(rows, rows.groupBy("k").agg(F.count("*").alias("n")), "k", "n", 6000)
        assert got.count() == 6000 and got.columns == ["k", "id", "n"]
        assert "Broadcast" not in got._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_the_drivers_jvm_gives_back_what_it_freed(spark):
    jvm = spark.sparkContext._jvm
    heap = lambda: jvm.java.lang.management.ManagementFactory.getMemoryMXBean().getHeapMemoryUsage()
    jvm.org.apache.commons.lang3.StringUtils.repeat("x", 1 << 27)  # garbage at once
    driver_gives_back(spark)
    assert heap().getUsed() < heap().getMax() // 2 and spark.range(3).count() == 3


def test_batches_are_bounded_in_bytes(spark):
    def sizes(batches):
        for b in batches:
            yield batch(n=pa.array([b.num_rows]), size=pa.array([b.nbytes]))

    rows = spark.range(0, 6000, 1, 1).select("id", F.expr("repeat('x', 3000)").alias("text"))
    got = map_batches(rows, sizes, "n long, size long").collect()
    assert sum(r.n for r in got) == 6000 and max(r.size for r in got) < 2 * BATCH_BYTES
