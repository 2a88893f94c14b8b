"""Queries on the relational surface around sketches: set algebra, diffs, rollups, ranks, lateral and interval joins, sampling."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily
from ..operators import cells
from ..operators import reserve as R
from ..operators import similarity as S
from ..operators import streams
from ..sources import collections as col
from ..sources.tables import read
from ..streaming.live import insert_delete_pairs


def register(query) -> None:
    from .catalog import FEW, LIVE, RESERVE, UPDATES, USERS

    half = f"(SELECT set_id, element FROM (SELECT set_id, element, arg_max(op, seq) AS op FROM ({UPDATES}) WHERE seq <= (SELECT max(seq) // 2 FROM ({UPDATES})) GROUP BY 1, 2) WHERE op = 1)"

    def at_half(spark: SparkSession, sf_dir: str) -> DataFrame:
        updates = col.event_updates(spark, sf_dir)
        upto = updates.agg(F.floor(F.max("seq") / 2).alias("upto"))
        return streams.members_at(updates.join(F.broadcast(upto), F.col("seq") <= F.col("upto")))

    @query(f"""SELECT 'came' AS change, * FROM (SELECT * FROM ({LIVE}) EXCEPT ALL SELECT * FROM {half}) UNION ALL
SELECT 'left', * FROM (SELECT * FROM {half} EXCEPT ALL SELECT * FROM ({LIVE}))""")
    def members_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
        """What came and what left between the middle of the stream and its end."""
        then, now = at_half(spark, sf_dir), col.user_keys_live(spark, sf_dir)
        came = now.exceptAll(then).withColumn("change", F.lit("came"))
        return came.unionByName(then.exceptAll(now).withColumn("change", F.lit("left")))

    @query(f"SELECT * FROM ({LIVE}) INTERSECT SELECT * FROM {half}")
    def members_kept(spark: SparkSession, sf_dir: str) -> DataFrame:
        return col.user_keys_live(spark, sf_dir).intersect(at_half(spark, sf_dir))

    @query("SELECT lang, source, count(*) AS docs, sum(n_chars)::BIGINT AS chars, count(*) FILTER (toxic = 1) AS toxic FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ROLLUP (lang, source)")
    def document_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
        docs = read(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars").join(read(spark, sf_dir, "labels").select("doc_id", "toxic"), "doc_id", "left")
        return docs.rollup("lang", "source").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_chars").alias("chars"), F.count(F.when(F.col("toxic") == 1, 1)).alias("toxic"))

    @query("""SELECT c_nationkey, o_orderpriority, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey
GROUP BY GROUPING SETS ((c_nationkey), (o_orderpriority), ())""")
    def order_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
        both = read(spark, sf_dir, "orders").select("o_custkey", "o_orderpriority").join(read(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
        n, p = F.col("c_nationkey"), F.col("o_orderpriority")
        return both.groupingSets([[n], [p], []], n, p).agg(F.count(F.lit(1)).alias("orders"))

    @query(f"""SELECT set_id, n, round(percent_rank() OVER (ORDER BY n), 9) AS share_below, ntile(4) OVER (ORDER BY n, set_id)::INT AS quarter,
rank() OVER (ORDER BY n)::INT AS place, dense_rank() OVER (ORDER BY n)::INT AS step FROM (SELECT set_id, count(*) AS n FROM ({USERS}) GROUP BY 1)""")
    def size_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Places of set sizes: one row a set, for choosing thresholds on collections of bounded number."""
        n = col.user_keys(spark, sf_dir).groupBy("set_id").agg(F.count(F.lit(1)).alias("n"))
        # Places follow from the histogram of sizes, which is all that one task sees; ties are numbered size by size.
        w = Window.orderBy("n")
        below = F.coalesce(F.sum("sets").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        counts = n.groupBy("n").agg(F.count(F.lit(1)).alias("sets")).select("n", below.alias("below"), F.row_number().over(w).alias("step"))
        every = F.broadcast(n.agg(F.count(F.lit(1)).alias("m")))  # one row
        at = F.col("below") + F.row_number().over(Window.partitionBy("n").orderBy("set_id")) - 1
        whole, rest = F.floor(F.col("m") / 4), F.col("m") % 4
        quarter = F.when(F.col("at") < rest * (whole + 1), F.floor(F.col("at") / (whole + 1))).otherwise(rest + F.floor((F.col("at") - rest * (whole + 1)) / F.greatest(whole, F.lit(1)))) + 1
        placed = n.join(counts, "n").withColumn("at", at).join(every)
        share = F.when(F.col("m") > 1, F.col("below") / (F.col("m") - 1)).otherwise(0.0)
        return placed.select("set_id", "n", F.round(share, 9).alias("share_below"), quarter.cast("int").alias("quarter"), (F.col("below") + 1).cast("int").alias("place"), "step")

    @query("""SELECT c_custkey, o_orderkey, o_totalprice FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)""")
    def lateral_top_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
        read(spark, sf_dir, "customer").createOrReplaceTempView("setstream_customer")
        read(spark, sf_dir, "orders").createOrReplaceTempView("setstream_orders")
        return spark.sql(
            "SELECT c_custkey, o_orderkey, o_totalprice FROM setstream_customer, "
            "LATERAL (SELECT o_orderkey, o_totalprice FROM setstream_orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)"
        )

    @query("SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s_suppkey AND l_returnflag = 'R' AND l_quantity > (SELECT avg(l_quantity) FROM lineitem))")
    def suppliers_with_large_returns(spark: SparkSession, sf_dir: str) -> DataFrame:
        read(spark, sf_dir, "supplier").createOrReplaceTempView("setstream_supplier")
        read(spark, sf_dir, "lineitem").createOrReplaceTempView("setstream_lineitem")
        return spark.sql(
            "SELECT s_suppkey FROM setstream_supplier WHERE EXISTS (SELECT 1 FROM setstream_lineitem WHERE l_suppkey = s_suppkey AND l_returnflag = 'R' "
            "AND l_quantity > (SELECT avg(l_quantity) FROM setstream_lineitem))"
        )

    @query(f"""SELECT p.set_id, p.element, p.ts AS put_at, d.ts AS out_at FROM (SELECT * FROM ({UPDATES}) WHERE op = 1) p JOIN (SELECT * FROM ({UPDATES}) WHERE op = -1) d
ON p.set_id = d.set_id AND p.element = d.element AND d.ts >= p.ts AND d.ts <= p.ts + INTERVAL 1 DAY""")
    def deletes_within_a_day(spark: SparkSession, sf_dir: str) -> DataFrame:
        updates = col.event_updates(spark, sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))
        return insert_delete_pairs(updates.where("op = 1"), updates.where("op = -1"))

    @query(f"SELECT set_id, count(*) AS n FROM ({USERS}) GROUP BY 1 HAVING count(*) >= 30")
    def size_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
        return col.user_keys(spark, sf_dir).groupBy("set_id").agg(F.count(F.lit(1)).alias("n")).where("n >= 30")

    @query()
    def sampled_pair_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Error of estimates over a sample of pairs, stratified by tenths of similarity: a report, not an operator."""
        found = cells.signature_errors(col.user_keys(spark, sf_dir), [HashFamily.affine(32, 3)], by_tenth=True, half=True)
        return found.drop("k")

    @query("SELECT 0::BIGINT AS differing")
    def compact_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Slots that differ between a sketch, and the same sketch made compact and expanded again."""
        sketch = R.reserve_init(col.user_keys_live(spark, sf_dir), FEW, RESERVE)
        back = R.expand(R.compact(sketch), FEW).withColumnRenamed("slots", "again")
        return sketch.join(back, "set_id", "full").agg(F.count(F.when(~F.col("slots").eqNullSafe(F.col("again")), 1)).alias("differing"))
