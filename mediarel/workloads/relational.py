"""Relational operators that surround the methods: joins, aggregations, windows, sets, scans and scalar functions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None):
    """Registers a function of (table reader) under its name, with DuckDB SQL for the same rows."""

    def add(f):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            return f(lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet"))

        run.__name__, run.__doc__ = f.__name__, f.__doc__
        QUERIES[f.__name__] = run
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


# Joins ---------------------------------------------------------------------------------------------------------------

_NATIONS = "SELECT s_suppkey, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey"


@query(_NATIONS)
def join_broadcast(t):
    """``nation`` has a fixed number of rows, so it may be broadcast."""
    return t("supplier").join(F.broadcast(t("nation")), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")


_ORDERS = "SELECT o_custkey, CAST(count(*) AS BIGINT) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey"


def _order_lines(t, hint):
    joined = t("orders").select("o_orderkey", "o_custkey").join(t("lineitem").select("l_orderkey").hint(hint), F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.groupBy("o_custkey").agg(F.count("*").alias("n"))


@query(_ORDERS)
def join_sortmerge(t):
    return _order_lines(t, "merge")


@query(_ORDERS)
def join_shufflehash(t):
    return _order_lines(t, "shuffle_hash")


@query("SELECT c_custkey, o_orderkey FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_totalprice > 300000) ON o_custkey = c_custkey")
def join_left(t):
    return t("customer").join(t("orders").where("o_totalprice > 300000"), F.col("o_custkey") == F.col("c_custkey"), "left").select("c_custkey", "o_orderkey")


@query("SELECT n_name, s_suppkey FROM (SELECT * FROM supplier WHERE s_acctbal > 5000) RIGHT JOIN nation ON s_nationkey = n_nationkey")
def join_right(t):
    return t("supplier").where("s_acctbal > 5000").join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey"), "right").select("n_name", "s_suppkey")


@query("SELECT a.doc_id AS label_id, d.doc_id FROM (SELECT doc_id FROM labels WHERE quality = 0) a FULL JOIN (SELECT doc_id FROM documents WHERE lang = 'fr') d ON a.doc_id = d.doc_id")
def join_full(t):
    low = t("labels").where("quality = 0").select(F.col("doc_id").alias("label_id"))
    return low.join(t("documents").where("lang = 'fr'").select("doc_id"), F.col("label_id") == F.col("doc_id"), "full")


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)")
def join_semi(t):
    return t("documents").join(t("labels").where("toxic = 1"), "doc_id", "left_semi").select("doc_id")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(t):
    return t("documents").join(t("labels"), "doc_id", "left_anti").select("doc_id")


@query("SELECT a.n_name AS low, b.n_name AS high FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_name > b.n_name")
def join_theta(t):
    """Brute-force comparison for oracles of pruned plans; both sides have a fixed size."""
    n = t("nation")
    a, b = n.select(F.col("n_name").alias("low"), F.col("n_regionkey").alias("ra")), n.select(F.col("n_name").alias("high"), F.col("n_regionkey").alias("rb"))
    return a.join(F.broadcast(b), (F.col("ra") < F.col("rb")) & (F.col("low") > F.col("high"))).select("low", "high")


@query("""SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM customer JOIN orders ON o_custkey = c_custkey) WHERE k <= 2""")
def join_lateral(t):
    """Top two orders of each customer: a lateral subquery, which Spark decorrelates into a join and a ranked window.

    The rank stands in the subquery because the rewrite of a correlated LIMIT loses its order at the shuffle.
    """
    spark = t("customer").sparkSession
    return spark.sql(
        """SELECT c_custkey, o_orderkey FROM {customer} JOIN LATERAL
           (SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) AS k FROM {orders} WHERE o_custkey = c_custkey) WHERE k <= 2""",
        customer=t("customer"), orders=t("orders"),
    )


@query("SELECT doc_id, count(*) AS n_lines, CAST(max(length(line)) AS BIGINT) AS longest FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) GROUP BY doc_id")
def join_lateral_function(t):
    """A lateral join with a table function of the outer row: the lines of every text."""
    docs = t("documents").select("doc_id", "text")
    lines = docs.sparkSession.tvf.explode(F.split(F.col("text").outer(), "\n")).toDF("line")
    return docs.lateralJoin(lines).groupBy("doc_id").agg(F.count("*").alias("n_lines"), F.max(F.length("line")).cast("bigint").alias("longest"))


# Aggregations --------------------------------------------------------------------------------------------------------


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, round(min(l_extendedprice), 2) AS low, round(max(l_extendedprice), 2) AS high FROM lineitem GROUP BY l_returnflag, l_linestatus")
def agg_basic(t):
    return t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.round(F.min("l_extendedprice"), 2).alias("low"), F.round(F.max("l_extendedprice"), 2).alias("high")
    )


@query("SELECT user_id, string_agg(event_type, '>' ORDER BY event_id) AS path FROM events GROUP BY user_id")
def agg_collect(t):
    return t("events").groupBy("user_id").agg(F.concat_ws(">", F.transform(F.array_sort(F.collect_list(F.struct("event_id", "event_type"))), lambda x: x["event_type"])).alias("path"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")
def agg_distinct(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@query(None)
def agg_approx(t):
    """Sketches: approximate distinct counts and medians; a test holds them within their bounds on random rows."""
    return t("lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("median_price"))


_CUBE = "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {how}"


@query(_CUBE.format(how="GROUPING SETS ((l_returnflag), (l_linestatus), ())"))
def agg_grouping_sets(t):
    spark = t("lineitem").sparkSession
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM {l} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())", l=t("lineitem"))


@query(_CUBE.format(how="CUBE (l_returnflag, l_linestatus)"))
def agg_cube(t):
    return t("lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query(_CUBE.format(how="ROLLUP (l_returnflag, l_linestatus)"))
def agg_rollup(t):
    return t("lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT event_type, count(*) FILTER (value > 100) AS high, bool_or(value > 300) AS any_huge, arg_max(event_id, value) AS top_id, arg_min(event_id, value) AS low_id FROM events GROUP BY event_type")
def agg_conditional(t):
    """Of events with the same extreme value the first counts, that with the smallest ``event_id``; so the row does not depend on partitions."""
    known = F.col("value").isNotNull() & F.col("event_id").isNotNull()
    place = lambda key: F.when(known, F.struct("value", key.alias("key")))
    return t("events").groupBy("event_type").agg(
        F.count_if(F.col("value") > 100).alias("high"), F.bool_or(F.col("value") > 300).alias("any_huge"),
        F.max_by("event_id", place(F.bitwise_not("event_id"))).alias("top_id"), F.min_by("event_id", place(F.col("event_id"))).alias("low_id"),
    )


@query("SELECT l_returnflag, round(median(l_extendedprice), 4) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY l_returnflag")
def agg_percentile(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_extendedprice", F.lit(0.5)), 4).alias("median"), F.round(F.percentile("l_extendedprice", F.lit(0.9)), 4).alias("p90"))


@query("SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase, count(*) FILTER (event_type = 'error') AS error FROM events GROUP BY user_id")
def agg_pivot(t):
    pivoted = t("events").groupBy("user_id").pivot("event_type", ["click", "purchase", "error"]).agg(F.count(F.lit(1)))
    return pivoted.na.fill(0)


@query("SELECT l_returnflag, 'qty' AS measure, round(sum(l_quantity), 2) AS total FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 'price', round(sum(l_extendedprice), 2) FROM lineitem GROUP BY 1")
def agg_unpivot(t):
    wide = t("lineitem").groupBy("l_returnflag").agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.sum("l_extendedprice"), 2).alias("price"))
    return wide.unpivot("l_returnflag", ["qty", "price"], "measure", "total")


@query("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
def agg_listagg(t):
    return t("nation").groupBy("n_regionkey").agg(F.concat_ws(",", F.array_sort(F.collect_list("n_name"))).alias("names"))


@query("SELECT label, d, round(avg(x), 5) AS x FROM (SELECT label, unnest(range(64)) AS d, unnest(CAST(embedding AS DOUBLE[])) AS x FROM embeddings) GROUP BY label, d")
def agg_vector_mean(t):
    """Element-wise mean of vectors: positions are grouped, so partial sums combine before the shuffle."""
    each = t("embeddings").select("label", F.posexplode(F.col("embedding").cast("array<double>")).alias("d", "x"))
    return each.groupBy("label", F.col("d").cast("bigint").alias("d")).agg(F.round(F.avg("x"), 5).alias("x"))


@query("SELECT label, d, round(avg(x), 5) AS x FROM (SELECT label, unnest(range(64)) AS d, unnest(CAST(embedding AS DOUBLE[])) AS x FROM embeddings) GROUP BY label, d")
def udaf_vector_mean(t):
    """The same mean by a grouped-aggregate Python UDF."""
    from mediarel.functions.udfs import vector_mean

    means = t("embeddings").groupBy("label").agg(vector_mean(F.col("embedding").cast("array<double>")).alias("m"))
    return means.select("label", F.posexplode("m").alias("d", "x")).select("label", F.col("d").cast("bigint").alias("d"), F.round("x", 5).alias("x"))


_SHIPPED = "SELECT l_suppkey AS source_id, l_linenumber * 10 + l_partkey % 50 AS start_ms, l_linenumber * 10 + l_partkey % 50 + l_orderkey % 7 + 1 AS end_ms FROM lineitem"
_UNION_MS = f"""WITH s AS (SELECT source_id, start_ms, end_ms, coalesce(max(end_ms) OVER (PARTITION BY source_id ORDER BY start_ms, end_ms ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), start_ms) AS reach FROM ({_SHIPPED}))
SELECT source_id, CAST(sum(greatest(end_ms - greatest(start_ms, reach), 0)) AS BIGINT) AS union_ms FROM s GROUP BY source_id"""


def _shipped(t):
    start = F.expr("bigint(l_linenumber * 10 + l_partkey % 50)")
    return t("lineitem").select(F.col("l_suppkey").alias("source_id"), start.alias("start_ms"), (start + F.expr("bigint(l_orderkey % 7 + 1)")).alias("end_ms"))


@query(_UNION_MS)
def udaf_union_ms(t):
    """Length of a union of intervals by a grouped-aggregate Python UDF."""
    from mediarel.functions.udfs import union_ms

    return _shipped(t).groupBy("source_id").agg(union_ms("start_ms", "end_ms").alias("union_ms"))


@query(_UNION_MS)
def apply_in_arrow(t):
    """The same by a grouped function on Arrow tables."""

    def union(group):
        import numpy as np
        import pyarrow as pa

        ordered = group.sort_by("start_ms")
        start, end = (np.asarray(ordered.column(c)) for c in ("start_ms", "end_ms"))
        reach = np.concatenate((start[:1], np.maximum.accumulate(end)[:-1]))
        return pa.table({"source_id": ordered.column("source_id").slice(0, 1), "union_ms": pa.array([int(np.maximum(end - np.maximum(start, reach), 0).sum())], pa.int64())})

    return _shipped(t).groupBy("source_id").applyInArrow(union, "source_id bigint, union_ms bigint")


@query("SELECT o_custkey AS source_id, count(*) AS n_left, (SELECT count(*) FROM events WHERE user_id = o_custkey) AS n_right FROM orders GROUP BY o_custkey")
def cogroup_arrow(t):
    """Predictions and references of one key side by side: a cogrouped function on Arrow tables."""

    def sizes(left, right):
        import pyarrow as pa

        if not left.num_rows:
            return pa.table({"source_id": pa.array([], pa.int64()), "n_left": pa.array([], pa.int64()), "n_right": pa.array([], pa.int64())})
        return pa.table({"source_id": left.column("source_id").slice(0, 1), "n_left": pa.array([left.num_rows], pa.int64()), "n_right": pa.array([right.num_rows], pa.int64())})

    left = t("orders").select(F.col("o_custkey").alias("source_id"), "o_orderkey").groupBy("source_id")
    right = t("events").select(F.col("user_id").alias("source_id"), "event_id").groupBy("source_id")
    return left.cogroup(right).applyInArrow(sizes, "source_id bigint, n_left bigint, n_right bigint")


@query(_UNION_MS)
def udtf_union_spans(t):
    """The same by an Arrow table function that streams a partition's batches."""
    from mediarel import sql

    rows = _shipped(t)
    sql.register(rows.sparkSession)
    return rows.sparkSession.sql("SELECT source_id, union_ms FROM union_spans(TABLE({r}) PARTITION BY source_id ORDER BY start_ms)", r=rows)


@query("""WITH p AS (SELECT a.vec_id AS a, b.vec_id AS b, CAST(a.embedding AS DOUBLE[]) AS x, CAST(b.embedding AS DOUBLE[]) AS y FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1)
SELECT a, b, round(list_sum(list_transform(list_zip(x, y), lambda z: z[1] * z[2])) / sqrt(list_sum(list_transform(x, lambda v: v * v)) * list_sum(list_transform(y, lambda v: v * v))), 6) AS score FROM p""")
def udf_cosine(t):
    """Cosine of neighbouring vectors by a scalar Arrow UDF."""
    from mediarel.functions.udfs import cosine_batch

    v = t("embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    pairs = v.select(F.col("vec_id").alias("a"), F.col("e").alias("x")).join(v.select(F.col("vec_id").alias("b"), F.col("e").alias("y")), F.expr("b = a + 1"))
    return pairs.select("a", "b", F.round(cosine_batch("x", "y"), 6).alias("score"))


@query("SELECT p_partkey, greatest(CAST(p_size AS BIGINT) - 5, 0) AS start_ms, least(CAST(p_size AS BIGINT) + 20, 50) AS end_ms FROM part")
def sql_pad_window(t):
    from mediarel import sql

    df = t("part")
    sql.register(df.sparkSession)
    return df.sparkSession.sql("SELECT p_partkey, w.start_ms, w.end_ms FROM (SELECT p_partkey, pad_window(bigint(p_size), bigint(p_size), 5L, 20L, 50L) AS w FROM {p})", p=df)


@query("SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey HAVING count(*) > 600")
def agg_having(t):
    return t("lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n")).where("n > 600")


# Windows -------------------------------------------------------------------------------------------------------------


@query("""SELECT p_partkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS q, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd
FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey), v AS (PARTITION BY p_brand ORDER BY p_size)""")
def win_ranking(t):
    w, v = Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    big = lambda c: c.cast("bigint")
    return t("part").select(
        "p_partkey", big(F.row_number().over(w)).alias("rn"), big(F.rank().over(v)).alias("rk"), big(F.dense_rank().over(v)).alias("dr"), big(F.ntile(4).over(w)).alias("q"),
        F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"),
    )


@query("""SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after, first_value(event_id) OVER w AS first_id, nth_value(event_id, 2) OVER w AS second_id,
last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER w AS bought FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)""")
def win_analytic(t):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return t("events").select(
        "event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after"), F.first("event_id").over(w).alias("first_id"), F.nth_value("event_id", 2).over(w).alias("second_id"),
        F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("bought"),
    )


@query("SELECT event_id, round(sum(value) OVER w, 4) AS total, round(max(value) OVER v, 6) AS top FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), v AS (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING)")
def win_rows(t):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return t("events").select("event_id", F.round(F.sum("value").over(w.rowsBetween(-2, 0)), 4).alias("total"), F.round(F.max("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 6).alias("top"))


_MS = "date_diff('microsecond', TIMESTAMP '2024-01-01', ts) // 600000"
_TS = "timestampdiff(MICROSECOND, timestamp_ntz'2024-01-01 00:00:00', ts) div 600000"


@query(f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY pos RANGE BETWEEN 10000 PRECEDING AND 10000 FOLLOWING) AS near FROM (SELECT event_id, user_id, {_MS} AS pos FROM events)")
def win_range(t):
    w = Window.partitionBy("user_id").orderBy("at").rangeBetween(-10_000, 10_000)
    return t("events").select("event_id", "user_id", F.expr(_TS).alias("at")).select("event_id", F.count("*").over(w).alias("near"))


@query(f"""WITH e AS (SELECT event_id, user_id, {_MS} AS pos FROM events), g AS (SELECT *, CASE WHEN pos - lag(pos) OVER (PARTITION BY user_id ORDER BY pos, event_id) < 60000 THEN 0 ELSE 1 END AS o FROM e),
s AS (SELECT *, sum(o) OVER (PARTITION BY user_id ORDER BY pos, event_id ROWS UNBOUNDED PRECEDING) AS no FROM g)
SELECT user_id, CAST(no AS BIGINT) AS no, count(*) AS n, min(pos) AS start_ms, max(pos) AS end_ms FROM s GROUP BY user_id, no""")
def win_session(t):
    """Gaps and islands by hand: a new session after a minute of source time without events."""
    w = Window.partitionBy("user_id").orderBy("at", "event_id")
    e = t("events").select("event_id", "user_id", F.expr(_TS).alias("at"))
    opened = e.withColumn("o", F.when(F.col("at") - F.lag("at").over(w) < 60_000, 0).otherwise(1)).withColumn("no", F.sum("o").over(w))
    return opened.groupBy("user_id", "no").agg(F.count("*").alias("n"), F.min("at").alias("start_ms"), F.max("at").alias("end_ms"))


@query("SELECT CAST(date_trunc('hour', ts) AS VARCHAR) AS hour, count(*) AS n FROM events GROUP BY 1")
def win_tumbling(t):
    hours = t("events").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return hours.select(F.date_format(F.col("w.start"), "yyyy-MM-dd HH:mm:ss").alias("hour"), "n")


@query("""WITH s AS (SELECT unnest([0, 1]) AS k) SELECT CAST(date_trunc('hour', ts) - to_hours(k) AS VARCHAR) AS start, count(*) AS n FROM events CROSS JOIN s GROUP BY 1""")
def win_sliding(t):
    spans = t("events").groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return spans.select(F.date_format(F.col("w.start"), "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS o FROM events),
s AS (SELECT *, sum(o) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM g) SELECT user_id, n, count(*) AS n_sessions FROM (SELECT user_id, no, count(*) AS n FROM s GROUP BY user_id, no) GROUP BY user_id, n""")
def win_session_gap(t):
    sessions = t("events").groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n"))
    return sessions.groupBy("user_id", "n").agg(F.count("*").alias("n_sessions"))


# Sorts, limits, sets, samples ----------------------------------------------------------------------------------------


@query("SELECT c_custkey, row_number() OVER (ORDER BY c_acctbal DESC NULLS LAST, c_custkey) AS place FROM customer")
def sort_global(t):
    """A range-partitioned sort numbered in order: partition sizes give each partition its first place."""
    ordered = t("customer").select("c_custkey", "c_acctbal").orderBy(F.col("c_acctbal").desc_nulls_last(), "c_custkey")
    placed = ordered.withColumns({"part": F.spark_partition_id(), "at": F.monotonically_increasing_id()})
    sizes = placed.groupBy("part").agg(F.count("*").alias("held"), F.min("at").alias("low"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    firsts = sizes.select("part", "low", F.coalesce(F.sum("held").over(before), F.lit(0)).alias("first"))
    return placed.join(F.broadcast(firsts), "part").select("c_custkey", (F.col("at") - F.col("low") + F.col("first") + 1).alias("place"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def topk_global(t):
    return t("orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("SELECT user_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS k FROM events) WHERE k <= 3")
def topk_per_source(t):
    place = F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id"))
    return t("events").select("user_id", "event_id", "value").withColumn("k", place).where("k <= 3").select("user_id", "event_id")


_A, _B = "(SELECT l_partkey FROM lineitem WHERE l_quantity > 45)", "(SELECT l_partkey FROM lineitem WHERE l_discount > 0.08)"


def _sides(t):
    return t("lineitem").where("l_quantity > 45").select("l_partkey"), t("lineitem").where("l_discount > 0.08").select("l_partkey")


@query(f"SELECT l_partkey FROM {_A} UNION SELECT l_partkey FROM {_B}")
def set_union(t):
    a, b = _sides(t)
    return a.union(b).distinct()


@query(f"SELECT l_partkey FROM {_A} INTERSECT SELECT l_partkey FROM {_B}")
def set_intersect(t):
    a, b = _sides(t)
    return a.intersect(b)


@query(f"SELECT l_partkey FROM {_A} EXCEPT SELECT l_partkey FROM {_B}")
def set_except(t):
    a, b = _sides(t)
    return a.subtract(b)


@query(f"SELECT l_partkey FROM {_A} EXCEPT ALL SELECT l_partkey FROM {_B}")
def set_except_all(t):
    a, b = _sides(t)
    return a.exceptAll(b)


@query("SELECT o_orderkey FROM orders WHERE (o_orderkey * 2654435761) % 4294967296 < 429496729")
def sample_hash(t):
    """Bernoulli sampling by a multiplicative hash of the key: the same rows on every run and engine."""
    return t("orders").where("(o_orderkey * 2654435761) % 4294967296 < 429496729").select("o_orderkey")


# Scans, projections, predicates, subqueries --------------------------------------------------------------------------


@query("SELECT r_regionkey, r_name FROM region")
def scan_parquet(t):
    return t("region").select("r_regionkey", "r_name")


@query("SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def proj_basic(t):
    return t("lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("SELECT vec_id, CAST(embedding[1] AS DOUBLE) AS first, len(embedding) AS size FROM embeddings")
def proj_nested(t):
    return t("embeddings").select("vec_id", F.col("embedding")[0].cast("double").alias("first"), F.size("embedding").cast("bigint").alias("size"))


@query("SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'R') AND NOT l_discount > 0.05")
def filter_basic(t):
    return t("lineitem").where(F.col("l_quantity").between(10, 12) & F.col("l_returnflag").isin("A", "R") & ~(F.col("l_discount") > 0.05)).select("l_orderkey", "l_linenumber")


@query("SELECT c_custkey FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND o_totalprice > 250000 WHERE o_orderkey IS NULL OR NULLIF(o_orderstatus, 'F') IS NOT DISTINCT FROM NULL GROUP BY c_custkey")
def filter_null(t):
    joined = t("customer").join(t("orders"), (F.col("o_custkey") == F.col("c_custkey")) & (F.col("o_totalprice") > 250000), "left")
    return joined.where(F.col("o_orderkey").isNull() | F.nullif("o_orderstatus", F.lit("F")).eqNullSafe(F.lit(None))).select("c_custkey").distinct()


@query("SELECT p_partkey FROM part WHERE p_name LIKE 'b%' OR regexp_matches(p_brand, '^Brand#1')")
def filter_like(t):
    return t("part").where(F.col("p_name").like("b%") | F.col("p_brand").rlike("^Brand#1")).select("p_partkey")


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT') AND c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)")
def filter_subquery(t):
    spark = t("customer").sparkSession
    return spark.sql(
        """SELECT c_custkey FROM {c} WHERE EXISTS (SELECT 1 FROM {o} WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')
           AND c_nationkey IN (SELECT n_nationkey FROM {n} WHERE n_regionkey = 1)""",
        c=t("customer"), o=t("orders"), n=t("nation"),
    )


@query("WITH big AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT c_mktsegment, max(n) AS top FROM customer JOIN big ON o_custkey = c_custkey GROUP BY c_mktsegment")
def cte_basic(t):
    spark = t("orders").sparkSession
    return spark.sql("WITH big AS (SELECT o_custkey, count(*) AS n FROM {o} GROUP BY o_custkey) SELECT c_mktsegment, max(n) AS top FROM {c} JOIN big ON o_custkey = c_custkey GROUP BY c_mktsegment", o=t("orders"), c=t("customer"))


@query("SELECT o_orderkey FROM orders o WHERE o_totalprice > 1.8 * (SELECT avg(o_totalprice) FROM orders)")
def subquery_scalar(t):
    spark = t("orders").sparkSession
    return spark.sql("SELECT o_orderkey FROM {o} WHERE o_totalprice > 1.8 * (SELECT avg(o_totalprice) FROM {o})", o=t("orders"))


@query("WITH RECURSIVE w AS (SELECT 0 AS pos UNION ALL SELECT pos + 60000 FROM w WHERE pos < 600000) SELECT CAST(pos AS BIGINT) AS pos, n_regionkey FROM w JOIN nation ON n_nationkey = pos // 60000")
def cte_recursive(t):
    spark = t("nation").sparkSession
    return spark.sql("WITH RECURSIVE w AS (SELECT 0L AS pos UNION ALL SELECT pos + 60000L FROM w WHERE pos < 600000) SELECT pos, n_regionkey FROM w JOIN {n} ON n_nationkey = pos div 60000", n=t("nation"))


# Scalar functions ----------------------------------------------------------------------------------------------------


@query("""SELECT p_partkey, upper(split_part(p_name, ' ', 1)) AS colour, regexp_extract(p_brand, '#([0-9]+)', 1) AS brand_no, substr(p_type, 1, 4) AS head, CAST(strpos(p_name, 'e') AS BIGINT) AS at_e,
CAST(length(p_name) AS BIGINT) AS size, p_brand || '/' || p_type AS path, CAST(levenshtein(p_name, p_type) AS BIGINT) AS far, replace(p_name, ' ', '_') AS joined, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded FROM part""")
def fn_string(t):
    big = lambda c: c.cast("bigint")
    return t("part").select(
        "p_partkey", F.upper(F.split_part("p_name", F.lit(" "), F.lit(1))).alias("colour"), F.regexp_extract("p_brand", "#([0-9]+)", 1).alias("brand_no"), F.substring("p_type", 1, 4).alias("head"), big(F.locate("e", "p_name")).alias("at_e"),
        big(F.length("p_name")).alias("size"), F.concat_ws("/", "p_brand", "p_type").alias("path"), big(F.levenshtein("p_name", "p_type")).alias("far"), F.replace("p_name", F.lit(" "), F.lit("_")).alias("joined"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"),
    )


@query(f"""SELECT event_id, {_MS} AS ms, CAST(year(ts) AS BIGINT) AS y, CAST(month(ts) AS BIGINT) AS m, CAST(hour(ts) AS BIGINT) AS h, strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, strftime(ts + INTERVAL 90 MINUTE, '%H:%M') AS later FROM events""")
def fn_datetime(t):
    big = lambda c: c.cast("bigint")
    return t("events").select(
        "event_id", F.expr(_TS).alias("ms"), big(F.year("ts")).alias("y"), big(F.month("ts")).alias("m"), big(F.hour("ts")).alias("h"), F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd").alias("day"),
        F.date_format(F.expr("ts + INTERVAL 90 MINUTE"), "HH:mm").alias("later"),
    )


@query("SELECT p_partkey, greatest(p_size, 25) AS high, least(p_size, 25) AS low, ((p_size - 30) % 7 + 7) % 7 AS turn, CAST(p_size // 7 AS BIGINT) AS whole, round(sqrt(p_retailprice), 6) AS root, round(ln(p_retailprice), 6) AS log, least(greatest(p_size, 10), 40) AS clamped FROM part")
def fn_math(t):
    return t("part").select(
        "p_partkey", F.greatest("p_size", F.lit(25)).alias("high"), F.least("p_size", F.lit(25)).alias("low"), F.pmod(F.col("p_size") - 30, F.lit(7)).alias("turn"), F.expr("bigint(p_size div 7)").alias("whole"),
        F.round(F.sqrt("p_retailprice"), 6).alias("root"), F.round(F.ln("p_retailprice"), 6).alias("log"), F.least(F.greatest("p_size", F.lit(10)), F.lit(40)).alias("clamped"),
    )


@query("""SELECT vec_id, CAST(len(list_filter(e, lambda x: x > 0)) AS BIGINT) AS n_pos, round(list_sum(list_transform(e, lambda x: x * x)), 5) AS norm, round(list_sum(e[1:8]), 5) AS head, len(list_filter(e, lambda x: x > 0.4)) > 0 AS spike FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings)""")
def fn_array(t):
    e = t("embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda a, x: a + x)
    return e.select("vec_id", F.size(F.filter("e", lambda x: x > 0)).cast("bigint").alias("n_pos"), F.round(total(F.transform("e", lambda x: x * x)), 5).alias("norm"), F.round(total(F.slice("e", 1, 8)), 5).alias("head"), F.exists("e", lambda x: x > 0.4).alias("spike"))


@query("SELECT p_partkey, p_brand AS brand, CAST(p_size * 2 AS BIGINT) AS twice, CAST(2 AS BIGINT) AS n FROM part WHERE p_size > 5")
def fn_map(t):
    made = t("part").select("p_partkey", F.create_map(F.lit("size"), F.col("p_size").cast("string"), F.lit("brand"), "p_brand").alias("m"), F.create_map(F.lit("s"), F.col("p_size") * 2).alias("n"))
    wide = made.withColumn("m", F.map_concat("m", F.map_from_entries(F.array(F.struct(F.lit("x"), F.lit(""))))))
    kept = wide.withColumn("m", F.map_filter("m", lambda k, v: v != ""))
    return kept.where(F.element_at("m", "size").cast("int") > 5).select("p_partkey", F.element_at("m", "brand").alias("brand"), F.element_at(F.transform_values("n", lambda k, v: v), "s").cast("bigint").alias("twice"), F.size("m").cast("bigint").alias("n"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) % 3 AS m FROM events")
def fn_json(t):
    k = F.from_json("props", "k bigint")["k"]
    return t("events").select("event_id", k.alias("k"), (F.expr("try_variant_get(parse_json(props), '$.k', 'bigint')") % 3).alias("m"))


@query("SELECT event_id, CASE WHEN value > 200 THEN 'high' WHEN value > 50 THEN 'mid' ELSE 'low' END AS band, coalesce(NULLIF(event_type, 'click'), 'c') AS kind, CASE WHEN user_id % 2 = 0 THEN NULL ELSE user_id END AS odd_user FROM events")
def fn_conditional(t):
    return t("events").select("event_id", F.when(F.col("value") > 200, "high").when(F.col("value") > 50, "mid").otherwise("low").alias("band"), F.nvl(F.nullif("event_type", F.lit("click")), F.lit("c")).alias("kind"), F.when(F.col("user_id") % 2 != 0, F.col("user_id")).alias("odd_user"))


@query("""SELECT l_orderkey, round(greatest(least(60.0, 30.0 + l_linenumber) - greatest(10.0 * l_linenumber, 30.0), 0) / (60 - 10 * l_linenumber + l_linenumber - greatest(least(60.0, 30.0 + l_linenumber) - greatest(10.0 * l_linenumber, 30.0), 0)), 6) AS iou FROM lineitem WHERE l_linenumber < 6""")
def sql_surface(t):
    """The SQL names of the engine: registered functions called from a SQL string."""
    from mediarel import sql

    df = t("lineitem")
    sql.register(df.sparkSession)
    return df.sparkSession.sql("SELECT l_orderkey, round(tiou(bigint(10 * l_linenumber), 60L, 30L, bigint(30 + l_linenumber)), 6) AS iou FROM {l} WHERE l_linenumber < 6", l=df)
