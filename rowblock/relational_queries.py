"""Queries for the operators around the methods: sources, joins, aggregates, windows, sets, functions and streams."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .functions.fixtures import table
from .operators import relational as rel
from .sources import dial, files
from .staging import Stage, shared_folder
from .streaming import summaries as st

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


# Sources and sinks


@query("o1_scan", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")
def o1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").where("l_quantity > 45 AND l_returnflag = 'R'").select("l_orderkey", "l_quantity")


for _kind in ("orc", "csv", "json"):

    @query(f"o2_{_kind}", "SELECT c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment FROM customer")
    def _(spark: SparkSession, sf_dir: str, kind: str = _kind) -> DataFrame:
        df = table(spark, sf_dir, "customer")
        path = f"{Stage(spark).path}/customer"
        files.write(df, path, kind)
        return files.read(spark, path, kind, df.schema)


@query("o2_text", "SELECT p_partkey || ',' || p_size AS value FROM part")
def o2_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{Stage(spark).path}/part"
    files.matrix_rows(table(spark, sf_dir, "part"), ["p_partkey"], ["p_size"], path)
    return spark.read.text(path)


@query("o4_partitioned", "SELECT event_type, count(*) AS n FROM events WHERE event_type = (SELECT min(event_type) FROM events) GROUP BY event_type")
def o4(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = table(spark, sf_dir, "events")
    path = f"{Stage(spark).path}/events"
    files.write(df, path, "parquet", ("event_type",))
    least = df.agg(F.min("event_type")).first()[0]
    return spark.read.parquet(path).where(F.col("event_type") == least).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("o4_bucketed", "SELECT o_orderkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey")
def o4_bucketed(spark: SparkSession, sf_dir: str) -> DataFrame:
    run = uuid.uuid4().hex
    orders = files.bucketed(table(spark, sf_dir, "orders").select("o_orderkey"), f"orders_{run}", 8, "o_orderkey")
    lines = files.bucketed(table(spark, sf_dir, "lineitem").select("l_orderkey"), f"lines_{run}", 8, "l_orderkey")
    return orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("n"))


@query("o6_dial_source", "SELECT count(o_orderkey) AS n, 4::BIGINT AS width FROM orders")
def o6(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every order takes a row of the source's matrix."""
    dial.register(spark)
    made = spark.read.format("dial_matrix").option("rows", 500).option("columns", 4).option("cond", 1e6).load()
    df = table(spark, sf_dir, "orders").select(F.pmod("o_orderkey", F.lit(500)).alias("id")).join(F.broadcast(made), "id")
    return df.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("a")).cast("long").alias("width"))


@query("o7_sql_text", "SELECT n_name, count(*) AS n FROM nation JOIN customer ON n_nationkey = c_nationkey WHERE c_acctbal > 100 GROUP BY n_name")
def o7(spark: SparkSession, sf_dir: str) -> DataFrame:
    table(spark, sf_dir, "nation").createOrReplaceTempView("o7_nation")
    table(spark, sf_dir, "customer").createOrReplaceTempView("o7_customer")
    return spark.sql("SELECT n_name, count(*) AS n FROM o7_nation JOIN o7_customer ON n_nationkey = c_nationkey WHERE c_acctbal > :least GROUP BY n_name", args={"least": 100})


# Joins


@query("j1_inner", "SELECT o_orderkey, c_mktsegment, count(*) AS lines FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY ALL")
def j1(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o, c = (table(spark, sf_dir, t) for t in ("lineitem", "orders", "customer"))
    lines = li.groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("lines"))  # summed before the join
    return lines.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment", "lines")


@query("j2_broadcast", "SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def j2(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, n, r = (table(spark, sf_dir, t) for t in ("supplier", "nation", "region"))
    return s.join(rel.broadcast_if_small(n), F.col("s_nationkey") == F.col("n_nationkey")).join(rel.broadcast_if_small(r), F.col("n_regionkey") == F.col("r_regionkey")).select("s_suppkey", "n_name", "r_name")


for _how, _sql in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):

    @query(f"j4_{_how}_outer", f"SELECT d.doc_id AS doc, coalesce(l.doc_id, -1) AS labelled, coalesce(quality, -1) AS quality FROM documents d {_sql} JOIN labels l ON d.doc_id = l.doc_id")
    def _(spark: SparkSession, sf_dir: str, how: str = _how) -> DataFrame:
        d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("doc"))
        x = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("labelled"), "quality")
        return d.join(x, F.col("doc") == F.col("labelled"), how).select("doc", F.coalesce("labelled", F.lit(-1).cast("long")).alias("labelled"), F.coalesce("quality", F.lit(-1)).alias("quality"))


@query("j5_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def j5_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "customer").join(table(spark, sf_dir, "orders").where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("j5_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def j5_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "customer").join(table(spark, sf_dir, "orders").where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("j6_theta", "SELECT a.n_nationkey AS i, b.n_nationkey AS j FROM nation a JOIN nation b ON a.n_nationkey <= b.n_nationkey AND a.n_regionkey = b.n_regionkey")
def j6(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "nation")
    a, b = n.select(F.col("n_nationkey").alias("i"), "n_regionkey"), n.select(F.col("n_nationkey").alias("j"), "n_regionkey")
    return a.join(b, "n_regionkey").where("i <= j").select("i", "j")


_DAY = 86_400


@query("j7_range", f"WITH e AS (SELECT event_id AS span_id, epoch_us(ts) // 1000000 AS at_s FROM events) SELECT span_id, count(*) OVER (ORDER BY at_s RANGE BETWEEN CURRENT ROW AND {_DAY - 1} FOLLOWING) AS n FROM e")
def j7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event opens a span of a day; the events of all spans are counted from sums by second and day, so no pair of events is made."""
    e = table(spark, sf_dir, "events").select(F.col("event_id").alias("span_id"), F.unix_seconds(F.col("ts").cast("timestamp")).alias("at"))
    return rel.count_within(e, "span_id", "at", _DAY)


@query("j8_as_of", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM events")
def j8(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    return rel.as_of(e, ["user_id"], "ts", "event_id", "value", F.col("event_type") == "purchase", "before").select("event_id", "before")


@query("j9_lateral", "SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS p FROM customer JOIN orders ON c_custkey = o_custkey) WHERE p <= 2")
def j9(spark: SparkSession, sf_dir: str) -> DataFrame:
    both = table(spark, sf_dir, "customer").join(table(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"))
    return rel.top_k(both, ["c_custkey"], [F.desc("o_totalprice"), F.asc("o_orderkey")], 2).select("c_custkey", "o_orderkey")


# Aggregates


@query("a1_statistics", "SELECT round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_quantity, l_extendedprice), 2) AS cov, count(DISTINCT l_orderkey) AS orders FROM lineitem")
def a1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").agg(
        F.round(F.avg("l_quantity"), 6).alias("mean"), F.round(F.stddev("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.covar_pop("l_quantity", "l_extendedprice"), 2).alias("cov"), F.countDistinct("l_orderkey").alias("orders")
    )


@query("a2_cube", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def a2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("q"), F.count(F.lit(1)).alias("n"))


@query("a3_conditional", "SELECT event_type, count(*) FILTER (value > 100) AS high, round(sum(value) FILTER (value <= 100), 4) AS low_sum FROM events GROUP BY event_type")
def a3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 100).alias("high"), F.round(F.sum(F.when(F.col("value") <= 100, F.col("value"))), 4).alias("low_sum"))


@query("a4_salted", "SELECT source, sum(n_chars)::BIGINT AS n_chars FROM documents GROUP BY source")
def a4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rel.salted_sum(table(spark, sf_dir, "documents").select("doc_id", "source", "n_chars"), ["source"], "n_chars")


@query("a5_observed", "SELECT count(*) AS n, count(*) FILTER (l_quantity > 10) AS passed FROM lineitem")
def a5(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import Observation

    seen = Observation("rows")
    table(spark, sf_dir, "lineitem").select("l_quantity").observe(seen, F.count(F.lit(1)).alias("n"), F.count_if(F.col("l_quantity") > 10).alias("passed")).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["n"], seen.get["passed"])], "n long, passed long")


@query("a6_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS F, count(*) FILTER (l_linestatus = 'O') AS O FROM lineitem GROUP BY l_returnflag")
def a6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().na.fill(0)


# Windows, sort, sets


@query("w_rank", "SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS d, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey) AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderstatus)")
def w_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderstatus")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("d"), F.ntile(4).over(Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")).cast("long").alias("q"))


@query("w_lag", "SELECT event_id, round(value - lag(value) OVER w, 6) AS step, round(sum(value) OVER w, 4) AS running FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def w_lag(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events").select("event_id", F.round(F.col("value") - F.lag("value").over(w), 6).alias("step"), F.round(F.sum("value").over(w), 4).alias("running"))


@query("w_time_frame", f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN {_DAY} PRECEDING AND CURRENT ROW) AS n FROM events")
def w_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-_DAY, 0)
    return table(spark, sf_dir, "events").select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@query("w_cumulative_gram", "SELECT strftime(day::TIMESTAMP, '%Y-%m-%d') AS day, round(sum(g) OVER (ORDER BY day), 4) AS g FROM (SELECT date_trunc('day', ts)::DATE AS day, sum(value * value) AS g FROM events GROUP BY 1)")
def w_gram(spark: SparkSession, sf_dir: str) -> DataFrame:
    daily = table(spark, sf_dir, "events").groupBy(F.to_date("ts").alias("day")).agg(F.sum(F.col("value") * F.col("value")).alias("g"))
    return daily.select(F.date_format("day", "yyyy-MM-dd").alias("day"), F.round(F.sum("g").over(Window.orderBy("day")), 4).alias("g"))  # one row for each day


@query("s_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def s_limit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("x_sets", "(SELECT c_nationkey AS k FROM customer UNION SELECT n_nationkey FROM nation) EXCEPT SELECT s_nationkey FROM supplier")
def x_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n, s = (table(spark, sf_dir, t).select(F.col(k).alias("k")) for t, k in (("customer", "c_nationkey"), ("nation", "n_nationkey"), ("supplier", "s_nationkey")))
    return c.unionByName(n).distinct().subtract(s)


@query("x_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def x_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).intersect(table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k")))


# Projections and scalar functions


@query("f_one_hot", "SELECT event_id, (event_type = 'click')::DOUBLE AS is_click, (event_type = 'purchase')::DOUBLE AS is_purchase FROM events")
def f_one_hot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rel.one_hot(table(spark, sf_dir, "events"), "event_type", ["click", "purchase"], "is").select("event_id", "is_click", "is_purchase")


@query("f_json", "SELECT event_id, (props->>'k')::INT AS k FROM events")
def f_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("f_dates", "SELECT o_orderkey, month(o_orderdate)::INT AS month, isodow(o_orderdate)::INT AS weekday, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first_day FROM orders")
def f_dates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select("o_orderkey", F.month("o_orderdate").alias("month"), (F.weekday("o_orderdate") + 1).alias("weekday"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("first_day"))


@query("f_arrays", "SELECT vec_id, round(list_sum(list_transform(embedding[1:4], lambda x: x::DOUBLE)), 6) AS s, embedding[1]::DOUBLE AS first FROM embeddings")
def f_arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(F.aggregate(F.transform(F.slice("embedding", 1, 4), lambda x: x.cast("double")), F.lit(0.0), lambda a, x: a + x), 6).alias("s"), F.element_at("embedding", 1).cast("double").alias("first"))


@query("f_maps", "SELECT p_partkey, p_size * 2 AS doubled FROM part")
def f_maps(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = F.transform_values(F.map_from_arrays(F.array(F.lit("size")), F.array("p_size")), lambda k, v: v * 2)
    return table(spark, sf_dir, "part").select("p_partkey", F.element_at(m, "size").alias("doubled"))


@query("f_strings", "SELECT p_partkey, upper(substr(p_name, 1, 3)) AS head, length(p_type) AS n FROM part WHERE p_brand LIKE 'Brand%'")
def f_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "part").where(F.col("p_brand").like("Brand%")).select("p_partkey", F.upper(F.substring("p_name", 1, 3)).alias("head"), F.length("p_type").cast("long").alias("n"))


@query("f_math", "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS lg, round(sqrt(l_quantity), 6) AS sq, greatest(l_discount, l_tax) + 0.0 AS top FROM lineitem")
def f_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.log("l_extendedprice"), 6).alias("lg"), F.round(F.sqrt("l_quantity"), 6).alias("sq"), (F.greatest("l_discount", "l_tax") + 0.0).alias("top"))


@query("f_nulls", "SELECT doc_id, coalesce(nullif(lang, 'en'), 'none') AS lang FROM documents")
def f_nulls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id", F.coalesce(F.nullif("lang", F.lit("en")), F.lit("none")).alias("lang"))


@query("f_key_sample")
def f_key_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rel.key_sample(table(spark, sf_dir, "orders"), ["o_orderkey"], 10).select("o_orderkey")


# Streams


def _event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of a folder with several files, as a stream of several batches."""
    e = table(spark, sf_dir, "events")
    folder = f"{shared_folder(spark)}/events-{uuid.uuid4().hex}"
    e.repartitionByRange(4, "event_id").write.parquet(folder)
    return st.row_stream(spark, folder, e.schema, 2).withColumn("ts", F.col("ts").cast("timestamp"))


@query("t1_rows", "SELECT event_id, value FROM events WHERE value > 50")
def t1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.drain(_event_stream(spark, sf_dir).where("value > 50").select("event_id", "value"), "append")


@query("t2_running_gram", "SELECT event_type, count(*) AS n, round(sum(value * value), 2) AS g FROM events GROUP BY event_type")
def t2(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = st.drain(st.running_gram(_event_stream(spark, sf_dir), ["value"], ["event_type"]), "complete")
    return out.select("event_type", "n", F.round("g0_0", 2).alias("g"))


@query("t3_running_r", "SELECT event_type, round(sqrt(g0_0), 4) AS r00, round(g0_1 / sqrt(g0_0), 4) AS r01, round(sqrt(g1_1 - g0_1 * g0_1 / g0_0), 4) AS r11 FROM (SELECT event_type, count(*)::DOUBLE AS g0_0, sum(value) AS g0_1, sum(value * value) AS g1_1 FROM events GROUP BY event_type)")
def t3(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _event_stream(spark, sf_dir).select("event_type", F.lit(1.0).alias("one"), "value")
    out = st.drain(st.running_r(rows, "event_type", ["one", "value"]), "update", ["event_type"])
    return out.select("event_type", *(F.round(F.get("r", k), 4).alias(n) for k, n in ((0, "r00"), (1, "r01"), (3, "r11"))))


@query("t4_windows", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*) AS n, round(sum(value * value), 2) AS g FROM events GROUP BY 1")
def t4(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = st.drain(st.windowed_gram(_event_stream(spark, sf_dir), "ts", ["value"], "1 day", late="3650 days"), "complete")
    return out.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n", F.round("g0_0", 2).alias("g"))


@query("t6_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def t6(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    return st.drain(_event_stream(spark, sf_dir).join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"), "append")


@query("t7_distinct", "SELECT count(*) AS n FROM events")
def t7(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _event_stream(spark, sf_dir)
    twice = e.withColumn("again", F.explode(F.array(F.lit(0), F.lit(1))))
    return st.drain(st.distinct_rows(twice, "event_id", "ts", "3650 days").select("event_id"), "append").agg(F.count(F.lit(1)).alias("n"))


@query("t8_frozen_r", "WITH g AS (SELECT sqrt(sum(value * value)) AS r FROM events) SELECT event_id, round(value / r, 9) AS q0 FROM events, g")
def t8(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = table(spark, sf_dir, "events").agg(F.sqrt(F.sum(F.col("value") * F.col("value")))).first()[0]
    return st.drain(_event_stream(spark, sf_dir).select("event_id", F.round(F.col("value") / r, 9).alias("q0")), "append")


@query("t5_late_rows", "WITH c AS (SELECT date_trunc('hour', max(ts)) - INTERVAL 2 DAY AS cut FROM events) SELECT count(*) FILTER (ts >= cut) AS kept, count(*) FILTER (ts < cut) AS dropped FROM events, c")
def t5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last two days come first, in two batches, and everything before them afterwards: behind a watermark of an hour, all of that is dropped.

    A batch drops rows by the watermark that held when the batch before it began.
    """
    e = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    cut = e.agg(F.date_trunc("hour", F.max("ts")) - F.expr("INTERVAL 2 DAYS")).first()[0]
    folder = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    new = e.where(F.col("ts") >= F.lit(cut))
    for part in (new.where("event_id % 2 = 0"), new.where("event_id % 2 = 1"), e.where(F.col("ts") < F.lit(cut))):
        part.coalesce(1).write.mode("append").parquet(folder)
        time.sleep(1.1)  # files come in the order of their times
    stream = st.row_stream(spark, folder, e.schema, 1)
    kept = st.drain(st.windowed_gram(stream, "ts", ["value"], "1 hour", late="1 hour"), "update", ["w"]).agg(F.sum("n").alias("kept"))
    return kept.select("kept", (F.lit(e.count()) - F.col("kept")).alias("dropped"))


@query("t5_sessions", """
    WITH b AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM b)
    SELECT n, count(*) AS sessions FROM (SELECT count(*) AS n FROM s GROUP BY user_id, k) GROUP BY n""")
def t5_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of a user end after six hours without an event."""
    rows = _event_stream(spark, sf_dir).withWatermark("ts", "3650 days")
    out = st.drain(rows.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n")), "complete")
    return out.groupBy("n").agg(F.count(F.lit(1)).alias("sessions"))


@query("t6_interval_join", "SELECT a.event_id AS first_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def t6_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _event_stream(spark, sf_dir).select("event_id", "user_id", "ts")
    a = e.select(F.col("event_id").alias("first_id"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "3650 days")
    b = e.select(F.col("event_id").alias("next_id"), "user_id", "ts").withWatermark("ts", "3650 days")
    both = a.join(b, F.expr("u = user_id AND ts > t AND ts <= t + INTERVAL 1 HOUR"))
    return st.drain(both.select("first_id", "next_id"), "append")


@query("a7_sketches", "SELECT true AS close_count, true AS close_median")
def a7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketches against exact values: distinct keys within 10 %, the median's rank within 2 %."""
    li = table(spark, sf_dir, "lineitem")
    near, exact, median = li.agg(F.approx_count_distinct("l_orderkey", 0.02), F.countDistinct("l_orderkey"), F.percentile_approx("l_extendedprice", 0.5, 1000)).first()
    below = li.agg(F.avg((F.col("l_extendedprice") <= median).cast("double"))).first()[0]
    return spark.createDataFrame([(abs(near / exact - 1) < 0.1, abs(below - 0.5) < 0.02)], "close_count boolean, close_median boolean")
