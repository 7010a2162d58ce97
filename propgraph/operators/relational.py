"""The relational surface around the graph operators, each on the given tables with its SQL."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def query(sql: str | None = None, name: str | None = None):
    """Registers a query; it gets a function that reads a table by name."""

    def add(f):
        key = name or f.__name__
        QUERIES[key] = lambda spark, d: f(lambda t: spark.read.parquet(f"{d}/{t}.parquet"))
        if sql:
            ORACLES[key] = sql
        return f

    return add


def money(c: str | Column) -> Column:
    return F.sum((F.col(c) if isinstance(c, str) else c).cast("decimal(18,2)")).cast("double")


@query("\nUNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def scan_parquet_counts(t):
    out = None
    for k in TABLES:
        one = t(k).agg(F.lit(k).alias("name"), F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT l_orderkey * 16 + 3 AS src, l_partkey * 16 + 2 AS dst FROM lineitem")
def edge_list_text(t):
    from ..sources.files import parse_edges

    rows = t("lineitem")
    return parse_edges(rows.select(F.concat_ws(" ", (F.col("l_orderkey") * 16 + 3).cast("string"), (F.col("l_partkey") * 16 + 2).cast("string")).alias("value")))


@query("SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem WHERE l_shipdate >= '1995-03-01' AND l_shipdate < '1995-04-01'")
def project_filter(t):
    rows = t("lineitem").where("l_shipdate >= timestamp_ntz'1995-03-01' AND l_shipdate < timestamp_ntz'1995-04-01'")
    return rows.select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


def _join(how: str):
    def run(t):
        o = t("orders").where("o_totalprice > 150000").select("o_orderkey", "o_custkey")
        c = t("customer").where("c_acctbal > 0").select("c_custkey", "c_name")
        return o.join(c, F.col("o_custkey") == F.col("c_custkey"), how).select("o_orderkey", "c_custkey", "c_name")

    return run


for _how in ("inner", "left", "right", "full"):
    query(f"SELECT o_orderkey, c_custkey, c_name FROM (SELECT * FROM orders WHERE o_totalprice > 150000) o {_how} JOIN (SELECT * FROM customer WHERE c_acctbal > 0) c ON o_custkey = c_custkey", f"join_{_how}")(_join(_how))


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def join_semi(t):
    return t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def join_anti(t):
    return t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


def _hinted(hint: str):
    def run(t):
        rows = t("lineitem").join(t("orders").hint(hint), F.col("l_orderkey") == F.col("o_orderkey")) if hint != "broadcast" else t("customer").join(t("nation").hint(hint), F.col("c_nationkey") == F.col("n_nationkey"))
        return rows.groupBy("o_orderpriority").agg(F.count("*").alias("n")) if hint != "broadcast" else rows.groupBy("n_name").agg(F.count("*").alias("n"))

    return run


query("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name", "join_broadcast")(_hinted("broadcast"))
for _hint, _name in (("merge", "join_merge"), ("shuffle_hash", "join_shuffle_hash")):
    query("SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority", _name)(_hinted(_hint))


@query("SELECT a.p_partkey AS id, count(*) AS n FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_size = b.p_size AND b.p_retailprice BETWEEN a.p_retailprice - 10 AND a.p_retailprice + 10 AND a.p_partkey <> b.p_partkey GROUP BY a.p_partkey")
def join_theta(t):
    a = t("part").select(F.col("p_partkey").alias("id"), "p_brand", "p_size", F.col("p_retailprice").alias("x"))
    b = a.withColumnRenamed("id", "other").withColumnRenamed("x", "y")
    return a.join(b, ["p_brand", "p_size"]).where("y BETWEEN x - 10 AND x + 10 AND id != other").groupBy("id").agg(F.count("*").alias("n"))


@query("WITH r AS (SELECT event_id % 50 AS k, min(ts) AS lo, min(ts) + INTERVAL '6 hours' AS hi FROM events GROUP BY event_id % 50) SELECT k, count(*) AS n FROM r JOIN events ON ts >= lo AND ts < hi GROUP BY k")
def join_range(t):
    """Range join by bucketed keys: a range is put into each of the hours that it touches."""
    ev = t("events").select("ts", F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("h"))
    r = t("events").groupBy((F.col("event_id") % 50).alias("k")).agg(F.min("ts").alias("lo")).withColumn("hi", F.col("lo") + F.expr("INTERVAL 6 HOURS"))
    r = r.withColumn("h", F.explode(F.sequence(F.date_trunc("hour", F.col("lo").cast("timestamp")), F.date_trunc("hour", F.col("hi").cast("timestamp")), F.expr("INTERVAL 1 HOUR"))))
    return r.join(ev, "h").where("ts >= lo AND ts < hi").groupBy("k").agg(F.count("*").alias("n"))


@query("SELECT event_id, last_view FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_view FROM events) q WHERE event_type = 'purchase'")
def join_asof(t):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return t("events").select("event_id", "event_type", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), True).over(w).alias("last_view")).where("event_type = 'purchase'").drop("event_type")


@query("SELECT c.event_id AS click, count(*) AS n FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL '1 hour' WHERE c.event_type = 'click' AND p.event_type = 'purchase' GROUP BY c.event_id")
def join_interval(t):
    c = t("events").where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("a"))
    p = t("events").where("event_type = 'purchase'").select("user_id", F.col("ts").alias("b"))
    return c.join(p, "user_id").where("b > a AND b <= a + INTERVAL 1 HOUR").groupBy("click").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, l_linestatus, sum(CAST(l_extendedprice AS DECIMAL(18,2)))::DOUBLE AS price, round(avg(l_quantity), 6) AS quantity, count(*) AS n FROM lineitem GROUP BY ALL")
def agg_basic(t):
    return t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(money("l_extendedprice").alias("price"), F.round(F.avg("l_quantity"), 6).alias("quantity"), F.count("*").alias("n"))


@query("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_suppkey")
def agg_distinct(t):
    return t("lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"))


@query("SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS done, count(*) AS n FROM orders GROUP BY o_orderpriority")
def agg_filtered(t):
    return t("orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("done"), F.count("*").alias("n"))


def _places(t):
    return t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))


_PLACES = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
for _kind in ("cube", "rollup"):
    query(f"SELECT r_name, c_mktsegment, grouping(r_name)::INT AS g, count(*) AS n FROM {_PLACES} GROUP BY {_kind}(r_name, c_mktsegment)", f"agg_{_kind}")(lambda t, k=_kind: getattr(_places(t), k)("r_name", "c_mktsegment").agg(F.grouping("r_name").cast("int").alias("g"), F.count("*").alias("n")))


@query(f"SELECT n_name, c_mktsegment, count(*) AS n FROM {_PLACES} GROUP BY GROUPING SETS ((n_name), (c_mktsegment))")
def agg_grouping_sets(t):
    return _places(t).groupingSets([["n_name"], ["c_mktsegment"]], "n_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, true AS parts_near, true AS median_near FROM lineitem GROUP BY l_returnflag")
def agg_approx(t):
    """Whether the approximate count lies within a tenth of the exact one, and the approximate median within one of the exact one."""
    rows, flag = t("lineitem"), "l_returnflag"
    # the default standard error of 5 % would miss a tenth in one group of twenty
    near = rows.groupBy(flag).agg(F.approx_count_distinct("l_partkey", 0.01).alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("mid"))
    # exact figures from distinct values, so that no aggregate buffer is kept a key
    parts = rows.select(flag, "l_partkey").distinct().groupBy(F.col(flag).alias("f")).agg(F.count("l_partkey").alias("all_parts"))
    mids = rows.groupBy(flag, "l_quantity").agg(F.count("*").alias("n")).groupBy(F.col(flag).alias("g")).agg(F.expr("percentile(l_quantity, 0.5, n)").alias("median"))
    rows = near.join(parts, F.col(flag).eqNullSafe(F.col("f"))).join(mids, F.col(flag).eqNullSafe(F.col("g")))
    median_near = (F.abs(F.col("mid") - F.col("median")) <= 1) | (F.col("mid").isNull() & F.col("median").isNull())
    return rows.select(flag, (F.abs(F.col("parts") - F.col("all_parts")) <= F.col("all_parts") * 0.1).alias("parts_near"), median_near.alias("median_near"))


@query("SELECT l_suppkey, l_orderkey, l_linenumber, l_extendedprice FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey DESC, l_linenumber DESC) AS k FROM lineitem) q WHERE k = 1")
def agg_argmax(t):
    best = F.max(F.struct("l_extendedprice", "l_orderkey", "l_linenumber")).alias("b")
    return t("lineitem").groupBy("l_suppkey").agg(best).select("l_suppkey", "b.l_orderkey", "b.l_linenumber", "b.l_extendedprice")


@query("SELECT * FROM (PIVOT (SELECT o_orderstatus, o_orderpriority FROM orders) ON o_orderstatus IN ('F', 'O', 'P') USING count(*) GROUP BY o_orderpriority) p")
def agg_pivot(t):
    return t("orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).fillna(0)


_BY = "PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey"


@query(f"SELECT o_orderkey, row_number() OVER ({_BY}) AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS dr FROM orders")
def win_rank(t):
    w, p = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return t("orders").select("o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(p).cast("long").alias("rk"), F.dense_rank().over(p).cast("long").alias("dr"))


@query(f"SELECT o_orderkey, lag(o_orderkey) OVER ({_BY}) AS before, lead(o_orderkey, 2) OVER ({_BY}) AS after FROM orders")
def win_lag_lead(t):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    return t("orders").select("o_orderkey", F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey", 2).over(w).alias("after"))


@query(f"SELECT o_orderkey, sum(CAST(o_totalprice AS DECIMAL(18,2))) OVER ({_BY} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::DOUBLE AS s FROM orders")
def win_frame_rows(t):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey").rowsBetween(-2, 0)
    return t("orders").select("o_orderkey", F.sum(F.col("o_totalprice").cast("decimal(18,2)")).over(w).cast("double").alias("s"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM (SELECT event_id, user_id, date_trunc('second', ts) AS ts FROM events) q")
def win_frame_range(t):
    w = Window.partitionBy("user_id").orderBy("at").rangeBetween(-3600, 0)
    return t("events").select("event_id", "user_id", F.unix_timestamp(F.date_trunc("second", F.col("ts").cast("timestamp"))).alias("at")).select("event_id", F.count("*").over(w).alias("n"))


@query("SELECT c_custkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS q FROM customer")
def win_ntile(t):
    return t("customer").select("c_custkey", F.ntile(4).over(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")).cast("long").alias("q"))


@query("SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 25")
def topk_global(t):
    return t("customer").select("c_custkey", "c_acctbal").orderBy(F.col("c_acctbal").desc(), "c_custkey").limit(25)


@query("SELECT c_nationkey, c_custkey FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS k FROM customer) q WHERE k <= 3")
def topk_per_group(t):
    w = Window.partitionBy("c_nationkey").orderBy(F.col("c_acctbal").desc(), "c_custkey")
    return t("customer").withColumn("k", F.row_number().over(w)).where("k <= 3").select("c_nationkey", "c_custkey")


for _op, _sql in (("union", "UNION"), ("intersect", "INTERSECT"), ("subtract", "EXCEPT"), ("unionAll", "UNION ALL"), ("intersectAll", "INTERSECT ALL"), ("exceptAll", "EXCEPT ALL")):
    query(f"SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 5000 {_sql} SELECT s_nationkey FROM supplier", "set_" + {"subtract": "except", "unionAll": "union_all", "intersectAll": "intersect_all", "exceptAll": "except_all"}.get(_op, _op))(
        lambda t, op=_op: (lambda x: x.distinct() if op == "union" else x)(getattr(t("customer").where("c_acctbal > 5000").select(F.col("c_nationkey").alias("k")), op)(t("supplier").select("s_nationkey")))
    )


@query("SELECT p_partkey, upper(p_name) AS u, string_split(p_name, ' ')[1] AS first, replace(p_type, ' ', '_') AS kind, length(p_name)::INT AS n, levenshtein(p_brand, 'Brand#11')::INT AS far, md5(p_name) AS h FROM part")
def fn_string(t):
    return t("part").select("p_partkey", F.upper("p_name").alias("u"), F.split("p_name", " ")[0].alias("first"), F.replace(F.col("p_type"), F.lit(" "), F.lit("_")).alias("kind"), F.length("p_name").alias("n"), F.levenshtein("p_brand", F.lit("Brand#11")).alias("far"), F.md5("p_name").alias("h"))


@query(r"SELECT page_id, regexp_extract(url, '^https?://([^/?#]+)', 1) AS host, regexp_extract(url, '^https?://[^/?#]+([^?#]*)', 1) AS path FROM pages")
def fn_url(t):
    return t("pages").select("page_id", F.try_parse_url("url", F.lit("HOST")).alias("host"), F.try_parse_url("url", F.lit("PATH")).alias("path"))


@query("SELECT l_orderkey, l_linenumber, date_diff('day', o_orderdate::DATE, l_shipdate::DATE)::INT AS days, date_trunc('month', o_orderdate)::TIMESTAMP AS month, year(l_shipdate)::INT AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def fn_date(t):
    rows = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.select("l_orderkey", "l_linenumber", F.datediff("l_shipdate", "o_orderdate").alias("days"), F.date_trunc("month", F.col("o_orderdate").cast("timestamp")).cast("timestamp_ntz").alias("month"), F.year("l_shipdate").alias("y"))


@query("SELECT o_orderkey, o_orderdate + INTERVAL '1 month' AS due, o_orderdate - INTERVAL '36 hours' AS before FROM orders")
def fn_interval(t):
    return t("orders").select("o_orderkey", (F.col("o_orderdate") + F.expr("INTERVAL 1 MONTH")).alias("due"), (F.col("o_orderdate") - F.expr("INTERVAL 36 HOURS")).alias("before"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 4) AS norm FROM embeddings")
def fn_math(t):
    return t("embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 4).alias("norm"))


@query("SELECT conv_id, len(list(turn)) AS n, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id")
def fn_array(t):
    return t("conversations").groupBy("conv_id").agg(F.count("*").alias("n"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ">").alias("roles"))


@query("SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(*) FILTER (event_type = 'view') AS views FROM events GROUP BY user_id")
def fn_map(t):
    per = t("events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", *[F.coalesce(F.try_element_at("m", F.lit(k)), F.lit(0)).alias(f"{k}s") for k in ("click", "view")])


@query("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def fn_struct(t):
    rows = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.select(F.struct("n_name", F.struct("r_name").alias("r")).alias("x")).select("x.n_name", "x.r.r_name")


@query("SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS k FROM events GROUP BY event_type")
def fn_json(t):
    return t("events").groupBy("event_type").agg(F.sum(F.from_json("props", "k long")["k"]).alias("k"))


@query("SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 + l_tax), 4) AS x FROM lineitem")
def udf_pandas(t):
    @F.pandas_udf("double")
    def taxed(price: pd.Series, tax: pd.Series) -> pd.Series:
        return price * (1 + tax)

    return t("lineitem").select("l_orderkey", "l_linenumber", F.round(taxed("l_extendedprice", "l_tax"), 4).alias("x"))


@query("SELECT c_nationkey, round(median(c_acctbal), 4) AS m FROM customer GROUP BY c_nationkey")
def udaf_pandas(t):
    @F.pandas_udf("double")
    def median(x: pd.Series) -> float:
        return float(x.median())

    return t("customer").groupBy("c_nationkey").agg(F.round(median("c_acctbal"), 4).alias("m"))


@query("SELECT conv_id, i::INT AS i FROM (SELECT conv_id, unnest(range(1, count(*) + 1)) AS i FROM conversations GROUP BY conv_id) q")
def udtf_numbers(t):
    @F.udtf(returnType="i int")
    class Numbers:
        def eval(self, n: int):
            for i in range(n):
                yield (i + 1,)

    rows = t("conversations").groupBy("conv_id").agg(F.count("*").alias("n"))
    spark = rows.sparkSession
    spark.udtf.register("propgraph_numbers", Numbers)
    rows.createOrReplaceTempView("propgraph_turns")
    return spark.sql("SELECT conv_id, i FROM propgraph_turns, LATERAL propgraph_numbers(n)")


@query("SELECT l_suppkey AS id, l_partkey AS neighbour, (row_number() OVER (PARTITION BY l_suppkey ORDER BY l_partkey) - 1)::INT AS place FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem) q")
def udtf_neighbours(t):
    @F.udtf(returnType="neighbour bigint, place int")
    class Neighbours:
        def eval(self, neighbours: list):
            for place, x in enumerate(neighbours):
                yield x, place

    rows = t("lineitem").groupBy(F.col("l_suppkey").alias("id")).agg(F.array_sort(F.collect_set("l_partkey")).alias("neighbours"))
    spark = rows.sparkSession
    spark.udtf.register("propgraph_neighbours", Neighbours)
    rows.createOrReplaceTempView("propgraph_adjacency")
    return spark.sql("SELECT id, neighbour, place FROM propgraph_adjacency, LATERAL propgraph_neighbours(neighbours)")
