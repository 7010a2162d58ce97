"""Graphs made from the given tables, each as Spark frames and as SQL for its oracle.

Ids of mixed graphs are key * 16 + tag: customer 0, supplier 1, part 2, order 3, nation 4, region 5."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.graph import PropertyGraph
from ..operators.loops import kept
from ..operators.neighbours import nearest_pairs

TAGS = {"customer": 0, "supplier": 1, "part": 2, "order": 3, "nation": 4, "region": 5}


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def tagged(key: str, kind: str) -> Column:
    return F.col(key).cast("long") * 16 + TAGS[kind]


def visits(spark: SparkSession, d: str) -> PropertyGraph:
    """Users; from each event's user to the next one's of the day.

    Events are put in order within a minute; a minute's last event goes to the first one of the day's next
    minute that has any, found among one row a minute, so that no task orders a whole day's events."""
    ev = table(spark, d, "events").select("user_id", "ts", "event_id", F.to_date("ts").alias("day"), F.date_trunc("minute", "ts").alias("minute"))
    w = Window.partitionBy("day", "minute").orderBy("ts", "event_id")
    first = ev.groupBy("day", "minute").agg(F.min(F.struct("ts", "event_id", "user_id"))["user_id"].alias("head"))
    after = first.select("day", "minute", F.lead("head").over(Window.partitionBy("day").orderBy("minute")).alias("_next"))
    rows = ev.select("day", "minute", F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("_within"), "ts")
    rows = rows.join(after, ["day", "minute"]).withColumn("dst", F.coalesce("_within", "_next"))
    e = rows.where("dst IS NOT NULL AND src != dst").groupBy("src", "dst").agg(F.count("*").alias("n"), F.min("ts").alias("first_ts"), F.max("ts").alias("last_ts"))
    v = table(spark, d, "events").groupBy(F.col("user_id").alias("id")).agg(F.count("*").alias("n_events"), F.sum("value").alias("sum_value"))
    return PropertyGraph.build(v, e, check=False)


VISITS_E = """SELECT src, dst, count(*) AS n, min(ts) AS first_ts, max(ts) AS last_ts FROM (SELECT user_id AS src,
  lead(user_id) OVER (PARTITION BY CAST(ts AS DATE) ORDER BY ts, event_id) AS dst, ts FROM events) q WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst"""
VISITS_V = "SELECT DISTINCT user_id AS id FROM events"


def supply(spark: SparkSession, d: str) -> PropertyGraph:
    """Parts and suppliers; a line item from its part to its supplier."""
    p = table(spark, d, "part").select(tagged("p_partkey", "part").alias("id"), F.lit("part").alias("kind"), F.col("p_name").alias("name"), F.col("p_retailprice").alias("amount"), F.col("p_size").alias("size"))
    s = table(spark, d, "supplier").select(tagged("s_suppkey", "supplier").alias("id"), F.lit("supplier").alias("kind"), F.col("s_name").alias("name"), F.col("s_acctbal").alias("amount"), F.lit(None).cast("int").alias("size"))
    e = table(spark, d, "lineitem").select(tagged("l_partkey", "part").alias("src"), tagged("l_suppkey", "supplier").alias("dst"), F.col("l_quantity").alias("quantity"), F.col("l_extendedprice").alias("price"), F.col("l_discount").alias("discount"), F.col("l_shipdate").alias("shipdate"))
    return PropertyGraph.build(p.unionByName(s), e, check=False)  # keys of the tables


SUPPLY_E = "SELECT l_partkey * 16 + 2 AS src, l_suppkey * 16 + 1 AS dst, l_quantity AS quantity, l_extendedprice AS price, l_discount AS discount, l_shipdate AS shipdate FROM lineitem"
SUPPLY_V = """SELECT p_partkey * 16 + 2 AS id, 'part' AS kind, p_name AS name, p_retailprice AS amount, p_size AS size FROM part
  UNION ALL SELECT s_suppkey * 16 + 1, 'supplier', s_name, s_acctbal, NULL FROM supplier"""


def trade(spark: SparkSession, d: str) -> PropertyGraph:
    """Customers and suppliers; a line item from its order's customer to its supplier."""
    c = table(spark, d, "customer").select(tagged("c_custkey", "customer").alias("id"), F.lit("customer").alias("kind"), F.col("c_nationkey").cast("long").alias("nation"), F.col("c_acctbal").alias("balance"))
    s = table(spark, d, "supplier").select(tagged("s_suppkey", "supplier").alias("id"), F.lit("supplier").alias("kind"), F.col("s_nationkey").cast("long").alias("nation"), F.col("s_acctbal").alias("balance"))
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey", F.col("o_orderdate").alias("orderdate"))
    e = table(spark, d, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey")).select(tagged("o_custkey", "customer").alias("src"), tagged("l_suppkey", "supplier").alias("dst"), "orderdate", F.col("l_extendedprice").alias("price"))
    return PropertyGraph.build(c.unionByName(s), e, check=False)


TRADE_E = "SELECT o_custkey * 16 AS src, l_suppkey * 16 + 1 AS dst, o_orderdate AS orderdate, l_extendedprice AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
TRADE_V = """SELECT c_custkey * 16 AS id, 'customer' AS kind, c_nationkey::BIGINT AS nation, c_acctbal AS balance FROM customer
  UNION ALL SELECT s_suppkey * 16 + 1, 'supplier', s_nationkey::BIGINT, s_acctbal FROM supplier"""


def baskets(spark: SparkSession, d: str) -> PropertyGraph:
    """Orders and parts that share a large, well discounted line."""
    e = table(spark, d, "lineitem").where("l_quantity > 45 AND l_discount >= 0.08").select(tagged("l_orderkey", "order").alias("src"), tagged("l_partkey", "part").alias("dst"), F.col("l_quantity").alias("quantity"))
    return PropertyGraph.from_edges(kept(e))  # few of the lines pass; vertices and edges are made of one scan


BASKETS_E = "SELECT l_orderkey * 16 + 3 AS src, l_partkey * 16 + 2 AS dst FROM lineitem WHERE l_quantity > 45 AND l_discount >= 0.08"


def _word(x: Column) -> Column:
    return F.lower(F.regexp_replace(x, r"[.,]", ""))


def page_words(spark: SparkSession, d: str) -> DataFrame:
    title = F.regexp_extract("html", r"<title>([^<]*)</title>", 1)
    return table(spark, d, "pages").select(F.col("page_id").alias("id"), "url", F.regexp_extract("url", r"^https?://([^/]+)", 1).alias("host"), title.alias("title"), _word(F.split(title, " ")[0]).alias("word"))


def page_links(spark: SparkSession, d: str) -> DataFrame:
    hrefs = F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), 1)
    return table(spark, d, "pages").select(F.col("page_id").alias("src"), F.explode(hrefs).alias("href")).select("src", _word(F.col("href")).alias("word")).distinct()


def weblinks(spark: SparkSession, d: str) -> PropertyGraph:
    """Pages; a link goes to every page whose title starts with the link's word."""
    v = page_words(spark, d)
    e = page_links(spark, d).join(v.select(F.col("id").alias("dst"), "word"), "word").where("src != dst").select("src", "dst", F.col("word").alias("anchor"))
    return PropertyGraph.build(v.drop("word"), e, check=False)


WEB_WORDS = r"""SELECT page_id AS id, url, regexp_extract(url, '^https?://([^/]+)', 1) AS host, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title,
  lower(regexp_replace(string_split(regexp_extract(html, '<title>([^<]*)</title>', 1), ' ')[1], '[.,]', '', 'g')) AS word FROM pages"""
WEB_LINKS = r"""SELECT DISTINCT src, lower(regexp_replace(href, '[.,]', '', 'g')) AS word FROM (SELECT page_id AS src, unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) AS href FROM pages) q"""
WEB_E = f"SELECT l.src, w.id AS dst, w.word AS anchor FROM ({WEB_LINKS}) l JOIN ({WEB_WORDS}) w ON l.word = w.word WHERE l.src <> w.id"
WEB_V = "SELECT page_id AS id FROM pages"


def copies(spark: SparkSession, d: str) -> PropertyGraph:
    """Documents of equal text, each linked to the least of them: a star a group, so no pairs within it."""
    doc = table(spark, d, "documents")
    first = doc.groupBy(F.md5("text").alias("_h")).agg(F.min("doc_id").alias("src"), F.count("*").alias("_n")).where("_n > 1")
    e = doc.select(F.col("doc_id").alias("dst"), F.md5("text").alias("_h")).join(first, "_h").where("src != dst").select("src", "dst")
    v = doc.select(F.col("doc_id").alias("id"), "lang", "n_chars")
    return PropertyGraph.build(v, e)


COPIES_E = "SELECT m AS src, doc_id AS dst FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS m FROM documents WHERE text IS NOT NULL) q WHERE m <> doc_id"


def turns(spark: SparkSession, d: str) -> PropertyGraph:
    t = table(spark, d, "conversations").select((F.col("conv_id") * 1024 + F.col("turn")).alias("id"), "conv_id", "turn", "role")
    e = t.select("conv_id", "turn", F.col("id").alias("src")).join(t.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("id").alias("dst")), ["conv_id", "turn"]).select("src", "dst")
    return PropertyGraph.build(t, e)


TURNS_V = "SELECT conv_id * 1024 + turn AS id FROM conversations"
TURNS_E = "SELECT a.conv_id * 1024 + a.turn AS src, b.conv_id * 1024 + b.turn AS dst FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1"


def flows(spark: SparkSession, d: str) -> PropertyGraph:
    """Nations; revenue from customer nation to supplier nation."""
    n = table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("id"), F.col("n_name").alias("name"), F.col("n_regionkey").cast("long").alias("region"))
    g = trade(spark, d).triplets(["nation"], ["nation"])
    e = g.groupBy(F.col("src__nation").alias("src"), F.col("dst__nation").alias("dst")).agg(F.sum(F.col("price").cast("decimal(18,2)")).cast("decimal(18,2)").alias("revenue"), F.count("*").alias("n"))
    return PropertyGraph.build(n, e, check=False)


FLOWS_E = f"SELECT c.nation AS src, s.nation AS dst, CAST(sum(CAST(e.price AS DECIMAL(18,2))) AS DECIMAL(18,2)) AS revenue, count(*) AS n FROM ({TRADE_E}) e JOIN ({TRADE_V}) c ON c.id = e.src JOIN ({TRADE_V}) s ON s.id = e.dst GROUP BY c.nation, s.nation"


def geo(spark: SparkSession, d: str) -> PropertyGraph:
    """Customers and suppliers belong to nations, nations to regions."""
    t = lambda name: table(spark, d, name)
    kinds = [("customer", "c_custkey", "c_name"), ("supplier", "s_suppkey", "s_name"), ("nation", "n_nationkey", "n_name"), ("region", "r_regionkey", "r_name")]
    v = [t(k).select(tagged(key, k).alias("id"), F.lit(k).alias("kind"), F.col(name).alias("name")) for k, key, name in kinds]
    up = [("customer", "c_custkey", "c_nationkey", "nation"), ("supplier", "s_suppkey", "s_nationkey", "nation"), ("nation", "n_nationkey", "n_regionkey", "region")]
    e = [t(k).select(tagged(a, k).alias("src"), tagged(b, to).alias("dst")) for k, a, b, to in up]
    return PropertyGraph.build(v[0].unionByName(v[1]).unionByName(v[2]).unionByName(v[3]), e[0].unionByName(e[1]).unionByName(e[2]), check=False)


GEO_E = """SELECT c_custkey * 16 AS src, c_nationkey::BIGINT * 16 + 4 AS dst FROM customer UNION ALL SELECT s_suppkey * 16 + 1, s_nationkey::BIGINT * 16 + 4 FROM supplier
  UNION ALL SELECT n_nationkey::BIGINT * 16 + 4, n_regionkey::BIGINT * 16 + 5 FROM nation"""


def targets(spark: SparkSession, d: str) -> PropertyGraph:
    """Pages and what they link to by host and path: most targets are no known page and get defaults."""
    clean = lambda u: F.lower(F.regexp_replace(u, r"^https?://(www\.|m\.)?|[?#].*$|/$", ""))
    p = table(spark, d, "pages").select(clean(F.col("url")).alias("name"), F.lit(True).alias("crawled"), F.lit(1).cast("long").alias("n_copies"), F.split(clean(F.col("url")), "/")[0].alias("_host"), F.explode_outer(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), 1)).alias("_href"), "page_id")
    v = p.select(F.xxhash64("name").alias("id"), "name", "crawled", "page_id").distinct().select("id", "name", "crawled", F.lit(1).cast("long").alias("n_copies"))
    e = p.where("_href IS NOT NULL").select(F.xxhash64("name").alias("src"), F.xxhash64(F.concat_ws("/", "_host", "_href")).alias("dst"))
    return PropertyGraph.build(v, e, merge={"name": F.min, "crawled": F.max, "n_copies": F.sum}, default={"crawled": F.lit(False), "n_copies": F.lit(0)})


_CLEAN = r"lower(regexp_replace(url, '^https?://(www\.|m\.)?|[?#].*$|/$', '', 'g'))"
TARGETS_COUNTS = f"""WITH p AS (SELECT DISTINCT page_id, {_CLEAN} AS name, html FROM pages), k AS (SELECT DISTINCT name FROM p),
t AS (SELECT DISTINCT string_split(name, '/')[1] || '/' || href AS name FROM (SELECT name, unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) AS href FROM p) q)
SELECT (SELECT count(*) FROM (SELECT name FROM k UNION SELECT name FROM t) u) AS vertices, (SELECT count(*) FROM k) AS crawled, (SELECT count(DISTINCT (page_id, name)) FROM p) AS copies"""


def nearest(spark: SparkSession, d: str, k: int = 3) -> PropertyGraph:
    """Vectors linked to their k nearest by cosine among all vectors."""
    v = table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), "embedding", "label")
    return PropertyGraph.build(v, kept(nearest_pairs(v, k)))


NEAREST_E = """SELECT src, dst, rank, cosine FROM (SELECT *, (row_number() OVER (PARTITION BY src ORDER BY cosine DESC, dst) - 1)::INT AS rank FROM (
  SELECT a.vec_id AS src, b.vec_id AS dst, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 12) AS cosine FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) p) q WHERE rank < 3"""
