"""The given tables with their declared schemas, and the role views that the methods read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey INT, r_name STRING",
    "nation": "n_nationkey INT, n_name STRING, n_regionkey INT",
    "customer": "c_custkey BIGINT, c_name STRING, c_nationkey INT, c_acctbal DOUBLE, c_mktsegment STRING",
    "supplier": "s_suppkey BIGINT, s_name STRING, s_nationkey INT, s_acctbal DOUBLE",
    "part": "p_partkey BIGINT, p_name STRING, p_brand STRING, p_type STRING, p_size INT, p_retailprice DOUBLE",
    "orders": "o_orderkey BIGINT, o_custkey BIGINT, o_orderstatus STRING, o_totalprice DOUBLE, o_orderdate TIMESTAMP_NTZ, o_orderpriority STRING",
    "lineitem": "l_orderkey BIGINT, l_partkey BIGINT, l_suppkey BIGINT, l_linenumber INT, l_quantity DOUBLE, l_extendedprice DOUBLE, "
    "l_discount DOUBLE, l_tax DOUBLE, l_returnflag STRING, l_linestatus STRING, l_shipdate TIMESTAMP_NTZ",
    "events": "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING",
    "documents": "doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT",
    "embeddings": "vec_id BIGINT, embedding ARRAY<FLOAT>, label INT",
    "pages": "page_id BIGINT, url STRING, html STRING",
    "benchmark": "item_id BIGINT, text STRING",
    "labels": "doc_id BIGINT, quality INT, toxic INT",
    "conversations": "conv_id BIGINT, turn BIGINT, role STRING, text STRING",
}
#: The columns that put the events of one part in a full order.
PART_ORDER = (
    "o_orderdate", "l_orderkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax",
    "l_suppkey", "l_returnflag", "l_linestatus", "l_shipdate",
)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def subscriber(spark: SparkSession, sf_dir: str) -> DataFrame:
    customer, nation, region = (read_table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    operator = F.when(F.col("c_mktsegment") == "MACHINERY", "rival").when(F.col("c_mktsegment") == "BUILDING", "landline").otherwise("home")
    places = nation.join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))  # fixed tables of 25 and 5 rows
    return customer.join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey")).select(
        F.col("c_custkey").alias("sub_id"), operator.alias("operator"), F.col("c_mktsegment").alias("segment"), F.col("c_acctbal").alias("balance"),
        F.col("n_name").alias("area"), F.col("r_name").alias("state"), (F.lit(18) + F.col("c_custkey") % 60).cast("int").alias("age_years"),
    )


def contact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Within each part, in full order, a row's customer contacts the next row's; self-contacts are left out."""
    lines, orders = read_table(spark, sf_dir, "lineitem"), read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    following = F.lead("o_custkey").over(Window.partitionBy("l_partkey").orderBy(*PART_ORDER))
    kind = F.when(F.col("l_returnflag") == "N", "call").when(F.col("l_returnflag") == "A", "sms").otherwise("mms")
    return (
        joined.withColumn("dst", following).where("dst IS NOT NULL AND dst <> o_custkey")
        .select(
            F.col("o_custkey").alias("src"), "dst", F.col("o_orderdate").alias("ts"), kind.alias("kind"),
            F.when(F.col("l_returnflag") == "N", F.col("l_quantity")).otherwise(F.lit(0.0)).alias("duration"),
            (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("charge"), F.col("l_partkey").alias("device"), F.col("l_suppkey").alias("package"),
        )
    )


def _k() -> F.Column:
    return F.try_element_at(F.from_json("props", "MAP<STRING,INT>"), F.lit("k"))


def touch(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events")
    return e.select(F.col("user_id").alias("src"), _k().cast("bigint").alias("dst"), "ts", F.col("event_type").alias("kind"), "value")


def session(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events").withColumn("k", _k())
    part = lambda kind: F.when(F.col("event_type") == kind, F.col("value")).otherwise(F.lit(0.0))
    rat = F.element_at(F.array(F.lit("2G"), F.lit("3G"), F.lit("4G")), (F.col("k") % 3 + 1).cast("int"))
    return e.select(
        F.col("user_id").alias("sub_id"), "ts", rat.alias("rat"), F.floor(F.col("k") / 3).cast("bigint").alias("site"), part("click").alias("bytes_up"),
        part("view").alias("bytes_down"), part("purchase").alias("top_up"), (F.col("event_type") == "error").alias("dropped"),
    )


def ticket(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events").where("event_type = 'error' AND value >= 40").withColumn("k", _k())
    result = F.when(F.col("k") % 2 == 1, "solved").otherwise("open")
    return e.select(F.col("user_id").alias("sub_id"), F.col("ts").alias("opened"), F.col("value").alias("hours_to_close"), (F.col("k") % 4 == 0).alias("coverage"), result.alias("result"))


def handset(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = read_table(spark, sf_dir, "part")
    return p.select(F.col("p_partkey").alias("device"), F.col("p_brand").alias("brand"), F.col("p_name").alias("model"), F.col("p_type").alias("type"), (F.col("p_size") % 2 == 0).alias("dual"))


def site(spark: SparkSession, sf_dir: str) -> DataFrame:
    supplier, nation, region = (read_table(spark, sf_dir, t) for t in ("supplier", "nation", "region"))
    places = nation.join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    return supplier.join(F.broadcast(places), F.col("s_nationkey") == F.col("n_nationkey")).select(
        F.col("s_suppkey").alias("site"), F.col("n_name").alias("area"), F.col("r_name").alias("state")
    )


def document_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A labelled task with real signal: text shape against quality."""
    labels = read_table(spark, sf_dir, "labels").select("doc_id", (F.lit(1) - F.col("quality")).alias("label"), "toxic")
    return labels.join(text_shape(spark, sf_dir), "doc_id")


def text_shape(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.greatest(F.char_length("text"), F.lit(1))
    words = F.regexp_count("text", F.lit(r"[^\x20\x09-\x0D]+"))
    return read_table(spark, sf_dir, "documents").select(
        "doc_id", n.cast("double").alias("chars"), words.cast("double").alias("words"),
        (F.regexp_count("text", F.lit(r"[^A-Za-zÀ-ɏ\s]")) / n).alias("non_letters"), (F.regexp_count("text", F.lit("[A-Z]")) / n).alias("capitals"),
        (F.regexp_count("text", F.lit(r"\n")) / n).alias("lines"), (n / F.greatest(words, F.lit(1))).alias("word_length"), "lang",
    )


def vector_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "embeddings")
    return e.select("vec_id", (F.col("label") == 0).cast("int").alias("label"), "embedding")


ROLES = {
    "subscriber": subscriber, "contact": contact, "touch": touch, "session": session, "ticket": ticket, "handset": handset, "site": site,
    "document_label": document_label, "vector_label": vector_label,
}


def register(spark: SparkSession, sf_dir: str) -> None:
    """Temp views of all tables and roles, for SQL text."""
    for name in SCHEMAS:
        read_table(spark, sf_dir, name).createOrReplaceTempView(name)
    for name, role in ROLES.items():
        role(spark, sf_dir).createOrReplaceTempView(name)


#: The role views as common table expressions for another SQL engine.
ROLE_SQL = {
    "subscriber": """subscriber AS (
  SELECT c_custkey AS sub_id, CASE c_mktsegment WHEN 'MACHINERY' THEN 'rival' WHEN 'BUILDING' THEN 'landline' ELSE 'home' END AS operator,
         c_mktsegment AS segment, c_acctbal AS balance, n_name AS area, r_name AS state, (18 + c_custkey % 60)::INT AS age_years
  FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)""",
    "contact": f"""contact AS (
  SELECT o_custkey AS src, dst, o_orderdate AS ts, CASE l_returnflag WHEN 'N' THEN 'call' WHEN 'A' THEN 'sms' ELSE 'mms' END AS kind,
         CASE WHEN l_returnflag = 'N' THEN l_quantity ELSE 0.0 END AS duration, l_extendedprice * (1 - l_discount) AS charge,
         l_partkey AS device, l_suppkey AS package
  FROM (SELECT *, lead(o_custkey) OVER (PARTITION BY l_partkey ORDER BY {", ".join(PART_ORDER)}) AS dst
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey) WHERE dst IS NOT NULL AND dst <> o_custkey)""",
    "event": """event AS (SELECT *, regexp_extract(props, '"k": *([0-9]+)', 1)::INT AS k FROM events)""",
    "touch": """touch AS (SELECT user_id AS src, k::BIGINT AS dst, ts, event_type AS kind, value FROM event)""",
    "session": """session AS (
  SELECT user_id AS sub_id, ts, CASE k % 3 WHEN 0 THEN '2G' WHEN 1 THEN '3G' ELSE '4G' END AS rat, (k // 3)::BIGINT AS site,
         CASE WHEN event_type = 'click' THEN value ELSE 0.0 END AS bytes_up, CASE WHEN event_type = 'view' THEN value ELSE 0.0 END AS bytes_down,
         CASE WHEN event_type = 'purchase' THEN value ELSE 0.0 END AS top_up, event_type = 'error' AS dropped FROM event)""",
    "ticket": """ticket AS (
  SELECT user_id AS sub_id, ts AS opened, value AS hours_to_close, k % 4 = 0 AS coverage, CASE WHEN k % 2 = 1 THEN 'solved' ELSE 'open' END AS result
  FROM event WHERE event_type = 'error' AND value >= 40)""",
    "handset": """handset AS (SELECT p_partkey AS device, p_brand AS brand, p_name AS model, p_type AS type, p_size % 2 = 0 AS dual FROM part)""",
    "site": """sites AS (
  SELECT s_suppkey AS site, n_name AS area, r_name AS state FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)""",
}
NEEDS = {"touch": ("event",), "session": ("event",), "ticket": ("event",)}


def with_roles(roles: str, body: str, *more: str) -> str:
    """SQL text: the role views named, further common table expressions, and the body."""
    names: list[str] = []
    for r in roles.split():
        for x in (*NEEDS.get(r, ()), r):
            if x not in names:
                names.append(x)
    parts = [*(ROLE_SQL[n] for n in names), *more]
    return ("WITH RECURSIVE " + ",\n".join(parts) + "\n" if parts else "") + body
