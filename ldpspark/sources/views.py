"""User views: one row (user, item) a user over the given tables. A null item is no contribution and is dropped."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.functions.dialect import DUCK, SPARK, Dialect

from .tables import load


def _line_user(d: Dialect) -> str:
    return "concat_ws('-', " + ", ".join(d.text(c) for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")) + ")"


def _planted(d: Dialect) -> str:
    """Three frequent items among part keys: 30, 20 and 12 of a hundred users, drawn by a keyed hash."""
    t = f"{d.digits(d.digest('plant', 42, _line_user(d)), 1, 13)} % 1000"
    return f"CASE WHEN {t} < 300 THEN 11 WHEN {t} < 500 THEN 2222 WHEN {t} < 620 THEN 40404 ELSE 50000 + l_partkey END"


def _host(d: Dialect) -> str:
    return "regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)"


#: name: (table, user, item) as texts of a dialect.
VIEWS: dict[str, tuple[str, Callable[[Dialect], str], Callable[[Dialect], str]]] = {
    "u_planted": ("lineitem", _line_user, _planted),
    "u_part": ("lineitem", _line_user, lambda d: "l_partkey"),
    "u_supp": ("lineitem", _line_user, lambda d: "l_suppkey"),
    "u_qty": ("lineitem", _line_user, lambda d: "CAST(l_quantity AS BIGINT)"),
    "v_flags": ("lineitem", _line_user, lambda d: "CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END + CASE WHEN l_linestatus = 'O' THEN 2 ELSE 0 END + CASE WHEN l_quantity > 25 THEN 4 ELSE 0 END + CASE WHEN l_discount > 0.05 THEN 8 ELSE 0 END"),
    "u_order_status": ("orders", lambda d: "o_orderkey", lambda d: "CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END"),
    "u_order_cust": ("orders", lambda d: "o_orderkey", lambda d: "o_custkey"),
    "u_order_priority": ("orders", lambda d: "o_orderkey", lambda d: "CAST(substr(o_orderpriority, 1, 1) AS BIGINT)"),
    "u_event_type": ("events", lambda d: "event_id", lambda d: "CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 WHEN 'view' THEN 4 END"),
    "u_event_k": ("events", lambda d: "event_id", lambda d: "CAST(json_extract_string(props, '$.k') AS BIGINT)" if d.duck else "CAST(get_json_object(props, '$.k') AS BIGINT)"),
    "u_lang": ("documents", lambda d: "doc_id", lambda d: "CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 WHEN 'fr' THEN 3 END"),
    "u_source": ("documents", lambda d: "doc_id", lambda d: "CAST(substr(source, 4) AS BIGINT)"),
    "u_host": ("pages", lambda d: "page_id", lambda d: f"{d.digits(f'md5({_host(d)})', 1, 4)}"),
    "u_role": ("conversations", lambda d: "concat_ws('-', " + d.text("conv_id") + ", " + d.text("turn") + ")", lambda d: "CASE role WHEN 'user' THEN 0 WHEN 'assistant' THEN 1 WHEN 'system' THEN 2 END"),
    "u_label_bits": ("labels", lambda d: "doc_id", lambda d: "quality + 2 * toxic"),
    "u_segment": ("customer", lambda d: "c_custkey", lambda d: f"{d.digits('md5(c_mktsegment)', 1, 1)}"),
}


def sql(name: str, d: Dialect = DUCK) -> str:
    """The view as a query over its table."""
    if name == "u_word":
        if d.duck:
            return (
                "SELECT concat_ws('-', CAST(doc_id AS VARCHAR), CAST(pos AS VARCHAR)) AS \"user\", CAST('0x' || substr(md5(w), 1, 6) AS BIGINT) AS item FROM "
                "(SELECT doc_id, unnest(ws) AS w, generate_subscripts(ws, 1) - 1 AS pos FROM (SELECT doc_id, string_split(replace(text, chr(10), ' '), ' ') AS ws FROM documents)) WHERE w <> ''"
            )
        raise ValueError("u_word is built by view()")
    if name == "v_signs16":
        bits = " + ".join(f"CASE WHEN embedding[{i + (1 if d.duck else 0)}] > 0 THEN {1 << i} ELSE 0 END" for i in range(16))
        return f'SELECT vec_id AS {"\"user\"" if d.duck else "user"}, CAST({bits} AS BIGINT) AS item FROM embeddings'
    if name == "u_nation":
        return f'SELECT {_line_user(d)} AS {"\"user\"" if d.duck else "user"}, CAST(n_nationkey AS BIGINT) AS item FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey'
    if name == "u_person":
        pick = d.digest("pick", 42, "event_id")
        item = VIEWS["u_event_type"][2](d)
        q = '"user"' if d.duck else "user"
        return f"SELECT {q}, item FROM (SELECT user_id AS {q}, CAST({item} AS BIGINT) AS item, row_number() OVER (PARTITION BY user_id ORDER BY {pick}, event_id) AS n FROM events) WHERE n = 1"
    table, user, item = VIEWS[name]
    q = '"user"' if d.duck else "user"
    return f"SELECT {user(d)} AS {q}, CAST({item(d)} AS BIGINT) AS item FROM {table}"


def view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(user, item) of the named view; the scan reads the view's columns only."""
    if name == "u_word":
        docs = load(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split(F.translate("text", "\n", " "), " ")).alias("pos", "w")).filter("w <> ''")
        return docs.select(F.concat_ws("-", F.col("doc_id").cast("string"), F.col("pos").cast("string")).alias("user"), F.expr(SPARK.digits("md5(w)", 1, 6)).alias("item"))
    if name == "u_nation":
        line, supp, nation = (load(spark, sf_dir, t) for t in ("lineitem", "supplier", "nation"))
        joined = line.join(supp, F.col("l_suppkey") == F.col("s_suppkey")).join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey"))
        return joined.select(F.expr(_line_user(SPARK)).alias("user"), F.col("n_nationkey").cast("long").alias("item"))
    if name == "v_signs16":
        bits = [F.when(F.col("embedding")[i] > 0, 1 << i).otherwise(0) for i in range(16)]
        return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("user"), sum(bits[1:], bits[0]).cast("long").alias("item"))
    if name == "u_person":
        from pyspark.sql import Window

        events = load(spark, sf_dir, "events").select(F.col("user_id").alias("user"), F.expr(VIEWS["u_event_type"][2](SPARK)).cast("long").alias("item"), F.expr(SPARK.digest("pick", 42, "event_id")).alias("pick"), "event_id")
        first = F.row_number().over(Window.partitionBy("user").orderBy("pick", "event_id"))
        return events.withColumn("n", first).filter("n = 1").select("user", "item")
    table, user, item = VIEWS[name]
    return load(spark, sf_dir, table).select(F.expr(user(SPARK)).alias("user"), F.expr(item(SPARK)).cast("long").alias("item")).filter("item is not null")


NAMES = [*VIEWS, "u_word", "v_signs16", "u_nation", "u_person"]


def assert_one_message(users: DataFrame) -> DataFrame:
    """Users with more than one row, which would break the rule of one message a user."""
    return users.groupBy("user").agg(F.count("*").alias("rows")).filter("rows > 1")
