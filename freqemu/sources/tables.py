"""Reading and writing tables; elements (key, value) of the experiment workloads."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

TOKEN = r"[\p{L}\p{N}]+"
HOST = r"^[a-zA-Z]+://([^/:?#]+)"


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def read(spark: SparkSession, path: str, form: str = "parquet", schema=None, **options) -> DataFrame:
    """Any of parquet, orc, csv, json, text."""
    reader = spark.read.format(form).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def write(df: DataFrame, path: str, form: str = "parquet", by: Sequence[str] = (), mode: str = "overwrite", **options) -> str:
    writer = df.write.format(form).mode(mode).options(**options)
    (writer.partitionBy(*by) if by else writer).save(path)
    return path


def to_elements(df: DataFrame, keys: Sequence[str | Column], value: str | Column | None = None, extra: Sequence[str | Column] = ()) -> DataFrame:
    """(key, value, ...): a composite key is joined by bars; bars and backslashes inside get a backslash before them.

    Rows with a null key, or a null, non-positive or non-finite value are left out.
    """
    cols = [F.col(k) if isinstance(k, str) else k for k in keys]
    parts = [c.cast("string") for c in cols]
    key = parts[0] if len(parts) == 1 else F.concat_ws("|", *[F.regexp_replace(p, r"([\\|])", r"\\$1") for p in parts])
    some = cols[0].isNotNull()
    for c in cols[1:]:
        some = some & c.isNotNull()
    v = F.lit(1.0) if value is None else (F.col(value) if isinstance(value, str) else value).cast("double")
    kept = df.where(some).select(key.alias("key"), v.alias("value"), *extra)
    return kept if value is None else kept.where((F.col("value") > 0) & (F.col("value") < float("inf")) & ~F.isnan("value"))


def tokens(df: DataFrame, text: str = "text", extra: Sequence[str] = ()) -> DataFrame:
    words = df.select(*extra, F.explode(F.regexp_extract_all(F.lower(F.col(text)), F.lit(TOKEN), F.lit(0))).alias("key"))
    return words.select("key", F.lit(1.0).alias("value"), *extra)


def lines(df: DataFrame, text: str = "text") -> DataFrame:
    parts = df.select(F.explode(F.split(F.col(text), "\n")).alias("key"))
    return parts.where(F.length(F.trim("key")) > 0).select("key", F.lit(1.0).alias("value"))


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The temporal graph: customer to supplier and part, at the order's date."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_partkey")
    return o.join(li, F.col("o_orderkey") == F.col("l_orderkey")).select(
        F.col("o_custkey").alias("src"), F.col("l_suppkey").alias("dst"), F.col("l_partkey").alias("part"), F.col("o_orderdate").alias("at")
    )


def elements(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Elements (key, value) of one of the workloads in ``FREQUENCY_SQL``."""
    t = lambda x: load(spark, sf_dir, x)
    if name == "doc_words":
        return tokens(t("documents"))
    if name == "conv_words":
        return tokens(t("conversations"))
    if name == "doc_lines":
        return lines(t("documents"))
    if name == "page_hosts":
        return to_elements(t("pages").select(F.regexp_extract("url", HOST, 1).alias("h")).where("h <> ''"), ["h"])
    if name == "cust_out":
        return to_elements(t("orders"), ["o_custkey"])
    if name == "part_in":
        return to_elements(t("lineitem"), ["l_partkey"])
    if name == "supp_in":
        return to_elements(t("lineitem"), ["l_suppkey"])
    if name == "ps_qty":
        return to_elements(t("lineitem").where("l_returnflag <> 'R'"), ["l_suppkey", "l_partkey"], "l_quantity")
    if name == "li_tuple":
        discount = F.round(F.col("l_discount") * 100).cast("int")
        return to_elements(t("lineitem"), ["l_suppkey", F.col("l_quantity").cast("int"), discount, "l_returnflag", "l_linestatus"])
    if name == "event_tuple":
        return to_elements(t("events"), ["user_id", "event_type", "props"])
    if name == "event_props":
        return to_elements(t("events"), ["props"])
    if name == "event_user_val":
        return to_elements(t("events"), ["user_id"], "value")
    if name == "doc_source":
        return to_elements(t("documents"), ["source"])
    if name == "cust_price":
        return to_elements(t("orders"), ["o_custkey"], "o_totalprice")
    raise ValueError(name)


def _count(table: str, key: str, where: str = "true") -> str:
    return f"SELECT {key} AS key, CAST(count(*) AS DOUBLE) AS w FROM {table} WHERE {where} GROUP BY 1"


#: For each workload, SQL for its frequencies (key, w).
FREQUENCY_SQL = {
    "doc_words": "SELECT key, CAST(count(*) AS DOUBLE) AS w FROM (SELECT unnest(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+')) AS key FROM documents) x GROUP BY 1",
    "conv_words": "SELECT key, CAST(count(*) AS DOUBLE) AS w FROM (SELECT unnest(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+')) AS key FROM conversations) x GROUP BY 1",
    "doc_lines": "SELECT key, CAST(count(*) AS DOUBLE) AS w FROM (SELECT unnest(string_split(text, chr(10))) AS key FROM documents) x WHERE length(trim(key)) > 0 GROUP BY 1",
    "page_hosts": _count("pages", "regexp_extract(url, '^[a-zA-Z]+://([^/:?#]+)', 1)"),
    "cust_out": _count("orders", "CAST(o_custkey AS VARCHAR)"),
    "part_in": _count("lineitem", "CAST(l_partkey AS VARCHAR)"),
    "supp_in": _count("lineitem", "CAST(l_suppkey AS VARCHAR)"),
    "ps_qty": "SELECT concat_ws('|', l_suppkey, l_partkey) AS key, sum(l_quantity) AS w FROM lineitem WHERE l_returnflag <> 'R' GROUP BY 1",
    "li_tuple": _count("lineitem", "concat_ws('|', l_suppkey, CAST(l_quantity AS INTEGER), CAST(round(l_discount * 100) AS INTEGER), l_returnflag, l_linestatus)"),
    "event_tuple": _count("events", "concat_ws('|', user_id, event_type, props)"),
    "event_props": _count("events", "props"),
    "event_user_val": "SELECT CAST(user_id AS VARCHAR) AS key, sum(value) AS w FROM events WHERE value > 0 GROUP BY 1",
    "doc_source": _count("documents", "source"),
    "cust_price": "SELECT CAST(o_custkey AS VARCHAR) AS key, sum(o_totalprice) AS w FROM orders WHERE o_totalprice > 0 GROUP BY 1",
}
