"""The given tables, and point views over them as SQL that Spark and DuckDB both run.

`{days:c}` and `{hours:c}` are the only places where the dialects differ.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

# l_orderkey and l_linenumber repeat; with part and price the key is unique. Fits a long up to l_orderkey 576,000; beyond that both engines raise an overflow, unless ids are wide (see view).
LINE_ID = "((l_orderkey * 8 + l_linenumber) * 200003 + l_partkey) * 10000019 + CAST(round(l_extendedprice * 100) AS BIGINT)"

VIEWS = {
    "pv_line2": f"SELECT {LINE_ID} AS pid, (l_extendedprice - 52950) / 52950 * CAST(2.5 AS DOUBLE) AS x, {{days:l_shipdate}} / CAST(2499 AS DOUBLE) * 5 - CAST(2.5 AS DOUBLE) AS y, CAST(0 AS DOUBLE) AS z FROM lineitem",
    "pv_line3": f"SELECT {LINE_ID} AS pid, (l_extendedprice - 52950) / 52950 * CAST(2.5 AS DOUBLE) AS x, {{days:l_shipdate}} / CAST(2499 AS DOUBLE) * 5 - CAST(2.5 AS DOUBLE) AS y, (l_quantity - CAST(25.5 AS DOUBLE)) / CAST(24.5 AS DOUBLE) * CAST(2.5 AS DOUBLE) AS z FROM lineitem",
    "pv_grid2": f"SELECT {LINE_ID} AS pid, l_quantity AS x, l_discount * 100 AS y, CAST(0 AS DOUBLE) AS z FROM lineitem",
    "pv_order2": "SELECT o_orderkey AS pid, o_totalprice / CAST(100000 AS DOUBLE) AS x, {days:o_orderdate} / CAST(480 AS DOUBLE) AS y, CAST(0 AS DOUBLE) AS z FROM orders",
    "pv_ring2": "SELECT ring, edge, x AS x1, y AS y1, coalesce(lead(x) OVER w, first_value(x) OVER w) AS x2, coalesce(lead(y) OVER w, first_value(y) OVER w) AS y2 FROM (SELECT o_custkey AS ring, o_orderkey AS edge, o_totalprice / CAST(100000 AS DOUBLE) AS x, {days:o_orderdate} / CAST(480 AS DOUBLE) AS y FROM orders) o WINDOW w AS (PARTITION BY ring ORDER BY edge, x, y)",
    "pv_part2": "SELECT p_partkey AS pid, CAST(p_size AS DOUBLE) AS x, p_retailprice - 900 AS y, CAST(0 AS DOUBLE) AS z FROM part",
    "pv_cust2": "SELECT c_custkey AS pid, c_acctbal / CAST(2000 AS DOUBLE) AS x, c_nationkey / CAST(5 AS DOUBLE) AS y, CAST(0 AS DOUBLE) AS z FROM customer",
    "pv_supp2": "SELECT s_suppkey AS seed_id, s_acctbal / CAST(2000 AS DOUBLE) AS x, s_nationkey / CAST(5 AS DOUBLE) AS y, CAST(0 AS DOUBLE) AS z FROM supplier",
    "pv_nation2": "SELECT CAST(n_nationkey AS BIGINT) AS seed_id, CAST(n_nationkey % 5 - 2 AS DOUBLE) AS x, CAST(floor(n_nationkey / CAST(5 AS DOUBLE)) - 2 AS DOUBLE) AS y, CAST(0 AS DOUBLE) AS z, n_regionkey FROM nation",
    "pv_event2": "SELECT event_id AS pid, user_id, {hours:ts} AS x, value / CAST(100 AS DOUBLE) AS y, CAST(0 AS DOUBLE) AS z FROM events",
    "pv_level": "SELECT CAST(r_regionkey AS BIGINT) AS level, CAST(0.05 AS DOUBLE) / power(2, r_regionkey) AS h_min, CAST(0.25 AS DOUBLE) / power(2, r_regionkey) AS h_max FROM region",
    "pv_doc2": "SELECT d.doc_id AS pid, ln(CAST(1 + n_chars AS DOUBLE)) AS x, n_chars / CAST(1000 AS DOUBLE) AS y, CAST(0 AS DOUBLE) AS z, CASE WHEN quality = 0 THEN CAST(0.01 AS DOUBLE) ELSE CAST(0.02 AS DOUBLE) END AS r FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
}


def spark_sql(text: str) -> str:
    text = re.sub(r"\{days:(\w+)\}", r"datediff(\1, DATE '1995-01-01')", text)
    return re.sub(r"\{hours:(\w+)\}", r"((unix_micros(\1) - unix_micros(TIMESTAMP '2024-01-01')) / CAST(3600000000 AS DOUBLE))", text)


def duck_sql(text: str) -> str:
    text = re.sub(r"\{days:(\w+)\}", r"date_diff('day', DATE '1995-01-01', CAST(\1 AS DATE))", text)
    return re.sub(r"\{hours:(\w+)\}", r"((epoch_us(\1) - epoch_us(TIMESTAMP '2024-01-01')) / CAST(3600000000 AS DOUBLE))", text)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table by name; Spark prunes its columns and pushes filters into the scan. Times without a zone count as the session's, so that time functions take them."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    plain = [c for c, t in df.dtypes if t == "timestamp_ntz"]
    return df.withColumns({c: df[c].cast("timestamp") for c in plain}) if plain else df


def view(spark: SparkSession, sf_dir: str, name: str, wide_ids: bool = False) -> DataFrame:
    """A point view, without temporary names in the session: the tables are parameters of the statement. Line ids as decimals, if asked, fit any number of orders."""
    text = spark_sql(VIEWS[name])
    if wide_ids:
        text = text.replace(LINE_ID, LINE_ID.replace("(l_orderkey * 8", "(CAST(l_orderkey AS DECIMAL(19, 0)) * 8"))
    used = [t for t in TABLES if re.search(rf"\b(FROM|JOIN) {t}\b", text)]
    for t in used:
        text = re.sub(rf"\b(FROM|JOIN) {t}\b", rf"\1 {{{t}}}", text)
    return spark.sql(text, **{t: load(spark, sf_dir, t) for t in used})


def with_views(body: str, *names: str) -> str:
    """DuckDB statement with the named views in front."""
    return "WITH " + ", ".join(f"{n} AS ({duck_sql(VIEWS[n])})" for n in names) + " " + body
