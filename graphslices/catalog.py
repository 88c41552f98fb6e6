"""Tables of a folder, and graphs drawn from them. Each graph is one SELECT of pairs, which Spark and the oracle read alike."""

from __future__ import annotations

import string

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

_LINKS = "2 * page_id AS a, 2 * ({id}) + 1 AS b"
_SPARK_ID = "cast(conv(substr(md5({x}), 1, 12), 16, 10) AS BIGINT)"
_DUCK_ID = "cast('0x' || substr(md5({x}), 1, 12) AS BIGINT)"

# name -> pairs (a, b); bipartite ids are 2k and 2k + 1
PAIRS = {
    "supplier_part": "SELECT DISTINCT 2 * l_suppkey AS a, 2 * l_partkey + 1 AS b FROM {lineitem}",
    "customer_part": "SELECT DISTINCT 2 * o_custkey AS a, 2 * l_partkey + 1 AS b FROM {orders} JOIN {lineitem} ON o_orderkey = l_orderkey",
    "order_part": "SELECT DISTINCT 2 * l_orderkey AS a, 2 * l_partkey + 1 AS b FROM {lineitem}",
    "copurchase": "SELECT DISTINCT x.l_partkey AS a, y.l_partkey AS b FROM {lineitem} x JOIN {lineitem} y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey",
    "geo_tree": """SELECT cast(10000000 + n_nationkey AS BIGINT) AS a, cast(20000000 + n_regionkey AS BIGINT) AS b FROM {nation}
        UNION ALL SELECT 2 * c_custkey, 10000000 + c_nationkey FROM {customer} UNION ALL SELECT 2 * s_suppkey + 1, 10000000 + s_nationkey FROM {supplier}""",
    "event_chain": "SELECT a, b FROM (SELECT event_id AS a, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM {events}) WHERE b IS NOT NULL",
    "conv_chain": "SELECT a, b FROM (SELECT conv_id * 100 + turn AS a, lead(conv_id * 100 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM {conversations}) WHERE b IS NOT NULL",
    "page_links": {
        "spark": f"SELECT DISTINCT 2 * page_id AS a, 2 * {_SPARK_ID.format(x='x')} + 1 AS b FROM (SELECT page_id, explode(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS x FROM {{pages}})",
        "duck": f"SELECT DISTINCT 2 * page_id AS a, 2 * {_DUCK_ID.format(x='x')} + 1 AS b FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS x FROM pages)",
    },
    "shared_lines": {
        "spark": f"""WITH l AS (SELECT DISTINCT doc_id, x FROM (SELECT doc_id, explode(split(text, '\\n')) AS x FROM {{documents}}) WHERE length(x) > 30),
            k AS (SELECT x FROM l GROUP BY x HAVING count(*) >= 2) SELECT 2 * doc_id AS a, 2 * {_SPARK_ID.format(x='x')} + 1 AS b FROM l JOIN k USING (x)""",
        "duck": f"""WITH l AS (SELECT DISTINCT doc_id, x FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE length(x) > 30),
            k AS (SELECT x FROM l GROUP BY x HAVING count(*) >= 2) SELECT 2 * doc_id AS a, 2 * {_DUCK_ID.format(x='x')} + 1 AS b FROM l JOIN k USING (x)""",
    },
    "purchase_hour": {
        "spark": "SELECT DISTINCT 2 * user_id AS a, 2 * timestampdiff(HOUR, timestamp_ntz'1970-01-01 00:00:00', ts) + 1 AS b FROM {events} WHERE event_type = 'purchase'",
        "duck": "SELECT DISTINCT 2 * user_id AS a, 2 * cast(floor(epoch(ts) / 3600) AS BIGINT) + 1 AS b FROM events WHERE event_type = 'purchase'",
    },
    "user_hour": {
        "spark": "SELECT DISTINCT 2 * user_id AS a, 2 * timestampdiff(HOUR, timestamp_ntz'1970-01-01 00:00:00', ts) + 1 AS b FROM {events}",
        "duck": "SELECT DISTINCT 2 * user_id AS a, 2 * cast(floor(epoch(ts) / 3600) AS BIGINT) + 1 AS b FROM events",
    },
}
# Their SELECTs are distinct, and a is even and b odd, or a less than b: in both directions they are distinct without another shuffle.
ONCE = ("supplier_part", "customer_part", "order_part", "copurchase", "page_links", "purchase_hour", "user_hour")
GRAPHS = (*PAIRS, "knn", "kron", "er")


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fields(text: str) -> list[str]:
    return sorted({f for _, f, _, _ in string.Formatter().parse(text) if f})


def sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """A statement over {table} fields as a DataFrame of the folder's tables."""
    return spark.sql(text, **{n: load_table(spark, sf_dir, n) for n in fields(text)})


def duck(text: str) -> str:
    """The same statement over plain table names."""
    return text.format(**{n: n for n in fields(text)})


def pairs(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    text = PAIRS[name]
    return sql(spark, sf_dir, text["spark"] if isinstance(text, dict) else text)


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Edges (src, dst) of a named graph, both directions, without loops and repetitions."""
    from graphslices import generate
    from graphslices.edges import normalize_edges

    if name == "kron":
        return generate.kronecker_edges(spark)
    if name == "er":
        return generate.er_edges_pairs(spark)
    if name == "knn":
        from graphslices.relational import knn_edges

        return knn_edges(spark, sf_dir)
    return normalize_edges(pairs(spark, sf_dir, name), "a", "b", once=name in ONCE)


def graph_sql(name: str) -> str:
    """A graph's edges for the oracle."""
    from graphslices import generate

    if name == "knn":
        from graphslices.oracles import RELATIONAL

        return RELATIONAL["knn_edges"]
    if name in ("kron", "er"):
        inner = generate.KRON_SQL if name == "kron" else generate.ER_SQL
    else:
        text = PAIRS[name]
        inner = text["duck"] if isinstance(text, dict) else duck(text)
    return f"SELECT DISTINCT src, dst FROM (SELECT a AS src, b AS dst FROM ({inner}) UNION ALL SELECT b, a FROM ({inner})) WHERE src <> dst"
