"""Where queries are registered, and SQL fragments that their oracles share."""

from __future__ import annotations

from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession

from ..operators import build
from ..operators.index import Index
from ..sources import planes, tables
from ..sources.storage import persisted

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None, name: str | None = None):
    """Register a query under its name, with the SQL that must agree."""

    def register(function):
        key = name or function.__name__
        QUERIES[key] = function
        if sql:
            ORACLES[key] = sql
        return function

    return register


def dot(a: str, b: str) -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda z: z[1] * z[2]))"


def norm(a: str) -> str:
    return f"sqrt({dot(a, a)})"


def sql_normals(n: int, d: int) -> str:
    """CTEs w0, w: unit normals by integer arithmetic."""
    return f"""w0 AS (SELECT i AS qid, list_transform(range(0, {d}), lambda j: (((31*i*i + 17*j*j + 101*i*j + 7*i + 13*j + 5) % 2003) - 1001) / 1001.0::DOUBLE) AS r FROM range(0, {n}) t(i)),
w AS (SELECT qid, list_transform(r, lambda v: v / {norm('r')}) AS w FROM w0)"""


def sql_planes_rows(points: str, n: int, d: int, share: float = 0.9, modulus: int = 500) -> str:
    """CTE planes (qid, q, q_norm), anchored at rows of points."""
    return f"""{sql_normals(n, d)},
pq AS (SELECT w.qid, list_append(w.w, -{share}::DOUBLE * {dot('w.w', f'p.x[1:{d}]')}) AS q FROM w JOIN {points} p ON p.id = (37 * w.qid) % {modulus}),
planes AS (SELECT qid, q, {norm('q')} AS q_norm FROM pq)"""


def sql_planes_box(n: int, d: int, share: float = 0.9) -> str:
    return f"""{sql_normals(n, d)},
pa AS (SELECT qid, w, list_transform(range(0, {d}), lambda j: ((13*qid + 29*j + 3) % 97) / 97.0::DOUBLE) AS a FROM w),
pq AS (SELECT qid, list_append(w, -{share}::DOUBLE * {dot('w', 'a')}) AS q FROM pa),
planes AS (SELECT qid, q, {norm('q')} AS q_norm FROM pq)"""


EMB = "emb AS (SELECT vec_id AS id, list_append(CAST(embedding AS DOUBLE[]), 1.0::DOUBLE) AS x, CAST(label AS BIGINT) AS label FROM embeddings)"

CLUSTER = f"""ml AS (SELECT label, unnest(CAST(embedding AS DOUBLE[])) AS v, generate_subscripts(embedding, 1) AS pos FROM embeddings),
mm AS (SELECT label, pos, round(avg(v), 9) AS v FROM ml GROUP BY label, pos),
means AS (SELECT label, list(v ORDER BY pos) AS mean FROM mm GROUP BY label),
unitm AS (SELECT label, list_transform(mean, lambda v: v / {norm('mean')}) AS centre FROM means),
emb AS (SELECT e.vec_id AS id, list_append(list_transform(list_zip(u.centre, CAST(e.embedding AS DOUBLE[])), lambda z: z[1] + z[2] * 0.1::DOUBLE), 1.0::DOUBLE) AS x, CAST(e.label AS BIGINT) AS label FROM embeddings e JOIN unitm u ON e.label = u.label)"""

LI4 = """emb AS (SELECT ('0x' || substr(md5(concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT), date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)))), 1, 15))::BIGINT AS id,
  [l_quantity / 50.0::DOUBLE, l_extendedprice / 105000.0::DOUBLE, l_discount * 10.0::DOUBLE, l_tax * 12.5::DOUBLE, 1.0::DOUBLE] AS x, l_orderkey, l_returnflag, l_linestatus FROM lineitem)"""

PART2 = "emb AS (SELECT p_partkey AS id, [p_size / 50.0::DOUBLE, p_retailprice / 1000.0::DOUBLE, 1.0::DOUBLE] AS x FROM part)"

LI6 = LI4.replace("l_tax * 12.5::DOUBLE, 1.0::DOUBLE]", "l_tax * 12.5::DOUBLE, date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)) / 3000.0::DOUBLE, l_linenumber / 7.0::DOUBLE, 1.0::DOUBLE]")

KINDS = ("click", "error", "login", "purchase", "view")
USERS = "emb AS (SELECT user_id AS id, [" + ", ".join([f"round(coalesce(avg(value) FILTER (event_type = '{k}'), 0.0::DOUBLE) / 100, 9)" for k in KINDS] + [f"count(*) FILTER (event_type = '{k}') / 100.0::DOUBLE" for k in KINDS]) + ", 1.0::DOUBLE] AS x FROM events GROUP BY user_id)"

ORDERS = "emb AS (SELECT o_orderkey AS id, [o_totalprice / 500000.0::DOUBLE, date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) / 3000.0::DOUBLE, 1.0::DOUBLE] AS x FROM orders)"

CUSTOMERS = "emb AS (SELECT c_custkey AS id, [c_acctbal / 10000.0::DOUBLE, c_nationkey / 25.0::DOUBLE, length(c_mktsegment) / 5.0::DOUBLE, 1.0::DOUBLE] AS x FROM customer)"


def sql_terms(table: str, key: str, text: str, d: int) -> str:
    """CTEs of a text column's word shares in d buckets."""
    return f"""dw AS (SELECT {key} AS id, list_filter(string_split_regex(lower({text}), '[^a-z]+'), lambda t: t <> '') AS ws FROM {table}),
db AS (SELECT id, unnest(ws) AS t FROM dw),
dc AS (SELECT id, (('0x' || substr(md5(t), 1, 8))::BIGINT) % {d} AS b, count(*) AS c FROM db GROUP BY ALL),
dd AS (SELECT dw.id, r.b, coalesce(dc.c, 0)::DOUBLE / greatest(len(dw.ws), 1)::DOUBLE AS v FROM dw CROSS JOIN (SELECT i AS b FROM range(0, {d}) t(i)) r LEFT JOIN dc ON dc.id = dw.id AND dc.b = r.b),
emb AS (SELECT id, list_append(list(v ORDER BY b), 1.0::DOUBLE) AS x FROM dd GROUP BY id)"""


DOC64 = sql_terms("documents", "doc_id", "text", 64)


def sql_topk(points: str, planes_sql: str, k: int = 10, where: str = "TRUE") -> str:
    """Plain scan: what every search must return."""
    return f"""WITH {points}, {planes_sql},
m AS (SELECT qid, id, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN planes WHERE {where}),
r AS (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY margin, id) AS rank, id, margin FROM m)
SELECT qid, rank, id, margin FROM r WHERE rank <= {k}"""


SETS = {
    "emb": (tables.emb, 64), "emb_scaled": (tables.emb_scaled, 64), "emb_cluster": (tables.emb_cluster, 64), "li4": (tables.li4, 4), "li6": (tables.li6, 6), "part2": (tables.part2, 2), "order2": (tables.order2, 2), "cust3": (tables.cust3, 3),
    "user_rates": (tables.user_rates, 10), "doc_tf": (tables.doc_tf, 64), "doc_tf256": (lambda spark, d: tables.doc_tf(spark, d, 256), 256), "doc_tf1024": (lambda spark, d: tables.doc_tf(spark, d, 1024), 1024), "page_tf": (tables.page_tf, 128), "conv_tf": (tables.conv_tf, 128),
}
ROWS = {"doc_tf": 200, "doc_tf256": 200, "doc_tf1024": 200, "emb": 500, "emb_scaled": 500, "emb_cluster": 500}  # sets whose planes are anchored at rows: ids below these are there

CHEAP = ("li4", "li6", "order2", "cust3", "part2")  # sets that are a row's own numbers: read again rather than written


def points_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return SETS[name][0](spark, sf_dir)


def planes_for(spark: SparkSession, sf_dir: str, name: str, n: int = 100, share: float = 0.9) -> DataFrame:
    """The planes that go with a set."""
    d = SETS[name][1]
    if name not in ROWS:
        return planes.through_box(spark, n, d, share)
    anchors = tables.doc_tf(spark, sf_dir, d, ROWS[name]) if name.startswith("doc_tf") else points_of(spark, sf_dir, name)  # texts of other rows aren't counted
    return planes.through_rows(spark, anchors, n, d, share, ROWS[name])


def index_of(spark: SparkSession, sf_dir: str, name: str, leaf_size: int, shards: int = 1, annotate: bool = True) -> Index:
    """An index of a set, built once a session."""
    return _index(spark.sparkContext.applicationId, sf_dir, name, leaf_size, shards, annotate)


@lru_cache(maxsize=32)
def _index(application: str, sf_dir: str, name: str, leaf_size: int, shards: int, annotate: bool) -> Index:
    spark = SparkSession.getActiveSession()
    points = points_of(spark, sf_dir, name).select("id", "x")
    return build.hybrid(points if name in CHEAP else persisted(points, f"set-{name}"), leaf_size, shards=shards, annotate=annotate)
