"""Queries on label groups: any group with a centre and a covering radius obeys the bounds, and SQL can compute it too."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import exprs as E
from ..operators.build import distance2
from .registry import CLUSTER, dot, norm, planes_for, points_of, query, sql_planes_rows


def gap(a: str, b: str) -> str:
    return f"sqrt(list_sum(list_transform(list_zip({a}, {b}), lambda z: (z[1] - z[2]) * (z[1] - z[2]))))"


GROUPS = f"""{CLUSTER}, {sql_planes_rows('emb', 100, 64)},
gl AS (SELECT label, unnest(x) AS v, generate_subscripts(x, 1) AS pos FROM emb),
gm AS (SELECT label, pos, round(avg(v), 9) AS v FROM gl GROUP BY label, pos),
gc AS (SELECT label, list(v ORDER BY pos) AS c FROM gm GROUP BY label),
g AS (SELECT e.label, any_value(c) AS c, {norm('any_value(c)')} AS c_norm, max({gap('x', 'c')}) AS radius, count(*) AS n FROM emb e JOIN gc ON e.label = gc.label GROUP BY e.label),
lp AS (SELECT e.label, e.id, e.x, c, c_norm, {gap('x', 'c')} AS r_x, {dot('x', 'c')} / c_norm AS x_par FROM emb e JOIN g ON e.label = g.label),
pp AS (SELECT *, {norm("list_transform(list_zip(x, c), lambda z: z[1] - x_par / c_norm * z[2])")} AS x_perp FROM lp),
qp AS (SELECT qid, q, q_norm, g.label, g.c_norm AS gn, {dot('c', 'q')} AS ip FROM planes CROSS JOIN g),
b AS (SELECT qp.qid, pp.id, pp.label, abs({dot('x', 'q')}) AS margin, greatest(abs(ip) - q_norm * r_x, 0) AS ball,
  ip / c_norm * x_par AS along, sqrt(greatest(q_norm * q_norm - (ip / c_norm) * (ip / c_norm), 0)) * x_perp AS across FROM pp JOIN qp ON pp.label = qp.label),
bc AS (SELECT *, CASE WHEN along - across > 0 THEN along - across WHEN along + across < 0 THEN -(along + across) ELSE 0 END AS cone FROM b)"""


def label_groups(spark, d) -> DataFrame:
    """label, center, center_norm, radius and n of each label of the clustered set."""
    points = points_of(spark, d, "emb_cluster")
    means = points.select("label", F.posexplode("x").alias("pos", "v")).groupBy("label", "pos").agg(F.round(F.avg("v"), 9).alias("v"))
    centre = means.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "v"))), lambda s: s["v"]).alias("center"))
    met = points.join(F.broadcast(centre), "label")  # ten labels
    whole = met.groupBy("label", "center").agg(F.max(F.sqrt(distance2("x", "center"))).alias("radius"), F.count("*").alias("n"))
    return whole.withColumn("center_norm", E.norm(F.col("center")))


def label_points(spark, d) -> DataFrame:
    """Points with their label's centre and the three numbers that leaves keep."""
    met = points_of(spark, d, "emb_cluster").join(F.broadcast(label_groups(spark, d)), "label")
    parts = met.withColumn("r_x", F.sqrt(distance2("x", "center"))).withColumn("x_par", E.dot(F.col("x"), F.col("center")) / F.col("center_norm"))
    across = F.zip_with("x", "center", lambda a, c: a - F.col("x_par") / F.col("center_norm") * c)
    return parts.withColumn("x_perp", E.norm(across))


def label_bounds(spark, d, planes: DataFrame | None = None) -> DataFrame:
    """qid, id, label, margin, ball and cone of all pairs."""
    some = planes_for(spark, d, "emb_cluster") if planes is None else planes
    pairs = label_points(spark, d).crossJoin(F.broadcast(some))
    ip = E.dot(F.col("center"), F.col("q"), 65)
    with_ip = pairs.select("qid", "id", "label", "q_norm", "center_norm", "r_x", "x_par", "x_perp", F.inline(F.array(F.struct(ip.alias("ip"), E.absdot(F.col("x"), F.col("q"), 65).alias("margin")))))
    cone = E.point_cone_bound(F.col("ip"), F.col("center_norm"), F.col("q_norm"), F.col("x_par"), F.col("x_perp"))
    return with_ip.select("qid", "id", "label", "margin", "q_norm", "x_par", "x_perp", E.point_ball_bound(F.col("ip"), F.col("q_norm"), F.col("r_x")).alias("ball"), cone.alias("cone"))


@query(f"WITH {GROUPS} SELECT label, pos - 1 AS pos, v FROM gm")
def centers_by_label(spark, d):
    return label_groups(spark, d).select("label", F.posexplode("center").alias("pos", "v")).withColumn("pos", F.col("pos").cast("long"))


@query(f"WITH {GROUPS} SELECT label, round(radius, 9) AS radius, n FROM g")
def radii_by_label(spark, d):
    return label_groups(spark, d).select("label", F.round("radius", 9).alias("radius"), "n")


@query(f"""WITH {CLUSTER}, v AS (SELECT label, arg_min(x, id) AS v FROM emb GROUP BY label),
d1 AS (SELECT e.label, e.id, e.x, {gap('e.x', 'v.v')} AS far FROM emb e JOIN v ON e.label = v.label), a AS (SELECT label, arg_max(id, (far, -id)) AS a, arg_max(x, (far, -id)) AS ax FROM d1 GROUP BY label),
d2 AS (SELECT e.label, e.id, {gap('e.x', 'a.ax')} AS far, a.a FROM emb e JOIN a ON e.label = a.label) SELECT label, any_value(a) AS a, arg_max(id, (far, -id)) AS b FROM d2 GROUP BY label""")
def pivot_sweep(spark, d):
    """Two sweeps in each label group: the point farthest from its least id, and the one farthest from that."""
    points = points_of(spark, d, "emb_cluster")
    far = lambda a, b: F.struct(F.sqrt(distance2(a, b)).alias("far"), -F.col("id"))
    start = points.groupBy("label").agg(F.min_by("x", "id").alias("v"))
    first = points.join(start, "label").groupBy("label").agg(F.max_by(F.struct("id", "x"), far("x", "v")).alias("a"))
    second = points.join(first, "label").withColumn("ax", F.col("a.x")).groupBy("label", "a.id").agg(F.max_by(F.col("id"), far("x", "ax")).alias("b"))
    return second.toDF("label", "a", "b")


@query(f"WITH {GROUPS} SELECT qid, qp.label, round(greatest(abs(ip) - q_norm * radius, 0), 9) AS bound FROM qp JOIN g ON qp.label = g.label")
def node_bound_by_label(spark, d):
    met = label_groups(spark, d).crossJoin(F.broadcast(planes_for(spark, d, "emb_cluster")))
    return met.select("qid", "label", F.round(E.node_bound(E.dot(F.col("center"), F.col("q"), 65), F.col("q_norm"), F.col("radius")), 9).alias("bound"))


@query(f"WITH {GROUPS} SELECT qid, id, round(ball, 9) AS ball FROM bc")
def ball_bound(spark, d):
    return label_bounds(spark, d).select("qid", "id", F.round("ball", 9).alias("ball"))


@query(f"WITH {GROUPS} SELECT qid, id, round(cone, 7) AS cone FROM bc")
def cone_bound(spark, d):
    return label_bounds(spark, d).select("qid", "id", F.round("cone", 7).alias("cone"))


@query(f"WITH {GROUPS} SELECT qid, id FROM bc WHERE cone <= 0.05 AND ball <= 0.05")
def bound_survivors(spark, d):
    return label_bounds(spark, d).filter((F.col("ball") <= 0.05) & (F.col("cone") <= 0.05)).select("qid", "id")


@query(f"WITH {GROUPS} SELECT qid, count(*) AS n, count(*) FILTER (ball > 0.05) AS by_ball, count(*) FILTER (ball <= 0.05 AND cone > 0.05) AS by_cone FROM bc GROUP BY qid")
def prune_rates(spark, d):
    by_cone = (F.col("ball") <= 0.05) & (F.col("cone") > 0.05)
    return label_bounds(spark, d).groupBy("qid").agg(F.count("*").alias("n"), F.count_if(F.col("ball") > 0.05).alias("by_ball"), F.count_if(by_cone).alias("by_cone"))


@query("SELECT 0::BIGINT AS ball, 0::BIGINT AS cone")
def bound_violations(spark, d):
    """Bounds above the margin they bound, over near and far planes."""
    from ..sources import planes

    every = planes_for(spark, d, "emb_cluster", 30).unionByName(planes.far_off(spark, 64).withColumn("qid", F.col("qid") + 1000))
    return label_bounds(spark, d, every).agg(F.count_if(F.col("ball") > F.col("margin") + 1e-9).alias("ball"), F.count_if(F.col("cone") - E.cone_slack(F.col("q_norm"), F.col("x_par"), F.col("x_perp")) > F.col("margin")).alias("cone"))


@query("SELECT 0::BIGINT AS n")
def cone_ge_ball(spark, d):
    return label_bounds(spark, d).agg(F.count_if(F.col("cone") < F.col("ball") - 1e-7).alias("n"))


@query(f"WITH {GROUPS} SELECT round(avg(cone - ball), 6) AS cone_gain FROM bc")
def bound_tightness(spark, d):
    return label_bounds(spark, d).agg(F.round(F.avg(F.col("cone") - F.col("ball")), 6).alias("cone_gain"))


@query(f"WITH {GROUPS} SELECT qid, qp.label FROM qp JOIN g ON qp.label = g.label WHERE greatest(abs(ip) - q_norm * radius, 0) <= 0.01")
def theta_prune(spark, d):
    """Planes joined with the groups that they can come within 0.01 of."""
    some, groups = planes_for(spark, d, "emb_cluster"), label_groups(spark, d)
    bound = E.node_bound(E.dot(F.col("center"), F.col("q")), F.col("q_norm"), F.col("radius"))
    return groups.join(F.broadcast(some), bound <= 0.01).select("qid", "label")


@query(f"WITH {GROUPS} SELECT count(*) AS n FROM emb WHERE label IN (SELECT qp.label FROM qp JOIN g ON qp.label = g.label WHERE qid = 3 AND greatest(abs(ip) - q_norm * radius, 0) <= 0.01)")
def survivor_semi(spark, d):
    """Points of the groups that plane 3 can reach."""
    return points_of(spark, d, "emb_cluster").join(theta_prune(spark, d).filter("qid = 3"), "label", "left_semi").agg(F.count("*").alias("n"))


@query(f"""WITH {CLUSTER}, {sql_planes_rows('emb', 100, 64)}, l AS (SELECT label, unnest(x) AS v, generate_subscripts(x, 1) AS pos FROM emb),
bx AS (SELECT label, pos, min(v) AS lo, max(v) AS hi FROM l GROUP BY label, pos), qq AS (SELECT qid, unnest(q) AS w, generate_subscripts(q, 1) AS pos FROM planes),
s AS (SELECT qid, label, list_sum(list(CASE WHEN w >= 0 THEN lo * w ELSE hi * w END ORDER BY bx.pos)) AS low, list_sum(list(CASE WHEN w >= 0 THEN hi * w ELSE lo * w END ORDER BY bx.pos)) AS high FROM bx JOIN qq ON bx.pos = qq.pos GROUP BY qid, label)
SELECT qid, label, round(CASE WHEN low > 0 THEN low WHEN high < 0 THEN -high ELSE 0 END, 8) AS bound FROM s""")
def box_bound_by_label(spark, d):
    """Axis-parallel boxes as zone maps."""
    long = points_of(spark, d, "emb_cluster").select("label", F.posexplode("x").alias("pos", "v")).groupBy("label", "pos").agg(F.min("v").alias("lo"), F.max("v").alias("hi"))
    ordered = lambda c: F.transform(F.array_sort(F.collect_list(F.struct("pos", c))), lambda s: s[c])
    boxes = long.groupBy("label").agg(ordered("lo").alias("lo"), ordered("hi").alias("hi"))
    met = boxes.crossJoin(F.broadcast(planes_for(spark, d, "emb_cluster")))
    return met.select("qid", "label", F.round(E.box_bound(F.col("lo"), F.col("hi"), F.col("q")), 8).alias("bound"))


@query(f"""WITH {GROUPS}, o AS (SELECT qid, qp.label, n, coalesce(sum(n) OVER (PARTITION BY qid ORDER BY abs(ip), qp.label ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM qp JOIN g ON qp.label = g.label)
SELECT qid, label, n, CAST(before AS BIGINT) AS before FROM o WHERE before < (SELECT ceil(count(*) * 0.3) FROM emb)""")
def budget_leaves(spark, d):
    """The groups that a budget of 30 % buys, nearest centre first."""
    groups, total = label_groups(spark, d), points_of(spark, d, "emb_cluster").agg(F.count("*").alias("total"))
    met = groups.crossJoin(F.broadcast(planes_for(spark, d, "emb_cluster"))).withColumn("ip", E.dot(F.col("center"), F.col("q"), 65))
    before = F.sum("n").over(W.partitionBy("qid").orderBy(F.abs("ip"), "label").rowsBetween(W.unboundedPreceding, -1))
    running = met.withColumn("before", F.coalesce(before, F.lit(0)))
    return running.crossJoin(F.broadcast(total)).filter(F.col("before") < F.ceil(F.col("total") * 0.3)).select("qid", "label", "n", "before")
