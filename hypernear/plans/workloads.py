"""Queries: applications of plane search, reports on their results, and time joins."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import exprs as E
from ..functions import sql as sqlfns
from ..operators import brute
from ..operators.metrics import percentiles
from ..operators.vectors import dedup
from ..sources import planes, tables
from .registry import DOC64, EMB, LI4, dot, norm, planes_for, points_of, query, sql_planes_box, sql_planes_rows

MEANS = "ml AS (SELECT label, unnest(CAST(embedding AS DOUBLE[])) AS v, generate_subscripts(embedding, 1) AS pos FROM embeddings), mm AS (SELECT label, pos, round(avg(v), 9) AS v FROM ml GROUP BY label, pos), means AS (SELECT label, list(v ORDER BY pos) AS mean FROM mm GROUP BY label)"
BISECTORS = f"""{MEANS},
bp AS (SELECT (10 * a.label + b.label)::BIGINT AS qid, list_transform(list_zip(a.mean, b.mean), lambda z: z[1] - z[2]) AS w, list_transform(list_zip(a.mean, b.mean), lambda z: (z[1] + z[2]) / 2) AS h FROM means a JOIN means b ON a.label < b.label),
braw AS (SELECT qid, list_append(w, -{dot('w', 'h')}) AS r FROM bp),
planes AS (SELECT qid, list_transform(r, lambda v: v / {norm('r[1:64]')}) AS q FROM braw)"""
MARGINS = f"m AS (SELECT qid, id, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN planes)"


# --- applications ---


@query(f"WITH {BISECTORS} SELECT qid, q[65] AS off, q[1] AS first FROM planes")
def label_bisectors(spark, d):
    """Planes half-way between each two label means."""
    return planes.bisectors(spark, d).select("qid", F.get("q", F.lit(64)).alias("off"), F.get("q", F.lit(0)).alias("first"))


@query(f"WITH {BISECTORS}, {EMB}, {MARGINS} SELECT qid, arg_min(id, (margin, id)) AS id, min(margin) AS margin FROM m GROUP BY qid")
def active_pick(spark, d):
    """Active learning: of each decision plane, the point to ask a label for."""
    return brute.nearest(points_of(spark, d, "emb").select("id", "x"), planes.bisectors(spark, d), 65)


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def unlabeled_anti(spark, d):
    return tables.table(spark, d, "documents").join(tables.table(spark, d, "labels"), "doc_id", "left_anti").select("doc_id")


def label_plane(spark, d, column: str):
    """H3: the plane half-way between the mean term shares of labelled documents with 1 and with 0."""
    met = tables.doc_tf(spark, d, 64).join(tables.table(spark, d, "labels").select(F.col("doc_id").alias("id"), column), "id")
    mean = met.select(column, F.posexplode("x").alias("i", "v")).groupBy("i").agg(F.round(F.avg(F.when(F.col(column) == 1, F.col("v"))), 9).alias("one"), F.round(F.avg(F.when(F.col(column) == 0, F.col("v"))), 9).alias("zero"))
    w, h = F.col("one") - F.col("zero"), (F.col("one") + F.col("zero")) / 2
    rows = mean.filter("i < 64").agg(F.array_sort(F.collect_list(F.struct("i", w.alias("w"), h.alias("h")))).alias("a"))
    normal, half = F.transform("a", lambda s: s["w"]), F.transform("a", lambda s: s["h"])
    return planes.finished(rows.select(F.lit(0).cast("long").alias("qid"), F.concat(normal, F.array(-E.dot(normal, half))).alias("q")))


def sql_label_requests(column: str) -> str:
    return f"""WITH {DOC64}, met AS (SELECT x, {column} AS y FROM emb JOIN labels ON doc_id = id),
long AS (SELECT y, unnest(x) AS v, generate_subscripts(x, 1) AS i FROM met),
mm AS (SELECT i, round(avg(v) FILTER (y = 1), 9) AS one, round(avg(v) FILTER (y = 0), 9) AS zero FROM long WHERE i <= 64 GROUP BY i),
ll AS (SELECT list(one - zero ORDER BY i) AS w, list((one + zero) / 2 ORDER BY i) AS h FROM mm),
qq AS (SELECT list_append(w, -{dot('w', 'h')}) AS r FROM ll),
planes AS (SELECT 0::BIGINT AS qid, list_transform(r, lambda v: v / {norm('r[1:64]')}) AS q FROM qq),
m AS (SELECT qid, id, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN planes WHERE id NOT IN (SELECT doc_id FROM labels)),
r AS (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY margin, id) AS rank, id, margin FROM m)
SELECT qid, rank, id, round(margin, 9) AS margin FROM r WHERE rank <= 20"""


def label_requests(spark, d, column: str):
    pool = tables.doc_tf(spark, d, 64).join(unlabeled_anti(spark, d).withColumnRenamed("doc_id", "id"), "id", "left_semi")
    return brute.topk(pool, label_plane(spark, d, column), 20, 65).withColumn("margin", F.round("margin", 9))


@query(sql_label_requests("quality"))
def document_label_requests(spark, d):
    """Active learning on documents: unlabelled ones nearest to the quality plane."""
    return label_requests(spark, d, "quality")


@query(sql_label_requests("toxic"))
def document_toxic_requests(spark, d):
    """The same for the plane between toxic documents and others."""
    return label_requests(spark, d, "toxic")


def active_learning(spark, d, rounds: int = 4, ask: int = 20, first: int = 10):
    """W9: rounds of asking for labels. A round puts the plane half-way between the mean vectors of the documents labelled so far, and asks
    for the labels of the unlabelled ones nearest to it. (round, asked, accuracy): how the plane divides all labelled documents."""
    from ..sources.storage import persisted

    marks = tables.table(spark, d, "labels").filter("quality is not null").groupBy(F.col("doc_id").alias("id")).agg(F.max("quality").alias("y"))
    pool = persisted(tables.doc_tf(spark, d, 64).select("id", "x").join(marks, "id"), "learning-pool")
    by = W.partitionBy("y").orderBy(F.xxhash64("id", F.lit(3)), "id")
    known = persisted(pool.withColumn("n", F.row_number().over(by)).filter(F.col("n") <= first).select("id"), "learning-known")
    rows = []
    for number in range(rounds):
        mean = pool.join(known, "id").select("y", F.posexplode("x").alias("i", "v")).filter("i < 64").groupBy("i").agg(F.avg(F.when(F.col("y") == 1, F.col("v"))).alias("one"), F.avg(F.when(F.col("y") == 0, F.col("v"))).alias("zero"))
        parts = mean.agg(F.array_sort(F.collect_list(F.struct("i", (F.col("one") - F.col("zero")).alias("w"), ((F.col("one") + F.col("zero")) / 2).alias("h")))).alias("a"))
        w, h = F.transform("a", lambda s: s["w"]), F.transform("a", lambda s: s["h"])
        plane = persisted(planes.finished(parts.select(F.lit(0).cast("long").alias("qid"), F.concat(w, F.array(-E.dot(w, h))).alias("q"))), "learning-plane")
        side = pool.crossJoin(F.broadcast(plane)).select("y", (E.dot(F.col("x"), F.col("q"), 65) > 0).cast("int").alias("side"))
        right = side.agg(F.avg((F.col("side") == F.col("y")).cast("double"))).first()[0]
        rows.append((number, known.count(), right))
        picked = brute.topk(pool.select("id", "x").join(known, "id", "left_anti"), plane, ask, 65).select("id")
        known = persisted(known.unionByName(picked), "learning-known")
    return spark.createDataFrame(rows, "round int, asked long, accuracy double")


@query("SELECT i::INT AS round, (20 + 20 * i)::BIGINT AS asked FROM range(0, 4) t(i)")
def active_learning_loop(spark, d):
    """Each round of the loop asks for as many new labels as it should, none twice."""
    return active_learning(spark, d).filter("accuracy between 0 and 1").select("round", "asked")


@query(f"WITH {EMB}, {sql_planes_rows('emb', 100, 64)}, {MARGINS}, l AS (SELECT qid, min(margin) AS least FROM m GROUP BY qid) SELECT arg_max(qid, (least, -qid)) AS qid, max(least) AS margin FROM l")
def max_margin_plane(spark, d):
    """The candidate plane whose nearest point is farthest."""
    least = brute.nearest(points_of(spark, d, "emb").select("id", "x"), planes_for(spark, d, "emb"), 65)
    best = least.agg(F.max_by(F.struct("qid", "margin"), F.struct("margin", -F.col("qid"))).alias("b"))
    return best.select("b.qid", "b.margin")


@query("WITH " + LI4 + ", a AS (SELECT i, min(abs(x[i + 1] - 0.37)) AS margin FROM emb CROSS JOIN range(0, 4) t(i) GROUP BY i) SELECT i AS dim, margin, rank() OVER (ORDER BY margin DESC, i) AS place FROM a")
def dimension_margin(spark, d):
    """Dimensions by the margin of their axis plane."""
    near = brute.nearest(points_of(spark, d, "li4").select("id", "x"), planes.axes(spark, 4, 0.37), 5)
    return near.select(F.col("qid").alias("dim"), "margin", F.rank().over(W.orderBy(F.desc("margin"), "qid")).cast("long").alias("place"))  # one row a dimension


def line_topk(spark, d, n: int = 100, k: int = 10):
    points = points_of(spark, d, "li4")
    return points, brute.topk_arrow(points.select("id", "x"), planes_for(spark, d, "li4", n), k)


LINE_TOP = f"{LI4}, {sql_planes_box(100, 4)}, {MARGINS}, top AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY margin, id) AS rank FROM m) WHERE rank <= 10)"


@query(f"WITH {LINE_TOP} SELECT r_name, n_name, count(*) AS hits, round(avg(margin), 9) AS mean_margin FROM top JOIN emb ON emb.id = top.id JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ALL")
def nearest_star(spark, d):
    """Where the orders of the nearest lines come from."""
    points, top = line_topk(spark, d)
    hit = F.broadcast(points.select("id", "l_orderkey").join(F.broadcast(top), "id"))  # ten rows a plane, so that no table is shuffled for them
    star = hit.join(tables.table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(tables.table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(tables.table(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(tables.table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return star.groupBy("r_name", "n_name").agg(F.count("*").alias("hits"), F.round(F.avg("margin"), 9).alias("mean_margin"))


PLANE0 = f"{LI4}, {sql_planes_box(1, 4)}, lm AS (SELECT l_returnflag, l_linestatus, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN planes)"


def line_margins(spark, d):
    return brute.all_margins(points_of(spark, d, "li4"), planes_for(spark, d, "li4", 1), 5)


@query(f"WITH {PLANE0} SELECT l_returnflag, l_linestatus, count(*) AS n, round(avg(margin), 9) AS mean_margin FROM lm GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def margin_rollup(spark, d):
    return line_margins(spark, d).rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.avg("margin"), 9).alias("mean_margin"))


@query(f"WITH {PLANE0} SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag, l_linestatus) AS BIGINT) AS level, min(margin) AS least FROM lm GROUP BY CUBE (l_returnflag, l_linestatus)")
def margin_cube(spark, d):
    return line_margins(spark, d).cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("level"), F.min("margin").alias("least"))


@query(f"WITH {PLANE0} SELECT quantile_cont(margin, 0.1) AS q10, quantile_cont(margin, 0.5) AS q50, quantile_cont(margin, 0.9) AS q90 FROM lm")
def margin_quantiles(spark, d):
    return spark.createDataFrame([tuple(percentiles(line_margins(spark, d), "margin", (0.1, 0.5, 0.9)))], "q10 double, q50 double, q90 double")


@query(f"WITH {PLANE0} SELECT CAST(least(floor(margin / 0.05), 19) AS BIGINT) + 1 AS bucket, count(*) AS n FROM lm GROUP BY 1")
def margin_hist(spark, d):
    margin = F.col("margin")
    return line_margins(spark, d).groupBy(F.least(F.floor(margin / 0.05) + 1, F.lit(20)).alias("bucket")).agg(F.count("*").alias("n"))


@query()
def margin_sketch(spark, d):
    """Approximate quantiles from mergeable sketches, to seed thresholds at scale."""
    sketch = line_margins(spark, d).agg(F.kll_sketch_agg_double("margin").alias("s"))
    return sketch.select(F.kll_sketch_get_quantile_double("s", F.lit(0.1)).alias("q10"), F.kll_sketch_get_quantile_double("s", F.lit(0.5)).alias("q50"))


@query("SELECT true AS low, true AS middle")
def margin_sketch_close(spark, d):
    """Sketched quantiles lie between the exact ones two hundredths to either side."""
    p8, p12, p48, p52 = map(F.lit, percentiles(line_margins(spark, d), "margin", (0.08, 0.12, 0.48, 0.52)))
    return margin_sketch(spark, d).select(F.col("q10").between(p8, p12).alias("low"), F.col("q50").between(p48, p52).alias("middle"))


@query("SELECT true AS close")
def distinct_estimate_close(spark, d):
    """The estimate of different documents is within a seventh of their number."""
    met = distinct_estimate(spark, d).crossJoin(F.broadcast(distinct_documents(spark, d).select(F.col("n").alias("exact"))))  # one row each
    return met.select((F.abs(F.col("n") - F.col("exact")) <= F.col("exact") / 7).alias("close"))


@query(f"WITH {DOC64} SELECT count(DISTINCT x) AS n FROM emb")
def distinct_documents(spark, d):
    """Different document vectors: copies fall together."""
    return dedup(tables.doc_tf(spark, d, 64)).agg(F.count("*").alias("n"))


@query()
def distinct_estimate(spark, d):
    return tables.doc_tf(spark, d, 64).agg(F.approx_count_distinct(F.xxhash64("x")).alias("n"))


# --- windows and sets ---


EMB_TOP = f"{EMB}, {sql_planes_rows('emb', 100, 64)}, {MARGINS}"


def emb_margins(spark, d, n: int = 100):
    return brute.all_margins(points_of(spark, d, "emb").select("id", "x"), planes_for(spark, d, "emb", n), 65)


@query(f"WITH {EMB_TOP}, c AS (SELECT qid, id, round(margin, 2) AS coarse FROM m), r AS (SELECT qid, id, coarse, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM c WINDOW w AS (PARTITION BY qid ORDER BY coarse, id), v AS (PARTITION BY qid ORDER BY coarse)) SELECT * FROM r WHERE rn <= 25")
def topk_rank(spark, d):
    """Ties in coarse margins under three kinds of rank."""
    coarse = emb_margins(spark, d).select("qid", "id", F.round("margin", 2).alias("coarse"))
    by, tied = W.partitionBy("qid").orderBy("coarse", "id"), W.partitionBy("qid").orderBy("coarse")
    ranks = coarse.withColumn("rn", F.row_number().over(by).cast("long")).withColumn("rk", F.rank().over(tied).cast("long")).withColumn("dr", F.dense_rank().over(tied).cast("long"))
    return ranks.filter("rn <= 25")


@query(f"WITH {EMB_TOP}, r AS (SELECT qid, id, margin, row_number() OVER w AS rank, margin - lag(margin) OVER w AS gap, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 9) AS share, round(cume_dist() OVER w, 9) AS upto FROM m WINDOW w AS (PARTITION BY qid ORDER BY margin, id)) SELECT qid, rank, gap, quarter, share, upto FROM r")
def margin_gaps(spark, d):
    by = W.partitionBy("qid").orderBy("margin", "id")
    return emb_margins(spark, d).select("qid", F.row_number().over(by).cast("long").alias("rank"), (F.col("margin") - F.lag("margin").over(by)).alias("gap"), F.ntile(4).over(by).cast("long").alias("quarter"), F.round(F.percent_rank().over(by), 9).alias("share"), F.round(F.cume_dist().over(by), 9).alias("upto"))


def two_methods(spark, d):
    points, some = points_of(spark, d, "emb"), planes_for(spark, d, "emb")
    whole = brute.topk(points.select("id", "x"), some, 20, 65).select("qid", "id")
    half = brute.topk(points.filter("label < 5").select("id", "x"), some, 20, 65).select("qid", "id")
    return whole, half


TWO = f"{EMB_TOP}, t AS (SELECT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY margin, id) AS r FROM m) WHERE r <= 20), f AS (SELECT qid, id FROM (SELECT m.*, row_number() OVER (PARTITION BY qid ORDER BY margin, m.id) AS r FROM m JOIN emb ON emb.id = m.id WHERE label < 5) WHERE r <= 20)"


@query(f"WITH {TWO} SELECT * FROM t INTERSECT SELECT * FROM f")
def method_intersect(spark, d):
    whole, half = two_methods(spark, d)
    return whole.intersect(half)


@query(f"WITH {TWO} SELECT * FROM t EXCEPT ALL SELECT * FROM f")
def method_except(spark, d):
    whole, half = two_methods(spark, d)
    return whole.exceptAll(half)


@query(f"WITH {TWO} SELECT coalesce(t.qid, f.qid) AS qid, count(t.id) AS whole, count(f.id) AS half, count(*) AS either FROM t FULL JOIN f ON t.qid = f.qid AND t.id = f.id GROUP BY 1")
def method_outer(spark, d):
    whole, half = two_methods(spark, d)
    joined = whole.withColumn("w", F.lit(1)).join(half.withColumn("h", F.lit(1)), ["qid", "id"], "full")
    return joined.groupBy("qid").agg(F.count("w").alias("whole"), F.count("h").alias("half"), F.count("*").alias("either"))


@query(f"WITH {EMB}, {sql_planes_rows('emb', 100, 64)} SELECT qid, id, abs({dot('x', 'q')}) AS margin, greatest(abs({dot('x', 'q')}) - q_norm * 0.01, 0) AS bound FROM emb CROSS JOIN planes")
def sql_margin(spark, d):
    """The SQL functions, inlined into a SQL query."""
    sqlfns.register(spark)
    points_of(spark, d, "emb").createOrReplaceTempView("hn_points")
    planes_for(spark, d, "emb").createOrReplaceTempView("hn_planes")
    return spark.sql("SELECT qid, id, hn_absdot(x, q) AS margin, hn_node_bound(hn_absdot(x, q), q_norm, 0.01D) AS bound FROM hn_points CROSS JOIN hn_planes")


@query(f"WITH {EMB}, {sql_planes_rows('emb', 100, 64)} SELECT qid, id, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN planes")
def batch_udf_margins(spark, d):
    """Margins by a vectorised Python function, which adds in the order of the components."""
    pairs = points_of(spark, d, "emb").select("id", "x").crossJoin(F.broadcast(planes_for(spark, d, "emb").select("qid", "q")))
    return pairs.select("qid", "id", sqlfns.absdot_batch("x", "q").alias("margin"))


@query(f"WITH {EMB}, c AS (SELECT label, unnest(x) AS v, generate_subscripts(x, 1) AS pos FROM emb), mc AS (SELECT label, pos, round(avg(v), 9) AS v FROM c GROUP BY ALL), cc AS (SELECT label, list(v ORDER BY pos) AS center FROM mc GROUP BY label), g AS (SELECT e.label, sqrt(list_sum(list_transform(list_zip(x, center), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS far FROM emb e JOIN cc ON cc.label = e.label) SELECT label, round(max(far), 9) AS radius FROM g GROUP BY label")
def radius_by_udaf(spark, d):
    """The radius of each label's ball, as a Python aggregate."""
    points = points_of(spark, d, "emb")
    parts = points.select("label", F.posexplode("x").alias("pos", "v")).groupBy("label", "pos").agg(F.round(F.avg("v"), 9).alias("v"))
    centers = parts.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "v"))), lambda s: s["v"]).alias("center"))
    met = points.join(F.broadcast(centers), "label")  # ten labels
    return met.groupBy("label").agg(F.round(sqlfns.vec_radius("x", "center"), 9).alias("radius"))


@query(f"WITH {EMB}, {sql_planes_rows('emb', 3, 64)}, {MARGINS}, r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY margin, id) AS rank FROM m WHERE qid = 2) SELECT id, margin FROM r WHERE rank <= 5")
def udtf_topk(spark, d):
    """Top-k as a Python table function over one partition of points."""
    sqlfns.register(spark)
    points_of(spark, d, "emb").select("id", "x").createOrReplaceTempView("hn_points")
    q = planes_for(spark, d, "emb", 3).filter("qid = 2").first().q
    values = ", ".join(f"{v!r}D" for v in q)
    return spark.sql(f"SELECT id, margin FROM hn_topk(TABLE(SELECT id, x FROM hn_points) WITH SINGLE PARTITION, array({values}), 5)")


# --- time ---


SCORE = "abs(value / 100.0::DOUBLE - 0.5)"


def events(spark, d):
    """Events with their margin from the plane value = 50."""
    return tables.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp_ntz")).withColumn("margin", F.abs(F.col("value") / 100.0 - 0.5))


@query(f"SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n, min({SCORE}) AS least FROM events GROUP BY ALL")
def tumbling_margin(spark, d):
    per = events(spark, d).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"), F.min("margin").alias("least"))
    return per.select(F.col("w.start").alias("day"), "event_type", "n", "least")


@query(f"WITH w AS (SELECT date_trunc('hour', ts) - to_hours(CAST((date_part('hour', ts) % 12) AS INT)) - to_hours(CAST(12 * k AS INT)) AS start, {SCORE} AS margin FROM events CROSS JOIN range(0, 2) t(k)) SELECT start, count(*) AS n, min(margin) AS least FROM w GROUP BY start")
def sliding_margin(spark, d):
    """Windows of a day that start every twelve hours."""
    per = events(spark, d).groupBy(F.window("ts", "1 day", "12 hours").alias("w")).agg(F.count("*").alias("n"), F.min("margin").alias("least"))
    return per.select(F.col("w.start").alias("start"), "n", "least")


@query(f"""WITH o AS (SELECT user_id, ts, {SCORE} AS margin, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR > ts THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o) SELECT user_id, min(ts) AS start, count(*) AS n, min(margin) AS least FROM s GROUP BY user_id, k""")
def session_margin(spark, d):
    """Sessions of a user end after six quiet hours."""
    per = events(spark, d).groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n"), F.min("margin").alias("least"))
    return per.select("user_id", F.col("w.start").alias("start"), "n", "least")


@query("""WITH p AS (SELECT user_id, ts, value AS off FROM events WHERE event_type = 'login'), e AS (SELECT event_id, user_id, ts, value FROM events WHERE event_type = 'purchase'),
j AS (SELECT e.event_id, e.value, (SELECT arg_max(p.off, (p.ts, p.off)) FROM p WHERE p.user_id = e.user_id AND p.ts <= e.ts) AS off FROM e) SELECT event_id, off, abs(value - off) AS margin FROM j""")
def asof_plane(spark, d):
    """Each purchase against the plane in force: the value of the user's last login at or before it."""
    kept = events(spark, d).filter(F.col("event_type").isin("login", "purchase"))
    is_plane = F.col("event_type") == "login"
    upto = W.partitionBy("user_id").orderBy("ts").rangeBetween(W.unboundedPreceding, W.currentRow)
    latest = kept.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("plane", F.max(F.when(is_plane, F.struct("ts", F.col("value").alias("off")))).over(upto))
    return latest.filter(~is_plane).select("event_id", F.col("plane.off").alias("off"), F.abs(F.col("value") - F.col("plane.off")).alias("margin"))


@query("SELECT a.event_id AS alert, count(b.event_id) AS around FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.event_id <> a.event_id AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'error' GROUP BY a.event_id")
def interval_events(spark, d):
    """Events within an hour of each error of the user: hours are keys, so the join is an equi-join on user and hour."""
    stamped = events(spark, d).withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = 3_600_000_000
    a = stamped.filter("event_type = 'error'").select(F.col("event_id").alias("alert"), F.col("user_id").alias("u"), F.col("s").alias("at"), F.explode(F.array(*[F.floor(F.col("s") / hour) + k for k in (-1, 0, 1)])).alias("slot"))
    b = stamped.select("event_id", "user_id", "s", F.floor(F.col("s") / hour).alias("hour"))
    met = a.join(b, (F.col("u") == F.col("user_id")) & (F.col("slot") == F.col("hour")) & (F.abs(F.col("s") - F.col("at")) <= hour) & (F.col("event_id") != F.col("alert")), "left")
    return met.groupBy("alert").agg(F.count("event_id").alias("around"))


@query("SELECT user_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY ALL")
def json_features(spark, d):
    return events(spark, d).groupBy("user_id", F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))

