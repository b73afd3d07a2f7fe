"""Mixing sources to target weights by Pareto order sampling, in DataFrame operations only.

Each source gets a target number of words. Within a source a document's expected number of copies follows its inclusion weight, the number
of binary digits of its word count (so longer texts, with more context, have better odds), up to ``most_copies``; one factor a source makes the
expected words meet the target. The whole part of that number is allocated for certain. The rest, p, is the inclusion probability of one more copy:
documents are ranked by their random odds u / (1 - u) over their inclusion odds p / (1 - p), and taken in rank
order while their words come nearest to what is left of the target. So the sample has a fixed size in words.

No source is ever gathered or sorted in one task. Ranks are read off counts: the rank axis is cut into cells, cells are
summed by partial aggregation, the cell where the target is reached is cut again, and only the documents of
one finest cell of a source are sorted together (a cell holds about one document in cells ** 2). Sources may be many: they are numbered
by ranges, and the common ratio of targets to weights is found by sums over all of them.

Defined cases: a null or empty text has size 0 and is never taken; a null source is a source of its own, last in
order; a null doc_id draws its random number by its text; of rows that agree in source, doc_id and text as many are taken as the target
asks for, whichever; an empty table gives an empty result; extra columns pass through ``mix`` untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import persisted

WEIGHTS = (5, 2, 1)
NOT_SPACE = r"[^\x20\x09-\x0D]+"
KEY = ("odds", "doc_id", "digest")


def size_of(text: Column) -> Column:
    """Number of runs of characters other than ASCII white space."""
    return F.coalesce(F.regexp_count(text, F.lit(NOT_SPACE)), F.lit(0)).cast("long")


def random_number(seed: int, digest: Column) -> Column:
    """Uniform in (0, 1), from 48 bits of an md5 of seed and doc_id (or text), so that reruns and SQL agree."""
    mark = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("text:"), digest))))
    return (F.conv(F.substring(mark, 1, 12), 16, 10).cast("long") + 0.5) / float(2**48)


def inclusion_weight(size: Column) -> Column:
    return F.length(F.bin(size))


def numbered(sizes: DataFrame) -> DataFrame:
    """sizes with the place of each source in code point order, null last; by ranges, so that no task sees all sources."""
    order = (F.col("source").isNull(), F.col("source"))
    ranged = persisted(sizes.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "mixing-sources")
    counted = ranged.groupBy("part").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row a range
    within = F.row_number().over(Window.partitionBy("part").orderBy(*order)) - 1
    return ranged.join(F.broadcast(counted.select("part", before.alias("before"))), "part").withColumn("place", F.col("before") + within).drop("part", "before")


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, percent: int = 150, most_copies: int = 2) -> DataFrame:
    """Source, size and target words. sizes: one row a source.

    Targets follow the weights, repeated over the sources in code point order; none passes most_copies times its
    source's size. The common ratio of target to weight starts at its value without caps; sources that it overfills are full, what
    they can't take raises it for the others, and so on until no other source is overfilled.
    """
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.col("place") % len(weights) + 1).cast("int")).cast("long")
    weighed = persisted(numbered(sizes).withColumn("weight", weight).drop("place"), "mixing-weights")
    cap = F.lit(most_copies) * F.col("source_size")
    ratio, state = 0.0, None
    while True:
        full = F.lit(ratio) * F.col("weight") > cap
        now = weighed.agg(F.sum("source_size"), F.sum(F.when(full, F.col("source_size"))), F.sum(F.when(~full, F.col("weight")))).first()
        if now == state or not now[2]:
            break
        state, ratio = now, (percent * now[0] - 100 * most_copies * (now[1] or 0)) / (100.0 * now[2])
    target = F.least(F.lit(ratio) * F.col("weight"), cap.cast("double")) if now[2] else cap.cast("double")
    return weighed.select("source", "source_size", target.alias("target"))


def expected_copies(strata: DataFrame, most_copies: int) -> DataFrame:
    """(source, source_size, target, wanted, rates) from rows (source, weight, words, source_size, target) of a source's inclusion weights:
    the expected copies by weight as a map, and the words that are left of the target after the whole copies.

    Copies are in proportion to the weight, up to most_copies; the heaviest weights are full first, and there are few of them a source.
    """
    most = F.lit(float(most_copies))
    by = Window.partitionBy("source").orderBy(F.desc("weight"))
    heavier = F.coalesce(F.sum("words").over(by.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    shared = F.sum(F.col("weight") * F.col("words")).over(Window.partitionBy("source").orderBy("weight").rowsBetween(Window.unboundedPreceding, 0))
    factor = (F.col("target") - most * heavier) / shared
    fitting = strata.withColumn("factor", factor).withColumn("factor", F.when(F.col("factor") * F.col("weight") <= most, F.col("factor")))
    first = F.max_by("factor", F.when(F.col("factor").isNotNull(), F.col("weight"))).over(Window.partitionBy("source"))
    rated = fitting.withColumn("rate", F.least(F.coalesce(first * F.col("weight"), most), most))
    whole = F.sum((F.floor("rate") * F.col("words")).cast("long"))
    rates = F.map_from_entries(F.collect_list(F.struct("weight", "rate")))
    return rated.groupBy("source", "source_size", "target").agg((F.col("target") - whole).alias("wanted"), rates.alias("rates"))


def placed(rows: DataFrame, plan: DataFrame, cells: int) -> DataFrame:
    """rows (with source, size, u) with the plan of their source, their expected copies, and their place on the axis of the ranking."""
    joined = extend(rows, plan)  # Spark broadcasts the plan while it measures it as small, else splits hot sources
    rate = F.when(F.col("size") > 0, F.try_element_at("rates", inclusion_weight(F.col("size"))))
    joined = joined.withColumn("rate", rate).withColumn("p", F.col("rate") - F.floor("rate"))
    odds = F.when(F.col("p") > 0, (F.col("u") / (1 - F.col("u"))) / (F.col("p") / (1 - F.col("p"))))
    axis = F.col("odds") / (1 + F.col("odds")) * cells
    ranked = joined.withColumn("odds", odds).withColumn("first", F.floor(axis).cast("int"))
    return ranked.withColumn("second", F.floor((axis - F.col("first")) * cells).cast("int"))


def cut(cells: DataFrame, cell: str, name: str) -> DataFrame:
    """By source: the first cell whose running words reach ``wanted``, and the words before it."""
    running = F.coalesce(F.sum("words").over(Window.partitionBy("source").orderBy(cell).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    reached = cells.withColumn("before", running).filter(F.col("before") + F.col("words") >= F.col("wanted"))
    return reached.groupBy("source").agg(F.min_by(F.struct(F.col(cell).alias("cell"), F.col("before").alias("before")), cell).alias(name))


def extend(rows: DataFrame, found: DataFrame) -> DataFrame:
    """rows with the columns of found, one row a source."""
    found = found.withColumnRenamed("source", "of")
    return rows.join(found, rows["source"].eqNullSafe(found["of"]), "left").drop("of")


def plan_mix(docs: DataFrame, seed: int = 42, cells: int = 256, most_copies: int = 2, **shares) -> DataFrame:
    """One row a source: its target, the expected copies by weight, and where its ranking is cut.

    ``last`` holds the key of the last document that gets an extra copy, ``ties`` how many rows have that key, and ``take`` how many of them get one.
    """
    digest = F.md5(F.coalesce("text", F.lit("")))
    sized = docs.select("source", "doc_id", size_of(F.col("text")).alias("size"), digest.alias("digest"), random_number(seed, digest).alias("u"))
    sized = persisted(sized.filter("size > 0"), "mixing-sizes")
    strata = persisted(sized.groupBy("source", inclusion_weight(F.col("size")).alias("weight")).agg(F.sum("size").alias("words")), "mixing-strata")
    goal = targets(strata.groupBy("source").agg(F.sum("words").alias("source_size")), most_copies=most_copies, **shares)
    plan = persisted(expected_copies(extend(strata, goal), most_copies), "mixing-plan")
    ranked = placed(sized, plan, cells).filter("p > 0 and wanted > 0")
    summed = ranked.groupBy("source", "first", "wanted").agg(F.sum("size").alias("words"))
    plan = persisted(extend(plan, cut(summed, "first", "top")), "mixing-plan")
    within = placed(sized, plan, cells).filter("wanted > 0 and first = top.cell")
    finer = within.groupBy("source", "second", "wanted", "top").agg(F.sum("size").alias("words"))
    plan = persisted(extend(plan, cut(finer.withColumn("wanted", F.col("wanted") - F.col("top.before")), "second", "low")), "mixing-plan")
    edge = placed(sized, plan, cells).filter("wanted > 0 and first = top.cell and second = low.cell")
    rank = Window.partitionBy("source").orderBy(*KEY).rowsBetween(Window.unboundedPreceding, 0)
    gap = F.col("wanted") - F.col("top.before") - F.col("low.before")
    summed_up = edge.withColumn("upto", F.sum("size").over(rank)).withColumn("gap", gap)
    nearest = F.col("upto") - F.col("gap") <= F.col("gap") - (F.col("upto") - F.col("size"))
    same = summed_up.groupBy("source", F.struct(*KEY).alias("last")).agg(F.count_if(nearest).alias("take"), F.count("*").alias("ties")).filter("take > 0")
    last = same.groupBy("source").agg(F.max(F.struct("last", "take", "ties")).alias("end")).select("source", "end.*")
    return persisted(extend(plan, last), "mixing-plan")


def copies(docs: DataFrame, seed: int = 42, cells: int = 256, **shares) -> DataFrame:
    """docs with size, source_size, target and the number of copies that the mix takes of each row."""
    plan = plan_mix(docs, seed, cells, **shares)
    names = [c for c in docs.columns if c not in ("size", "source_size", "target", "copies")]
    digest = F.md5(F.coalesce("text", F.lit("")))
    keyed = docs.select("source", "doc_id", size_of(F.col("text")).alias("size"), digest.alias("digest"), random_number(seed, digest).alias("u"), F.struct(*names).alias("_row"))
    ranked = placed(keyed, plan, cells)
    cell, edge, key = F.struct("first", "second"), F.struct(F.col("top.cell").alias("first"), F.col("low.cell").alias("second")), F.struct(*KEY)
    at_end = F.coalesce((cell == edge) & key.eqNullSafe(F.col("last")), F.lit(False))
    extra = F.when((F.col("p") > 0) & (F.col("wanted") > 0) & ((cell < edge) | (cell == edge) & (key <= F.col("last"))), 1).otherwise(0)
    split = F.col("take") < F.col("ties")
    if not plan.filter(split).isEmpty():  # of the rows at the end some are taken: only these rows are numbered
        number = F.row_number().over(Window.partitionBy("source").orderBy(F.lit(0)))
        ends = ranked.filter(at_end & split)
        ranked = ranked.filter(~(at_end & F.coalesce(split, F.lit(False)))).withColumn("extra", extra).unionByName(ends.withColumn("extra", F.when(number <= F.col("take"), 1).otherwise(0)))
    else:
        ranked = ranked.withColumn("extra", extra)
    number = F.coalesce(F.floor("rate") + F.col("extra"), F.lit(0)).cast("long")
    return ranked.select("_row.*", "size", F.coalesce("source_size", F.lit(0)).alias("source_size"), F.coalesce("target", F.lit(0.0)).alias("target"), number.alias("copies"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """The mixed corpus: the rows of docs, each as often as its copies."""
    chosen = copies(docs.select("source", "doc_id", "text", F.struct(*docs.columns).alias("_whole")), **options).filter("copies > 0")
    return chosen.select("_whole", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select("_whole.*")
