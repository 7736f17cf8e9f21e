"""Mixing sources to target weights by Pareto order sampling, in DataFrame operations only.

A source's target is its weight's share of all words, at most ``cap`` times its size; the excess is shared again by weight.
Every document is taken whole as often as its source's rate allows (the certain copies). The words that are still missing come
from a sample with unequal probabilities: a document's inclusion probability goes with the root of its size, capped at 1, and
the probabilities of a source are scaled so that its sample is expected to hold the missing words. Their sum is the planned
size of the sample. Documents at 1 are certain; the others are ranked by random odds over inclusion odds,
(u/(1-u)) / (p/(1-p)), and taken from the front; the last places are corrected to the words that are missing, so that the end
is as near to them as whole documents allow. u is a digest of the id, so reruns agree.

The scale comes from counts by (source, size), in which certain documents are those over one size. Ranks need no sort of a
source: sums by (source, slice of the ranking) find the one slice in which the sample ends, and only that slice, a few
thousand rows, is ranked. Documents themselves are never shuffled; sources' figures are sent to them.

Null texts have size 0 and are taken 0 words; a source without words has target 0; a null source is a source of its own; a
null id ranks by a fixed u. Repeated rows count as rows, each taken or not by itself; which of equal rows is taken at the last
place is open. Very long texts are documents like any other. Empty tables give empty results; other columns pass through
``mixed`` whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, cut, small, with_unit

SLICE_ROWS = 2_000


def words(text) -> F.Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def cyclic_weights(sources: DataFrame, cycle: int = 3) -> DataFrame:
    """sources with weight 1, 2, ..., cycle, 1, ... by code point, null last. One row for each source."""
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))
    return sources.withColumn("weight", ((place - 1) % cycle + 1).cast("long"))


def targets(sources: DataFrame, cap: int = 3) -> DataFrame:
    """sources (source, source_size, weight) with target: equal level of target over weight, each held at cap * source_size."""
    ratio = F.col("source_size") * cap / F.col("weight")
    order = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    before, every = order.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    t = sources.withColumn("ratio", ratio).withColumn("place", F.row_number().over(order))
    held = F.coalesce(F.sum(F.col("source_size") * cap).over(before), F.lit(0))
    spent = F.coalesce(F.sum("weight").over(before), F.lit(0))
    t = t.withColumn("level", (F.sum("source_size").over(every) - held) / (F.sum("weight").over(every) - spent))
    t = t.withColumn("free", F.min(F.when(F.col("level") <= F.col("ratio"), F.col("place"))).over(every))
    level = F.max(F.when(F.col("place") == F.col("free"), F.col("level"))).over(every)
    target = F.when(F.col("place") < F.col("free"), (F.col("source_size") * cap).cast("double")).otherwise(F.least(F.col("weight") * level, (F.col("source_size") * cap).cast("double")))
    return t.withColumn("target", target).select("source", "source_size", "weight", "target")


def rates(slim: DataFrame, cap: int = 3) -> DataFrame:
    """For each source of slim (source, size): source_size, target, whole (certain copies of every document), missing (words
    that the sample holds), most (largest size that isn't certain), scale (inclusion probability over ``draw``), sure (words
    of certain documents), planned (documents that the sample is planned to hold) and slices (of its ranking)."""
    counts = cut(slim.groupBy("source", "size").agg(F.count("*").alias("n")))
    sources = counts.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"), F.sum("n").alias("rows"))
    rated = targets(cyclic_weights(sources.select("source", "source_size")), cap)
    rate = F.coalesce(F.try_divide(F.col("target"), F.col("source_size")), F.lit(0.0))
    rated = rated.withColumn("whole", F.floor(rate)).withColumn("missing", (rate - F.floor(rate)) * F.col("source_size"))
    rated = cut(rated.join(sources.select(F.col("source").alias("s"), (F.col("rows") / SLICE_ROWS + 1).cast("long").alias("slices")), F.col("source").eqNullSafe(F.col("s"))).drop("s", "weight"))
    wanted = small(rated.select(F.col("source").alias("s"), "missing").filter("missing > 0"))
    sized = counts.filter("size > 0").join(wanted, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    # For each size the scale if just the larger ones were certain; it holds from the largest size on whose probability is in reach.
    larger = Window.partitionBy("source").orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, -1)
    upto = Window.partitionBy("source").orderBy("size").rowsBetween(Window.unboundedPreceding, 0)
    whole = lambda c: c.cast("decimal(38,0)")  # noqa: E731  # sums of products pass a long at scale
    sized = sized.withColumn("sure", F.coalesce(F.sum(whole(F.col("size") * F.col("n"))).over(larger), whole(F.lit(0))))
    sized = sized.withColumn("certain", F.coalesce(F.sum("n").over(larger), F.lit(0))).withColumn("drawn", F.sum(whole(draw("size") * F.col("n"))).over(upto))
    sized = sized.withColumn("mass", F.sum(whole(draw("size") * F.col("size")) * whole(F.col("n"))).over(upto))
    sized = sized.withColumn("scale", (F.col("missing") - F.col("sure").cast("double")) / F.col("mass").cast("double")).filter(F.col("scale") * draw("size") <= 1)
    first = sized.groupBy("source").agg(F.max_by(F.struct(F.col("size").alias("most"), "scale", F.col("sure").cast("double").alias("sure"), "certain", "drawn"), "size").alias("f"))
    first = first.select(F.col("source").alias("s"), "f.most", "f.scale", "f.sure", (F.col("f.certain") + F.round(F.col("f.scale") * F.col("f.drawn").cast("double")).cast("long")).alias("planned"))
    return rated.join(first, F.col("source").eqNullSafe(F.col("s")), "left").drop("s")


def draw(size) -> F.Column:
    """What inclusion probabilities go with: the root of the size, whole, so that sums are exact."""
    return F.ceil(F.sqrt(F.col(size).cast("double"))).cast("long")


def _ranked(rows: DataFrame, rated: DataFrame) -> DataFrame:
    """rows (i, source, size and others) with their source's figures, p, odds and the slice of the ranking."""
    rows = rows.join(rated, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    p = F.when((F.col("size") <= 0) | F.col("scale").isNull(), F.lit(0.0)).when((F.col("size") > F.col("most")) | (F.col("scale") * draw("size") >= 1), F.lit(1.0)).otherwise(F.col("scale") * draw("size"))
    u = with_unit(F.md5(F.coalesce(F.col("i").cast("string"), F.lit(""))))
    rows = rows.withColumn("p", p).withColumn("u", u)
    odds = F.when((F.col("p") > 0) & (F.col("p") < 1), (F.col("u") / (1 - F.col("u"))) / (F.col("p") / (1 - F.col("p"))))
    return rows.withColumn("odds", odds).withColumn("slice", F.floor(F.col("odds") / (1 + F.col("odds")) * F.col("slices"))).drop("u")


def _taken(slim: DataFrame, rows: DataFrame, cap: int) -> DataFrame:
    """rows (i, source, size and others) with source_size, target, p and copies. slim: the same rows, those three columns only."""
    rated = small(cut(rates(slim.select("source", "size"), cap)).withColumnRenamed("source", "s"))
    ranked = _ranked(slim, rated)
    sums = ranked.filter("p > 0").groupBy("source", F.coalesce("slice", F.lit(-1)).alias("slice"), "missing").agg(F.sum("size").alias("words"))  # slice -1: certain ones
    upto = Window.partitionBy("source").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    ends = sums.withColumn("ahead", F.coalesce(F.sum("words").over(upto), F.lit(0))).filter("slice >= 0 and ahead <= missing")
    last = ends.groupBy("source").agg(F.max("slice").alias("last"), F.max_by("ahead", "slice").alias("ahead"))
    marked = _ranked(rows, rated).join(small(cut(last).withColumnRenamed("source", "s")), F.col("source").eqNullSafe(F.col("s")), "left").drop("s")
    edge = F.coalesce(F.col("slice") == F.col("last"), F.lit(False))
    sure = marked.filter(~edge).withColumn("one", F.coalesce((F.col("p") == 1) | (F.col("slice") < F.col("last")), F.lit(False)).cast("long"))
    order = Window.partitionBy("source").orderBy("odds", "i", "size").rowsBetween(Window.unboundedPreceding, -1)
    near = marked.filter(edge).withColumn("one", (F.col("ahead") + F.coalesce(F.sum("size").over(order), F.lit(0)) + F.col("size") / 2 <= F.col("missing")).cast("long"))
    return sure.unionByName(near).withColumn("copies", F.col("whole") + F.col("one"))


def copies(docs: DataFrame, cap: int = 3) -> DataFrame:
    """(doc_id, source, size, source_size, target, p, copies) for each row of docs (doc_id, source, text). p: inclusion
    probability of the copy beside the certain ones."""
    slim = cut(docs.select(F.col("doc_id").alias("i"), "source", words("text").alias("size")))
    return _taken(slim, slim, cap).select(F.col("i").alias("doc_id"), "source", "size", "source_size", "target", "p", "copies")


def mixed(docs: DataFrame, cap: int = 3) -> DataFrame:
    """The rows of docs, each as often as the mix takes it."""
    names = [f"c{k}" for k in range(len(docs.columns))]
    at = {c: names[docs.columns.index(c)] for c in ("doc_id", "source", "text")}
    rows = docs.toDF(*names).withColumns({"i": F.col(at["doc_id"]), "source": F.col(at["source"]), "size": words(F.col(at["text"]))})
    taken = _taken(cut(rows.select("i", "source", "size")), rows, cap).filter("copies > 0")
    return taken.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select(*names).toDF(*docs.columns)
