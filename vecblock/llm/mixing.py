"""Mixing sources to target weights with distributed prefix sums, in native columns only.

Every document gets a hash-random key.  Each source is cut into ranges of that
key, sizes are summed per range, and prefix sums over the few range totals give
every range its offset, so only one range (not one source) is ever sorted in
one task.  A source's target is water-filled: weights share the whole size, no
target exceeds ``cap`` times its source.  The target buys whole epochs of the
source and then the documents in key order up to the exact budget; the document
on the border gives the words that are left.

Defined results: a null text has size 0; a null source is a source of its own,
after all others; ties of the key are ordered by doc_id, size; rows with equal
doc_id are separate; an empty table gives no rows; other columns pass through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.llm.shared import Stored, free_name

WEIGHTS = (5, 2, 1)
CAP = 3
RANGE_ROWS = 2000
WORDS = r"[^\x20\x09-\x0D]+"


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """(source, source_size, n_docs, target): from (source, size) rows; one row per source.

    The water level L solves sum(min(w L, cap S)) = total.  Sources fill up in
    the order of cap S / w; of the levels at which the rest fits, L is the highest.
    """
    by = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_docs"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    turn = F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1
    by = by.withColumn("w", F.element_at(F.array(*[F.lit(float(x)) for x in weights]), turn))
    by = by.withColumn("full", (F.col("source_size") * cap).cast("double"))
    rank = Window.orderBy(F.col("full") / F.col("w"), F.col("source").asc_nulls_last())
    everything = Window.partitionBy(F.lit(0))
    by = by.withColumns({
        "total": F.sum("source_size").over(everything).cast("double"),
        "filled": F.coalesce(F.sum("full").over(rank.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)),
        "open": F.sum("w").over(rank.rowsBetween(Window.currentRow, Window.unboundedFollowing)),
    })
    by = by.withColumn("level", (F.col("total") - F.col("filled")) / F.col("open"))
    level = F.max(F.when(F.col("w") * F.col("level") <= F.col("full"), F.col("level"))).over(everything)
    return by.withColumn("lambda", level).select("source", "source_size", "n_docs", F.least("full", F.coalesce(F.col("w") * F.col("lambda"), F.col("full"))).alias("target"))


def _draw(seed: int, size):
    """A hash-random key of 60 bits."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("doc_id").cast("string"), size.cast("string"))), 1, 15), 16, 10).cast("long")


def _plan(docs: DataFrame, seed: int, weights: tuple[int, ...], cap: int) -> DataFrame:
    spark = docs.sparkSession
    sized = docs.select("doc_id", "source", size_of("text").alias("size"))
    sized = Stored(spark, sized.withColumn("draw", _draw(seed, F.col("size"))), "sizes")
    aim = Stored(spark, targets(sized.df, weights, cap), "targets")
    # each source gets as many ranges as its rows ask for; a range is known by its number
    rows = sized.df.join(aim.df.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s"))).drop("s")
    unit = F.col("draw").cast("double") / F.lit(2.0**60)
    ranges = F.ceil(F.col("n_docs") / RANGE_ROWS)
    rows = rows.withColumn("range", F.least(F.floor(unit * ranges), ranges - 1).cast("long"))
    per = rows.groupBy("source", "range").agg(F.sum("size").alias("k"))
    w = Window.partitionBy("source").orderBy("range")
    ahead = per.select(F.col("source").alias("s"), F.col("range").alias("r"), (F.sum("k").over(w) - F.col("k")).alias("ahead"))
    rows = rows.join(ahead, F.col("source").eqNullSafe(F.col("s")) & (F.col("range") == F.col("r"))).drop("s", "r")
    inside = Window.partitionBy("source", "range").orderBy("draw", "doc_id", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = rows.withColumn("start", F.col("ahead") + F.sum("size").over(inside) - F.col("size"))
    budget = F.floor(F.col("target") + F.lit(0.5))
    whole = F.greatest(F.col("source_size"), F.lit(1))
    rows = rows.withColumn("epochs", F.least(F.floor(budget / whole), F.lit(cap)))
    left = F.when(F.col("epochs") < cap, budget - F.col("epochs") * whole).otherwise(0)
    return rows.withColumn("part", F.greatest(F.lit(0), F.least(F.col("size"), left - F.col("start"))))


def size_of(text: str):
    """Words of a text; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORDS)), F.lit(0)).cast("long")


def mix(docs: DataFrame, seed: int = 17, weights: tuple[int, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """(doc_id, source, size, source_size, target, taken) for every row."""
    return _plan(docs, seed, weights, cap).select("doc_id", "source", "size", "source_size", "target", (F.col("epochs") * F.col("size") + F.col("part")).cast("long").alias("taken"))


def mixed_documents(docs: DataFrame, seed: int = 17, weights: tuple[int, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """The mix itself: ``docs``' columns, each row as often as it is drawn.

    Only each source's last key within its budget is needed, so no text is
    shuffled; the border document is taken whole, and with it rows of the same key.
    """
    cuts = _plan(docs, seed, weights, cap).groupBy("source").agg(F.max("epochs").alias("e"), F.max(F.when(F.col("part") > 0, F.col("draw"))).alias("last"))
    of, epochs, last, copies = (free_name(docs, f"cut_{x}") for x in ("source", "epochs", "last", "copies"))
    cuts = Stored(docs.sparkSession, cuts.select(F.col("source").alias(of), F.col("e").cast("int").alias(epochs), F.col("last").alias(last)), "cuts")
    rows = docs.join(cuts.df, F.col("source").eqNullSafe(F.col(of)))
    taken = F.col(epochs) + F.coalesce((_draw(seed, size_of("text")) <= F.col(last)).cast("int"), F.lit(0))
    rows = rows.withColumn(copies, taken).where(F.col(copies) > 0)
    return rows.withColumn(copies, F.explode(F.sequence(F.lit(1), F.col(copies)))).select(*[F.col(f"`{c}`") for c in docs.columns])
