"""Mixing sources to target weights by hash-threshold histograms.

Every document has a fixed pseudo-random key. A source that must give a share of its words takes exactly the documents whose key lies
below a threshold, so a larger budget always contains a smaller one. Thresholds come from histograms of words by source and key
prefix; only the bucket that a budget ends in is refined, and nothing is ever sorted.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import join_lookup, materialize, scratch, table

WEIGHTS = (3, 1, 2)
SHARE = 1.5
MAX_EPOCHS = 2
#: Key bits that each histogram splits by, and all key bits.
DIGIT_BITS, KEY_BITS = 14, 56

WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    """Number of maximal runs without blank characters (space, tab to carriage return); 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def mix_key(doc_id: Column) -> Column:
    """First 56 bits of MD5 of the id as text: equal in every engine and run; null ids share one key."""
    return F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), 1, KEY_BITS // 4), 16, 10).cast("long")


def targets(totals: DataFrame, weights: Sequence[int] = WEIGHTS, share: float = SHARE, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """(source, source_size, target) from one row per source. Sources are dealt the weights in code-point order, null last.

    Water-filling in closed form: in order of cap/weight, sources before the first one that stays below its cap keep their caps
    and the rest divide what is left by weight. Code-point order and the level are properties of all sources together, so the global
    windows run in one task, over one row of some 50 bytes a source: a million sources, far beyond any mix, are 50 MB there.
    """
    order = Window.orderBy(F.col("source").isNull(), F.col("source").cast("binary"))
    every = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    t = totals.withColumn("_i", F.row_number().over(order) - 1)
    t = t.withColumn("_w", F.element_at(F.array(*[F.lit(w) for w in weights]), (F.col("_i") % len(weights) + 1).cast("int")))
    t = t.withColumns({"_cap": F.col("source_size") * max_epochs, "_budget": F.sum("source_size").over(Window.partitionBy().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)) * F.lit(float(share))})
    first = Window.orderBy(F.col("_cap") / F.col("_w"), "_i").rowsBetween(Window.unboundedPreceding, -1)
    rest = Window.orderBy(F.col("_cap") / F.col("_w"), "_i").rowsBetween(0, Window.unboundedFollowing)
    t = t.withColumn("_level", (F.col("_budget") - F.coalesce(F.sum("_cap").over(first), F.lit(0))) / F.sum("_w").over(rest))
    t = t.withColumn("_level", F.max(F.when(F.col("_level") * F.col("_w") <= F.col("_cap"), F.col("_level"))).over(Window.partitionBy().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    full = F.col("_cap").cast("double")
    return t.select("source", "source_size", F.when(F.col("_level").isNull(), full).otherwise(F.least(full, F.col("_level") * F.col("_w"))).alias("target"))


def _key(c: str = "source") -> Column:
    """A join key that tells null from the empty name."""
    return F.struct(F.col(c).isNull().alias("n"), F.coalesce(F.col(c), F.lit("")).alias("s"))


def source_plan(d: DataFrame, weights: Sequence[int] = WEIGHTS, share: float = SHARE, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """One row per source of d (source, size, _h): _s (join key), source_size, target, _full, _threshold.

    A document of the source is taken _full times and once more if its key is below _threshold, which is all that a row's decision
    needs. Joined by source, so repeated ids, or ids that several sources hold, are decided row by row.
    """
    with scratch(d.sparkSession):
        goal = materialize(targets(d.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, max_epochs))
        full = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0))
        full = F.least(full, F.lit(max_epochs))
        # open: the key prefix in which the budget ends and the words still to be taken in it
        bound = goal.select(_key().alias("_s"), F.lit(0).cast("long").alias("_prefix"), (F.col("target") - full * F.col("source_size")).alias("_left"))
        rows = d.select(_key().alias("_s"), "_h", "size")
        for shift in range(KEY_BITS - DIGIT_BITS, -1, -DIGIT_BITS):
            inside = join_lookup(rows, bound, "_s", "inner").where(F.shiftright("_h", shift + DIGIT_BITS) == F.col("_prefix"))
            digit = F.shiftright("_h", shift).bitwiseAND((1 << DIGIT_BITS) - 1)
            hist = inside.groupBy("_s", digit.alias("_d")).agg(F.sum("size").alias("_n"))
            before = Window.partitionBy("_s").orderBy("_d").rowsBetween(Window.unboundedPreceding, Window.currentRow)
            ends = materialize(hist.withColumn("_cum", F.sum("_n").over(before)))
            # the first bucket that does not fit whole; past the last one when all fit
            cut = join_lookup(ends, bound, "_s", "inner").groupBy("_s", "_prefix", "_left").agg(
                F.min(F.when(F.col("_cum") > F.col("_left"), F.col("_d"))).alias("_cut"),
                F.coalesce(F.max(F.when(F.col("_cum") <= F.col("_left"), F.col("_cum"))), F.lit(0)).alias("_fits"),
                F.min(F.when(F.col("_cum") > F.col("_left"), F.col("_cum"))).alias("_over"))
            bound = materialize(cut.select(
                "_s", (F.shiftleft("_prefix", DIGIT_BITS) + F.coalesce("_cut", F.lit(1 << DIGIT_BITS))).alias("_prefix"),
                (F.col("_left") - F.col("_fits")).alias("_left"),
                (F.col("_over") - F.col("_fits")).alias("_last")))
            open_ = bound.where("_last is not null")
            closed = bound.where("_last is null").select("_s", F.shiftleft("_prefix", shift).alias("_threshold"))
            done = closed if shift == KEY_BITS - DIGIT_BITS else done.unionByName(closed)
            if shift == 0:  # the last bucket is one key: taken if that ends nearer to the budget
                nearer = F.col("_last") - F.col("_left") < F.col("_left")
                done = done.unionByName(open_.select("_s", (F.col("_prefix") + nearer.cast("long")).alias("_threshold")))
            bound = open_.select("_s", "_prefix", "_left")
        per = goal.withColumns({"_s": _key(), "_full": full.cast("long")}).drop("source").join(done, "_s", "left")
        return materialize(per.withColumn("_threshold", F.coalesce("_threshold", F.lit(0).cast("long"))), lasting=True)


def sized(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """doc_id, source, size, _h of every row, in a shared table, so that texts are read once."""
    return materialize(docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).cast("string").alias("source"), word_count(F.col(text_col)).alias("size"), mix_key(F.col(id_col)).alias("_h")))


def epochs_of(key: Column, full: Column, threshold: Column, max_epochs: int = MAX_EPOCHS) -> Column:
    return F.least(full + (key < threshold).cast("long"), F.lit(max_epochs).cast("long"))


def mix(docs: DataFrame, weights: Sequence[int] = WEIGHTS, share: float = SHARE, max_epochs: int = MAX_EPOCHS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """One row per document row: doc_id, size, source, source_size, target, epochs (times the mix repeats it), taken = size * epochs.

    A source takes all its documents floor(target / source_size) times and once more those whose key is below its threshold. The
    threshold is the largest key prefix whose words fit the remaining budget, or the next one if that ends nearer to it; documents
    with one key (repeated ids) are taken or left together. Null text has size 0, null source is a source of its own, empty
    tables give empty results, extra columns are ignored. Two documents never share a threshold decision by position, so reruns agree.
    """
    d = sized(docs, id_col, text_col, source_col)
    out = join_lookup(d.withColumn("_s", _key()), source_plan(d, weights, share, max_epochs), "_s", "left")
    epochs = epochs_of(F.col("_h"), F.col("_full"), F.col("_threshold"), max_epochs)
    return out.select("doc_id", "size", "source", "source_size", "target", epochs.alias("epochs"), (F.col("size") * epochs).alias("taken"))


#: Columns added to documents for a while; no table has such names.
PLAN, TIMES = "__flowlens_plan", "__flowlens_times"


def mixed_documents(docs: DataFrame, weights: Sequence[int] = WEIGHTS, share: float = SHARE, max_epochs: int = MAX_EPOCHS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The rows of docs, with all their columns, as often as the mix takes them; rows without words have nothing to take and stay once.

    Every row decides for itself from its key and its source's plan, so texts are neither shuffled nor joined by document.
    """
    with scratch(docs.sparkSession):
        per = source_plan(sized(docs, id_col, text_col, source_col), weights, share, max_epochs)
        plan = materialize(per.select(F.col("_s").alias(TIMES), F.struct("_full", "_threshold").alias(PLAN)), lasting=True)
    keyed = docs.withColumn(TIMES, F.struct(F.col(source_col).isNull().alias("n"), F.coalesce(F.col(source_col).cast("string"), F.lit("")).alias("s")))
    times = epochs_of(mix_key(F.col(id_col)), F.col(f"{PLAN}._full"), F.col(f"{PLAN}._threshold"), max_epochs)
    times = F.when(F.coalesce(F.col(text_col), F.lit("")).rlike(WORD), F.coalesce(times, F.lit(0))).otherwise(F.lit(1)).cast("int")
    copies = join_lookup(keyed, plan, TIMES, "left").withColumn(TIMES, F.explode(F.array_repeat(F.lit(1), times)))
    return copies.select(*docs.columns)


def op3_mix_hash_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


ORACLE = r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size,
    CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 14) AS BIGINT) AS h FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, [3, 1, 2][1 + (row_number() OVER (ORDER BY source IS NULL, encode(source)) - 1) % 3] AS wt,
    row_number() OVER (ORDER BY source IS NULL, encode(source)) AS i, sum(source_size) OVER () AS total FROM s),
l AS (SELECT *, (total * CAST(1.5 AS DOUBLE) - coalesce(sum(2 * source_size) OVER (ORDER BY 2.0 * source_size / wt, i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
    / sum(wt) OVER (ORDER BY 2.0 * source_size / wt, i ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS lev FROM w),
g AS (SELECT source, source_size, least(2.0 * source_size, coalesce(max(CASE WHEN lev * wt <= 2 * source_size THEN lev END) OVER () * wt, 2.0 * source_size)) AS target FROM l),
j AS (SELECT d.doc_id, d.size, d.h, g.source, g.source_size, g.target,
    CASE WHEN g.source_size > 0 THEN least(floor(g.target / g.source_size), 2) ELSE 0 END AS fulls FROM d JOIN g ON d.source IS NOT DISTINCT FROM g.source),
c AS (SELECT *, target - fulls * source_size AS budget, sum(size) OVER (PARTITION BY source ORDER BY h) AS cum,
    sum(size) OVER (PARTITION BY source, h) AS own FROM j),
k AS (SELECT *, cum <= budget OR (cum - own <= budget AND cum - budget < budget - (cum - own)) AS extra FROM c)
SELECT doc_id, CAST(size AS BIGINT) AS size, source_size, CAST(target AS DOUBLE) AS target,
    CAST(size * least(fulls + CAST(extra AS INT), 2) AS BIGINT) AS taken FROM k
"""
