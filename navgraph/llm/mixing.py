"""Mixing sources to target weights, without sorting the documents.

Every document has a place on a line of 128-bit hashes of its id. A source takes each of its documents `copies` whole
times and once more those below a threshold on that line. The threshold comes from nested histograms: words are summed by
source and hash bucket, the bucket where the budget runs out is opened into finer buckets, and only at the last level are
single hashes looked at. Documents are never ordered; the plan holds at most sources x BUCKETS rows per level.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from navgraph.llm.arrow import fresh, named
from navgraph.session import written

#: Rows of a table of sources that are sent to all tasks at most; a larger one is joined by shuffling.
SENT = 100_000

#: Hex digits of the hash per histogram level, and levels; the rest of the hash is the last level.
DIGITS, LEVELS = 3, 3
WEIGHTS = (3, 1, 2)


def words_in(text: Column) -> Column:
    """Number of `[^\\x20\\x09-\\x0D]+` in a text; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.5, most: float = 2.0) -> DataFrame:
    """Adds weight and target to one row per source with source, source_size. These rows, not documents, go through one task.

    Sources by code point (null last) weigh `weights`, repeating. They share `share` times all words in proportion; a
    target stops at `most` times its source's size and what it can't use goes to the others. Sharing anew until none is
    above gives each source min(level * weight, limit) with one common level, found here by running sums over limit / weight.
    """
    order = Window.orderBy(F.col("source").isNull(), "source")
    everything = Window.partitionBy()
    weighed = sizes.withColumn("n", F.row_number().over(order) - 1).withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (F.col("n") % len(weights) + 1).cast("int")))
    line = Window.orderBy("full", "n")
    run = (
        weighed.withColumn("limit", F.col("source_size") * F.lit(most))
        .withColumn("full", F.col("limit") / F.col("weight"))
        .withColumn("budget", F.sum("source_size").over(everything) * F.lit(share))
        .withColumn("used", F.coalesce(F.sum("limit").over(line.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("open", F.sum("weight").over(line.rowsBetween(Window.currentRow, Window.unboundedFollowing)))
        .withColumn("level", (F.col("budget") - F.col("used")) / F.col("open"))
    )
    # From the first source that isn't filled on, levels only fall; so that of the first one is the largest.
    level = F.max(F.when(F.col("level") <= F.col("full"), F.col("level"))).over(everything)
    return run.withColumn("common", level).select("source", "source_size", "weight", F.least(F.col("limit"), F.coalesce(F.col("common") * F.col("weight"), F.col("limit"))).alias("target"))


def sent(sources: DataFrame) -> DataFrame:
    """A written table of one row per source, marked for broadcasting if it is small."""
    return F.broadcast(sources) if sources.count() <= SENT else sources


def thresholds(sized: DataFrame, goals: DataFrame) -> DataFrame:
    """Per source: copies, and the hash `edge` with the share `part` of the words at it; below it all is taken once more.

    sized: source, size, place (hex digits). goals: source, source_size, target.
    """
    left = goals.select(
        F.col("source").alias("of"),
        "source_size",
        "target",
        F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long").alias("copies"),
    ).withColumn("left", F.col("target") - F.col("copies") * F.col("source_size")).withColumn("prefix", F.lit(""))
    left = written(left, "mix-level")
    for level in range(LEVELS + 1):
        digits = DIGITS * (level + 1) if level < LEVELS else 32
        here = F.substring("place", 1, digits)
        inside = sized.join(sent(left), F.col("source").eqNullSafe(F.col("of")) & F.col("place").startswith(F.col("prefix")), "inner")
        bucket = inside.groupBy("of", here.alias("bucket")).agg(F.sum("size").alias("words"), F.first("left").alias("left"))
        line = Window.partitionBy("of").orderBy("bucket")
        edge = (
            bucket.withColumn("before", F.coalesce(F.sum("words").over(line.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
            .filter((F.col("before") <= F.col("left")) & (F.col("left") < F.col("before") + F.col("words")))
            .select(F.col("of").alias("edge_of"), F.col("bucket"), F.col("words"), (F.col("left") - F.col("before")).alias("rest"))
        )
        left = left.join(edge, F.col("of").eqNullSafe(F.col("edge_of")), "left").select(
            "of", "source_size", "target", "copies",
            F.coalesce("rest", F.lit(0.0)).alias("left"),
            F.coalesce("bucket", F.lit("")).alias("prefix"),
            (F.coalesce("rest", F.lit(0.0)) / F.coalesce("words", F.lit(1))).alias("part"),
        )
        # One row per source from here on: cutting the plan keeps the levels from being run again by those that follow.
        left = written(left.coalesce(1), "mix-level")
    return left.select("of", "source_size", "target", "copies", F.col("prefix").alias("edge"), "part")


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.5, most: float = 2.0) -> DataFrame:
    """Adds size, source_size, target and taken (words the mix takes of each document, repeats counted) to `docs`.

    Needs doc_id, text and source; other columns stay, those of the four names are replaced. A source with no words takes
    none. Rows with one doc_id share a place on the line and so a fate; if the budget ends at that place, each gives the same
    share of its words (rounded down). A null doc_id counts as an id of its own. An empty table gives an empty result.
    At most `most` times a document's words are taken, and each source's total is short of its target by less than a word for
    every row at its edge.
    """
    own = [named(c) for c in docs.columns if c.lower() not in ("size", "source_size", "target", "taken")]
    at, of, copies, edge, part = fresh([*docs.columns, "size", "source_size", "target", "taken"], "place", "of", "copies", "edge", "part")
    place = F.md5(F.coalesce(named("doc_id").cast("string"), F.lit("null")))
    sized = written(docs.select(named("source").alias("source"), words_in(named("text")).alias("size"), place.alias("place")), "mix-sizes")
    goals = written(targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, most), "mix-targets")
    plan = thresholds(sized, goals)
    plan = sent(plan).select(F.col("of").alias(of), "source_size", "target", F.col("copies").alias(copies), F.col("edge").alias(edge), F.col("part").alias(part))
    once_more = F.when(F.col(edge) == "", F.lit(0)).when(F.col(at) < F.col(edge), F.col("size")).when(F.col(at) == F.col(edge), F.floor(F.col("size") * F.col(part) + F.lit(1e-9))).otherwise(F.lit(0))
    return (
        docs.select(*own, words_in(named("text")).alias("size"), place.alias(at))
        .join(plan, named("source").eqNullSafe(F.col(of)), "inner")
        .select(*own, "size", "source_size", "target", (F.col("size") * F.col(copies) + once_more).cast("long").alias("taken"))
    )


def op10_mixing_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    return mix(docs).select("doc_id", "size", "source_size", "target", "taken")


SQL = r"""
WITH RECURSIVE s AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size, md5(doc_id::VARCHAR) AS place FROM documents
), z AS (
  SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source IS NULL, source) - 1 AS n FROM s GROUP BY source
), w AS (
  SELECT *, [3, 1, 2][(n % 3 + 1)::INT] AS weight, source_size * 2.0::DOUBLE AS cap, (SELECT sum(source_size) * 1.5::DOUBLE FROM z) AS budget FROM z
), r AS (
  SELECT *, (budget - coalesce(sum(cap) OVER (ORDER BY cap / weight, n ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(weight) OVER (ORDER BY cap / weight, n ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS lvl FROM w
), g AS (
  SELECT source, source_size, least(cap, coalesce((SELECT max(lvl) FROM r WHERE lvl <= cap / weight) * weight, cap))::DOUBLE AS target FROM r
), c AS (
  SELECT s.doc_id, s.size, g.source_size, g.target, CASE WHEN g.source_size > 0 THEN floor(g.target / g.source_size) ELSE 0 END::BIGINT AS copies,
         sum(s.size) OVER (PARTITION BY s.source ORDER BY s.place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before
  FROM s JOIN g ON s.source IS NOT DISTINCT FROM g.source
)
SELECT doc_id, size, source_size, target,
       (size * copies + greatest(0, least(size, floor((target - copies * source_size) - coalesce(before, 0) + 1e-9))))::BIGINT AS taken
FROM c
"""
