"""Mixing sources to target weights.

Tokens are summed per source, a repetition rate follows for each source, and every document is taken
floor(rate) times plus once more with the fraction as its chance, decided by a hash of its key.

The split of the whole among sources is a water level: a source gets ``level x weight`` words unless
that is above its ceiling (``max_repeat`` times its own words), and the level is such that all words
are used up. It is found by rounds of re-sharing on the per-source table, each a small aggregate, so
no source list is gathered anywhere.

Results for odd rows: a null or empty text has size 0 and is taken 0 words; a null source is a source of
its own, last in order; repeated rows are drawn as one (same key, same draw), rows without a key by their text; an empty table gives an
empty table. Only ``key``, ``text`` and ``source`` are read, so other columns can have any name.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from geoherald.llm.scratch import store, unused

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (5.0, 2.0, 1.0)


def n_words(text: Column) -> Column:
    """Runs without ASCII white space; 0 for null. Counted as the places where such a run starts."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def ranked_sources(docs: DataFrame, text: str, source: str) -> DataFrame:
    """Per source: its words and its place in code-point order (null last), from 0.

    The place comes from a range partitioning: rows are numbered inside their partition, and only one
    count per partition goes to the driver.
    """
    per = docs.groupBy(F.col(source).alias("source")).agg(F.sum(n_words(F.col(text))).alias("source_size"))
    order = [F.col("source").isNull(), F.col("source")]
    per = store(per.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id()), "sources")
    counts = {r["part"]: r["n"] for r in per.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect()}
    base, offsets = 0, []
    for part in sorted(counts):
        offsets.append((part, base))
        base += counts[part]
    local = F.row_number().over(Window.partitionBy("part").orderBy(*order)) - 1
    starts = docs.sparkSession.createDataFrame(offsets or [(-1, 0)], "part int, start long")
    return per.withColumn("local", local).join(F.broadcast(starts), "part").select("source", "source_size", (F.col("start") + F.col("local")).alias("place"))


def targets(sources: DataFrame, weights: tuple[float, ...], max_repeat: float) -> DataFrame:
    """Adds ``target``: the words a source should give.

    Every round takes the sources whose share is above their ceiling out of the sharing at that ceiling;
    a round needs two numbers from the table. There are as many rounds as distinct groups of ceilings
    passed, at most the number of sources.
    """
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("place") % len(weights) + 1).cast("int"))
    rows = sources.withColumn("weight", weight).withColumn("ceiling", F.col("source_size") * F.lit(float(max_repeat)))
    whole = rows.agg(F.sum("source_size")).first()[0] or 0
    level, fixed = 0.0, F.lit(False)
    while True:
        free = F.when(~fixed, F.col("weight"))
        held = rows.agg(F.sum(free).alias("w"), F.sum(F.when(fixed, F.col("ceiling"))).alias("c")).first()
        if not held["w"]:
            break
        following = (whole - (held["c"] or 0.0)) / held["w"]
        if level and following <= level * (1 + 1e-12):
            break
        level = following
        fixed = F.col("ceiling") < F.lit(level) * F.col("weight")
    return rows.withColumn("target", F.round(F.least("ceiling", F.lit(level) * F.col("weight")), 6)).select("source", "source_size", "target")


def mix_sources(
    docs: DataFrame,
    key: str = "doc_id",
    text: str = "text",
    source: str = "source",
    weights: tuple[float, ...] = WEIGHTS,
    max_repeat: float = 3.0,
    seed: int = 7,
) -> DataFrame:
    """Every row with ``size``, ``source_size``, ``target``, ``copies`` and ``taken`` added.

    The source table is broadcast while it has under 100,000 sources; beyond that it is joined by
    shuffling.
    """
    table = store(targets(ranked_sources(docs, text, source), weights, max_repeat), "targets")
    name = unused("__source", docs.columns)
    table = table.withColumnRenamed("source", name)
    if table.count() < 100_000:
        table = F.broadcast(table)
    added = {"size", "source_size", "target", "copies", "taken"}
    rows = docs.select(*[F.col(f"`{c}`") for c in docs.columns if c not in added])
    rows = rows.join(table, rows[source].eqNullSafe(table[name]), "left").drop(name)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    # 52 bits of a digest of seed and key, as a number in [0, 1); any engine with MD5 draws the same
    named = F.coalesce(F.col(key).cast("string"), F.concat(F.lit("~"), F.md5(F.coalesce(F.col(text), F.lit("")))))
    digest = F.md5(F.concat(F.lit(f"{seed}:"), named))
    draw = F.conv(F.substring(digest, 1, 13), 16, 10).cast("long").cast("double") / F.lit(float(1 << 52))
    copies = (F.floor(rate) + F.when(draw < rate - F.floor(rate), 1).otherwise(0)).cast("long")
    rows = rows.withColumn("size", n_words(F.col(text))).withColumn("copies", copies)
    return rows.withColumn("taken", F.col("size") * F.col("copies"))


def emit_copies(mixed: DataFrame) -> DataFrame:
    """One row for each copy that the mix takes, numbered from 1 in ``copy_no``."""
    return mixed.withColumn("copy_no", F.explode(F.when(F.col("copies") > 0, F.sequence(F.lit(1).cast("long"), F.col("copies")))))
