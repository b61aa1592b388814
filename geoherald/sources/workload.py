"""Subscriptions over a stream of objects, their lifetimes, and the mix of all three kinds of tuples.

Three groups of subscriptions: Q1 draws keywords as they occur and small squares; Q2 has at least one
keyword outside the most frequent hundredth of terms and squares up to twice as wide; Q3 mixes the two
by region, a ten by ten lattice. ``all_rare`` keeps only keywords outside that hundredth.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from geoherald.functions import rarest
from geoherald.functions.expr import distinct
from geoherald.sources.shared import settle
from geoherald.sources.tables import read_table
from geoherald.sources.world import SMALL_SIDE, WIDE_SIDE, lexicon, object_source, ranked

# tasks need no path to the package
register_pickle_by_value(rarest)

#: Between the terms of a text that goes through an exchange.
BREAK = "\x1f"
#: Terms of a lexicon up to which tasks get it whole.
HELD_TERMS = 1_000_000
#: Objects whose texts go through an exchange at once when subscriptions are written.
TEXTS = 1_500_000
#: Multipliers whose sum of products imitates a bell curve.
LIFE = (48271, 69621, 16807, 39373, 40692, 40014, 62089, 63027, 30269, 30307, 30323, 26841)


def _region(x: Column, y: Column, side: int) -> tuple[Column, Column]:
    step = side // 10 + 1
    axis = lambda v: F.least(F.lit(9), F.floor(v / step)).cast("int")
    return axis(x), axis(y)


def _clauses(words: Column, op: Column) -> Column:
    """AND of all, OR of all, or (first two) OR third; one or two words are always joined by AND in the last form."""
    each = F.transform(words, lambda w: F.array(w))
    mixed = F.array(distinct(F.slice(words, 1, 2)), F.slice(words, 3, 1))
    whole = F.array(distinct(words))
    return F.when(op == 1, F.array_sort(F.array_distinct(each))).when((op == 2) & (F.size(words) >= 3), mixed).otherwise(whole)


def _with_rarest(texts: DataFrame, lex: DataFrame, v: int) -> DataFrame:
    """``kw, text, rare, rare_rk`` of ``kw, text, terms``: a text with the least frequent of its terms, of equal ones the smaller.
    A lexicon of up to ``HELD_TERMS`` is looked up where the text is; beyond, terms meet it by shuffling."""
    if v > HELD_TERMS:
        least = texts.select("kw", F.explode("terms").alias("term")).join(lex, "term").groupBy("kw").agg(F.min(F.struct("df", "term", "rk")).alias("rare"))
        return texts.drop("terms").join(least.select("kw", F.col("rare.term").alias("rare"), F.col("rare.rk").alias("rare_rk")), "kw")
    # at most HELD_TERMS rows
    first = lex.orderBy("df", "term").select("term", "rk").toArrow().combine_chunks()
    terms, ranks = (first[c].combine_chunks() for c in ("term", "rk"))
    held = texts.sparkSession.sparkContext.broadcast((terms, ranks.to_numpy()))
    return texts.mapInArrow(lambda batches: rarest.rarest(batches, *held.value), "kw long, text string, rare string, rare_rk long")


def subscriptions(spark: SparkSession, folder: str, group: str, world: str = "wide", all_rare: bool = False, flips: Column | None = None, objects: DataFrame | None = None, spare: tuple[str, ...] = ()) -> DataFrame:
    """``sub_id, owner, x0, x1, y0, y1, dnf`` of a group (``Q1``, ``Q2`` or ``Q3``), without an ``owner`` that is ``spare``.

    ``flips`` turns the style of a region of Q3: a column over ``q`` (the subscription's number) and ``g``
    (its region), odd for turned ones.
    """
    return next(subscription_parts(spark, folder, group, world, all_rare, flips, objects, spare))


def subscription_parts(spark: SparkSession, folder: str, group: str, world: str = "wide", all_rare: bool = False, flips: Column | None = None, objects: DataFrame | None = None, spare: tuple[str, ...] = (), texts_at_once: int | None = None) -> Iterator[DataFrame]:
    """The rows of :func:`subscriptions` in parts that have no text in common, for no more than ``texts_at_once``
    objects each; all in one part without it."""
    side = WIDE_SIDE if world == "wide" else SMALL_SIDE
    objects = objects if objects is not None else settle(object_source(spark, folder, world), "objects")
    count = objects.agg(F.count(F.lit(1))).first()[0]
    # ids of both worlds are 0, 1, 2, ... so an id is a position
    orders = read_table(spark, folder, "orders").select(F.col("o_orderkey").alias("q"), F.col("o_custkey").alias("owner")).drop(*spare)
    picks = orders.withColumns({"at": (F.col("q") * 48271) % max(count, 1), "kw": (F.col("q") * 16807 + 11) % max(count, 1)})
    pieces = -(-count // texts_at_once) if texts_at_once and count else 1
    centres = objects.select(F.col("obj_id").alias("at"), F.col("x").alias("cx"), F.col("y").alias("cy"))
    # a text goes through the exchange as one string
    texts = objects.filter(F.size("terms") > 0).select(F.col("obj_id").alias("kw"), F.array_join("terms", BREAK).alias("text"), "terms")
    lex, v = None, 0
    if group != "Q1":
        lex = settle(ranked(lexicon(objects)), "ranked")
        v = lex.agg(F.count(F.lit(1))).first()[0]
    for k in range(pieces):
        piece = (lambda rows, k=k: rows.filter(F.pmod("kw", F.lit(pieces)) == k)) if pieces > 1 else (lambda rows: rows)
        words = piece(texts).drop("terms") if lex is None else _with_rarest(piece(texts), lex, v)
        centred = piece(picks).join(centres, "at").drop("at")
        if pieces == 1:
            # written in between, so that the files of one join go before those of the next come
            centred = settle(centred, "centred")
        yield _drawn(centred.join(words, "kw"), group, side, all_rare, flips, lex, v, spare)


def _drawn(rows: DataFrame, group: str, side: int, all_rare: bool, flips: Column | None, lex: DataFrame | None, v: int, spare: tuple[str, ...]) -> DataFrame:
    """Subscriptions of picks with their centres and texts; ``lex`` has ``v`` terms with their ranks."""
    rows = rows.withColumn("kt", F.split("text", BREAK, -1)).drop("text")
    op = F.floor(F.col("q") / 3) % 3
    n = (1 + F.col("q") % 3).cast("int")
    start = (1 + F.col("q") % F.greatest(F.size("kt") - 2, F.lit(1))).cast("int")
    rows = rows.withColumn("k1", F.slice("kt", start, n))
    wide_style = {"Q1": F.lit(False), "Q2": F.lit(True)}.get(group)
    if wide_style is None:
        rx, ry = _region(F.col("cx"), F.col("cy"), side)
        rows = rows.withColumn("g", 10 * ry + rx)
        turned = flips if flips is not None else F.lit(0)
        wide_style = (rx + ry + turned) % 2 == 1
    rows = rows.withColumn("style2", wide_style)
    if group == "Q1":
        rows = rows.withColumn("words", F.col("k1"))
    else:
        common = lex.filter(F.col("rk") * 100 <= v).select("term", "rk")
        rows = rows.filter(~F.col("style2") | (F.col("rare_rk") * 100 > v))
        words2 = distinct(F.concat(F.array("rare"), F.slice("k1", 2, 2)))
        if all_rare:
            # keywords of the first hundredth go; a subscription has few keywords, so this is one narrow join
            kept = rows.filter("style2").select("q", F.explode(words2).alias("term")).join(common.select("term"), "term", "left_anti").groupBy("q").agg(F.array_sort(F.collect_set("term")).alias("kept"))
            rows = rows.join(kept, "q", "left").withColumn("words", F.when(F.col("style2"), F.coalesce("kept", F.array().cast("array<string>"))).otherwise(F.col("k1"))).filter(F.size("words") > 0)
        else:
            rows = rows.withColumn("words", F.when(F.col("style2"), words2).otherwise(F.col("k1")))
    half = F.floor((1000 + (F.col("q") * 69621) % F.when(F.col("style2"), 99001).otherwise(49001)) / 2).cast("long")
    return rows.select(
        F.col("q").alias("sub_id"), *(c for c in ("owner",) if c not in spare),
        (F.col("cx") - half).alias("x0"), (F.col("cx") + half).alias("x1"), (F.col("cy") - half).alias("y0"), (F.col("cy") + half).alias("y1"),
        _clauses(F.col("words"), op).alias("dnf"),
    )


def drift(interval: int, share_of_ten: int = 1) -> Column:
    """For Q3: each epoch of ``interval`` registrations, ``share_of_ten`` tenths of the regions turn."""
    epoch = F.floor(F.col("q") / interval)
    return F.floor((epoch * share_of_ten + (F.col("g") * 7) % 10) / 10).cast("int")


def lifetime(r: Column, mu: int) -> Column:
    """Registrations until a subscription is cancelled: about normal, mean ``mu``, deviation a fifth of it."""
    s = F.lit(0).cast("long")
    for i, m in enumerate(LIFE):
        s = s + ((r * m + i * 97 + 13) * (m % 9973 + 1)) % 10007
    return F.greatest(F.lit(1), F.floor(mu * F.greatest(s - 10001, F.lit(0)) / 50035)).cast("long")


def timed(subs: DataFrame, objects: DataFrame, mu: int) -> tuple[DataFrame, DataFrame]:
    """Subscriptions with ``reg_seq`` and ``cancel_seq``, and objects with ``seq``: of ten objects one
    registration and one cancellation, ``mu`` subscriptions standing at the start.

    Numbers of objects and subscriptions are their places in the order of their ids.
    """
    number = ranked_ids(subs, "sub_id", "r")
    at = lambda n: F.when(n < mu, n - mu)
    last = objects.agg(F.count(F.lit(1))).first()[0]
    end = 12 * ((last - 1) // 10) + (last - 1) % 10
    gone = F.col("r") + lifetime(F.col("r"), mu)
    rows = number.withColumn("reg_seq", at(F.col("r")).cast("long")).withColumn("reg_seq", F.coalesce("reg_seq", (F.col("r") - mu) * 12 + 10))
    rows = rows.withColumn("cancel_seq", F.when(gone < mu, gone - mu).otherwise((gone - mu) * 12 + 11)).filter(F.col("reg_seq") < end).drop("r")
    timed_objects = ranked_ids(objects, "obj_id", "i").withColumn("seq", F.floor(F.col("i") / 10).cast("long") * 12 + F.col("i") % 10).drop("i")
    return rows, timed_objects


def ranked_ids(df: DataFrame, key: str, name: str) -> DataFrame:
    """Adds the place of a row in the order of a unique id, from 0, without one task for all rows."""
    ids = df.select(key)
    parted = settle(ids.repartitionByRange(F.col(key)).withColumn("part", F.spark_partition_id()), "ids")
    sizes = parted.groupBy("part").agg(F.count(F.lit(1)).alias("size"))
    starts = sizes.select("part", F.sum("size").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)).alias("start"))
    local = F.row_number().over(Window.partitionBy("part").orderBy(key)) - 1
    places = parted.withColumn("local", local).join(F.broadcast(starts), "part").select(key, (F.coalesce("start", F.lit(0)) + F.col("local")).cast("long").alias(name))
    return df.join(places, key)


def tuple_mix(subs: DataFrame, objects: DataFrame) -> DataFrame:
    """One stream ``seq, op, obj_id, sub_id`` of objects, registrations and cancellations."""
    none = F.lit(None).cast("long")
    last = objects.agg(F.max("seq")).first()[0]
    stream = objects.select("seq", F.lit("obj").alias("op"), "obj_id", none.alias("sub_id"))
    stream = stream.union(subs.select(F.col("reg_seq"), F.lit("reg"), none, "sub_id"))
    return stream.union(subs.filter(F.col("cancel_seq") <= last).select(F.col("cancel_seq"), F.lit("cancel"), none, "sub_id"))
