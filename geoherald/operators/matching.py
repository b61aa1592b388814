"""Workers: posting lists by cell and term, lazy deletion, matching; and the merger.

Postings and probes meet on (worker, cell, term). A probe carries its place and a signature of its terms, never
the terms. Of short texts the signature has a 64-bit code for each term; where no two words share a code, a pair
is settled where posting and probe meet, under the first clause that it satisfies: no pair goes through an
exchange, and none comes twice. Many such objects do not even meet the postings by term: they go to the workers that
they are routed to once, as the postings of a subscription do, and the terms are looked at there (:func:`match_routed`). For longer texts the signature is 64 bits in all: rectangle and signature leave
few pairs, and these meet the terms, by the object's id, for the exact test of the expression.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark import Broadcast
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geoherald.functions.expr import alive, can_match, code, codes, first_match, matches, signature
from geoherald.functions.geometry import Grid, inside
from geoherald.operators import cellmatch
from geoherald.operators.assignment import Assignment, whole_world
from geoherald.operators.routing import live_map, object_terms, route_subs, routing_terms, send_all, send_waiting, subs_at_cells, term_freq
from geoherald.sources.shared import settle

# tasks need no path to the package
register_pickle_by_value(cellmatch)

POSTING = ["worker", "cell", "term", "sub_id", "dnf", "x0", "x1", "y0", "y1"]
SALTS = 16
#: Terms of an object up to which their codes go with its probes.
CARRIED = 16
#: Objects over which they meet subscriptions by cell, once each, and not by cell and term, once for each term.
GATHERED = 5000
#: A cell with over one part in so many of all the work is cut into pieces, ``SALTS`` at most.
SHARES = 50
#: Objects times subscriptions, cell by cell, up to which tasks are put together by the size of their blocks.
LIGHT = 100_000_000
#: Terms whose codes all tasks have; any other code goes with its block.
WORDS = 1_000_000
#: Subscriptions that the nested loop takes, which broadcasts them and looks at every pair.
NESTED_SUBS = 200_000


def build_index(routed_subs: DataFrame) -> DataFrame:
    """Postings: one row per worker, cell, term and subscription."""
    more = [c for c in ("clauses", "reg_seq", "cancel_seq") if c in routed_subs.columns]
    return routed_subs.select(*POSTING, *more)


def insert(index: DataFrame, routed_subs: DataFrame) -> DataFrame:
    return index.unionByName(build_index(routed_subs), allowMissingColumns=True)


def cancel(tombstones: DataFrame | None, cancelled: DataFrame) -> DataFrame:
    """Lazy deletion: ids are put down, postings stay where they are."""
    ids = cancelled.select("sub_id")
    return ids if tombstones is None else tombstones.union(ids).distinct()


def cancel_eager(index: DataFrame, cancelled: DataFrame) -> DataFrame:
    """The posting lists without the cancelled ones, rewritten at once."""
    return index.join(cancelled.select("sub_id").distinct(), "sub_id", "left_anti")


def purge(index: DataFrame, tombstones: DataFrame, touched: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Lists that were gone through (``cell, term``) lose their cancelled entries; a tombstone goes when no
    list holds its subscription any more."""
    dead = index.join(tombstones, "sub_id", "left_semi").join(touched.select("cell", "term").distinct(), ["cell", "term"], "left_semi")
    left = index.join(dead.select("worker", "cell", "term", "sub_id"), ["worker", "cell", "term", "sub_id"], "left_anti")
    return left, tombstones.join(left.select("sub_id").distinct(), "sub_id", "left_semi")


def _within() -> Column:
    return inside(F.col("x"), F.col("y"), F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1"))


def _fits() -> Column:
    return _within() & matches(F.col("terms"), F.col("dnf"))


def _masked(entries: DataFrame) -> DataFrame:
    return entries.withColumn("masks", F.transform("dnf", signature))


def _verified(pairs: DataFrame, objects: DataFrame) -> DataFrame:
    """Of pairs that rectangle and signature leave, with ``obj_id`` and ``dnf``, those whose terms satisfy the expression."""
    texts = objects.select("obj_id", "terms")
    return pairs.join(texts, "obj_id").filter(matches(F.col("terms"), F.col("dnf"))).drop("terms", "dnf")


def candidates(objects: DataFrame, routed_objects: DataFrame, index: DataFrame, grid: Grid) -> DataFrame:
    """The checks that workers make: every entry of the lists that an object goes through. Terms stay behind."""
    seq = [c for c in ("seq",) if c in objects.columns]
    placed = objects.select("obj_id", "x", "y", *seq, "terms").join(routed_objects.select("obj_id", "worker", "cell"), "obj_id")
    probes = placed.select("obj_id", "x", "y", *seq, "worker", "cell", signature(F.col("terms")).alias("bits"), F.explode(F.array_distinct("terms")).alias("term"))
    return probes.join(_masked(index), ["worker", "cell", "term"])


def match(objects: DataFrame, routed_objects: DataFrame, index: DataFrame, grid: Grid, tombstones: DataFrame | None = None) -> DataFrame:
    """``sub_id, obj_id, worker``: what each worker finds, with its own repeats."""
    found = candidates(objects, routed_objects, index, grid).filter(_within() & can_match(F.col("bits"), F.col("masks")))
    if "reg_seq" in index.columns and "seq" in objects.columns:
        found = found.filter(alive(F.col("reg_seq"), F.col("cancel_seq"), F.col("seq")))
    found = _verified(found.select("sub_id", "obj_id", "worker", "dnf"), objects).select("sub_id", "obj_id", "worker")
    return found if tombstones is None else found.join(tombstones, "sub_id", "left_anti")


def told_apart(objects: DataFrame, subs: DataFrame) -> bool:
    """Whether codes decide matches: all texts are short, and no two words of objects and subscriptions share a code."""
    longest = objects.agg(F.max(F.size("terms"))).first()[0]
    if longest is not None and longest > CARRIED:
        return False
    words = objects.select(F.explode("terms").alias("term")).distinct().union(subs.select(F.explode(F.flatten("dnf")).alias("term")).distinct()).distinct()
    return words.groupBy(code(F.col("term")).alias("code")).agg(F.count(F.lit(1)).alias("n")).filter("n > 1").isEmpty()


def _keyed(entries: DataFrame) -> DataFrame:
    return entries.withColumn("keys", F.transform("dnf", codes)).drop("dnf")


def _settled() -> Column:
    """Whether a pair matches, under a posting of the first clause that it satisfies."""
    return _within() & F.array_contains("clauses", first_match(F.col("codes"), F.col("keys")).cast("int"))


def match_once(objects: DataFrame, routed_objects: DataFrame | Assignment, index: DataFrame, grid: Grid, tombstones: DataFrame | None = None) -> DataFrame:
    """``sub_id, obj_id, worker``: what workers find, each pair once, for objects and subscriptions that are
    :func:`told_apart`. Objects, with
    their columns or without, go where they are routed, or by an assignment straight to the worker of each term."""
    seq = [c for c in ("seq",) if c in objects.columns]
    rows = objects.select("obj_id", "x", "y", *seq, codes(F.col("terms")).alias("codes"), "terms")
    if isinstance(routed_objects, Assignment):
        probes = routed_objects.place(object_terms(rows, grid).drop("terms"))
    elif "terms" in routed_objects.columns:
        rows = routed_objects.select("obj_id", "x", "y", *seq, codes(F.col("terms")).alias("codes"), "terms", "worker", "cell")
        probes = rows.withColumn("term", F.explode(F.array_distinct("terms"))).drop("terms")
    else:
        probes = rows.join(routed_objects.select("obj_id", "worker", "cell"), "obj_id").withColumn("term", F.explode(F.array_distinct("terms"))).drop("terms")
    found = probes.join(_keyed(index), ["worker", "cell", "term"]).filter(_settled())
    if "reg_seq" in index.columns and seq:
        found = found.filter(alive(F.col("reg_seq"), F.col("cancel_seq"), F.col("seq")))
    found = found.select("sub_id", "obj_id", "worker")
    return found if tombstones is None else found.join(tombstones, "sub_id", "left_anti")


def many(objects: DataFrame) -> bool:
    """Whether there are objects enough for :func:`match_by_cell`."""
    return objects.limit(GATHERED + 1).count() > GATHERED


def cuts(objects: DataFrame, subs: DataFrame, grid: Grid) -> tuple[tuple[np.ndarray, np.ndarray, np.ndarray], int]:
    """Tiles of cells, by their first cell, with over a ``SHARES``-th of the work, which is objects times subscriptions of
    each cell, in how many pieces each is cut, and whether the objects are dealt out to the pieces or, where they are fewer, the subscriptions; and
    the whole work."""
    seen = objects.groupBy(grid.cell(F.col("x"), F.col("y")).alias("cell")).agg(F.count(F.lit(1)).alias("n"))
    held = subs.select(F.explode(grid.overlapped(F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1"))).alias("cell")).groupBy("cell").agg(F.count(F.lit(1)).alias("m"))
    work: dict[int, tuple[int, int, int]] = {}
    # at most one row per cell of the grid
    for r in seen.join(held, "cell").collect():
        tile = (r.cell // grid.n // cellmatch.TILE * grid.n + r.cell % grid.n // cellmatch.TILE) * cellmatch.TILE
        n, m, pairs = work.get(tile, (0, 0, 0))
        work[tile] = n + r.n, m + r.m, pairs + r.n * r.m
    whole = sum(pairs for _, _, pairs in work.values())
    rows = sorted((tile, min(SALTS, -(-pairs * SHARES // whole)), n >= m) for tile, (n, m, pairs) in work.items() if pairs * SHARES > whole)
    return (np.array([r[0] for r in rows], dtype=np.int64), np.array([r[1] for r in rows], dtype=np.int64), np.array([r[2] for r in rows], dtype=bool)), whole


def word_table(freq: DataFrame) -> np.ndarray:
    """Codes of the ``WORDS`` most frequent terms, the most frequent and, of equal ones, the larger term first."""
    rows = freq.select(code(F.col("term")).alias("code"), "df", "term").orderBy(F.desc("df"), F.desc("term")).limit(WORDS).select("code").toArrow()
    return rows["code"].to_numpy()


FIRST, LAST = -(1 << 63), (1 << 63) - 1


def _long(value: int) -> Column:
    return F.lit(value).cast("long")


def _met(held: DataFrame, seen: DataFrame, pack: Callable, words: Broadcast, whole: int, grid: Grid) -> DataFrame:
    """Blocks of subscriptions and objects, put together by ``pack``, to pairs."""
    side, across = grid.n, grid.cell_side
    blocks = lambda rows, kind: rows.mapInArrow(lambda batches: pack(batches, kind), "cell int, salt int, kind int, block binary")
    both = blocks(held, 0).union(blocks(seen, 1))
    # blocks are small for the work that they make, so that by their size they would be put together to too few tasks
    n = int(held.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = both.repartition(n, "cell", "salt") if whole > LIGHT else both.repartition("cell", "salt")
    together = dealt.sortWithinPartitions("cell", "salt", "kind")
    return together.mapInArrow(lambda batches: cellmatch.by_cell(batches, words.value, side, across), "sub_id long, obj_id long")


def match_by_cell(objects: DataFrame, subs: DataFrame, freq: DataFrame, grid: Grid, assignment: Assignment | None = None) -> DataFrame:
    """``sub_id, obj_id``, as :func:`match_once`, for many objects: what goes through the exchange are blocks of objects, or
    of subscriptions, of a tile of cells (:func:`geoherald.operators.cellmatch.packed`), each row once for its tile and not for
    each term. Cells and terms are told apart behind it. With an assignment they go to its workers, see :func:`match_routed`."""
    if assignment is not None:
        index = build_index(route_subs(subs, assignment, freq))
        return match_routed(objects, subs, send_all(objects, assignment), index, freq, grid, assignment.places())
    timed = "seq" in objects.columns and "reg_seq" in subs.columns
    cut, whole = cuts(objects, subs, grid)
    words = objects.sparkSession.sparkContext.broadcast(word_table(freq))
    at = lambda c, name: grid.axis(F.col(c)).alias(name)
    seen = _seen(objects, timed, at("x", "cx0"), at("x", "cx1"), at("y", "cy0"), at("y", "cy1"))
    held = _held(subs, timed, at("x0", "cx0"), at("x1", "cx1"), at("y0", "cy0"), at("y1", "cy1"))
    side = grid.n
    return _met(held, seen, lambda batches, kind: cellmatch.packed(batches, kind, side, words.value, cut), words, whole, grid)


def _seen(objects: DataFrame, timed: bool, *more: Column | str) -> DataFrame:
    return objects.filter("x is not null and y is not null").select(
        F.col("obj_id").alias("id"), F.col("x").alias("x0"), F.col("x").alias("x1"), F.col("y").alias("y0"), F.col("y").alias("y1"), *more,
        (F.col("seq") if timed else _long(0)).alias("since"), _long(LAST).alias("until"), F.array(F.coalesce(codes(F.array_distinct("terms")), F.array().cast("array<long>"))).alias("keys"),
    )


def _held(subs: DataFrame, timed: bool, *more: Column | str) -> DataFrame:
    return subs.filter("x0 <= x1 and y0 <= y1 and dnf is not null").select(
        F.col("sub_id").alias("id"), "x0", "x1", "y0", "y1", *more,
        (F.col("reg_seq") if timed else _long(FIRST)).alias("since"), (F.coalesce("cancel_seq", _long(LAST)) if timed else _long(LAST)).alias("until"), F.transform("dnf", codes).alias("keys"),
    )


def match_routed(objects: DataFrame, subs: DataFrame, sent: DataFrame, index: DataFrame, freq: DataFrame, grid: Grid, places: np.ndarray | None = None) -> DataFrame:
    """``sub_id, obj_id``, as :func:`match_once`, for many objects: those that are ``sent`` (with ``worker, cell``) and the postings
    of ``index`` go to their workers in blocks (:func:`geoherald.operators.cellmatch.placed`). A pair is found at a worker that has
    a posting of it and that its object was sent to, and nowhere else. ``places`` are those of cells that workers share by
    text (:meth:`Assignment.places`): such workers' rows go to one place together, once."""
    timed = "seq" in sent.columns and "reg_seq" in index.columns
    cut, whole = cuts(objects, subs, grid)
    words = objects.sparkSession.sparkContext.broadcast(word_table(freq))
    held = _held(index, timed, "cell", "worker", code(F.col("term")).alias("term"), "clauses")
    side = grid.n
    return _met(held, _seen(sent, timed, "cell", "worker"), lambda batches, kind: cellmatch.placed(batches, kind, side, words.value, cut, places), words, whole, grid)


def matched(objects: DataFrame, subs: DataFrame, routed_objects: DataFrame, index: DataFrame, grid: Grid, tombstones: DataFrame | None = None, freq: DataFrame | None = None) -> DataFrame:
    """``sub_id, obj_id``, each once; by :func:`match_once` where it can be, and by :func:`match_routed` for many objects,
    which are best routed with their columns (:func:`geoherald.operators.routing.send_waiting`)."""
    if "clauses" not in index.columns or not told_apart(objects, subs):
        return merge(match(objects, routed_objects, index, grid, tombstones))
    if not many(objects):
        return match_once(objects, routed_objects, index, grid, tombstones).select("sub_id", "obj_id")
    sent = routed_objects if "terms" in routed_objects.columns else objects.join(routed_objects.select("obj_id", "worker", "cell"), "obj_id")
    index = index if tombstones is None else index.join(tombstones, "sub_id", "left_anti")
    return match_routed(objects, subs, sent, index, term_freq(objects) if freq is None else freq, grid)


def merge(pairs: DataFrame, subs: DataFrame | None = None) -> DataFrame:
    """The merger: each pair once, whichever workers and terms found it, with its owner if known."""
    once = pairs.select("sub_id", "obj_id").distinct()
    return once if subs is None else once.join(subs.select("sub_id", "owner"), "sub_id").select("owner", "sub_id", "obj_id")


def match_nested_loop(objects: DataFrame, subs: DataFrame) -> DataFrame:
    """Every object against every subscription, as the answer to compare with; refused over ``NESTED_SUBS``."""
    if subs.limit(NESTED_SUBS + 1).count() > NESTED_SUBS:
        raise ValueError(f"over {NESTED_SUBS} subscriptions: use run or match_fast")
    small = F.broadcast(subs.select("sub_id", "dnf", "x0", "x1", "y0", "y1"))
    return objects.join(small, _fits()).select("sub_id", "obj_id")


def match_single(objects: DataFrame, subs: DataFrame, grid: Grid) -> DataFrame:
    """One worker with the same index and no partitioning."""
    return run(objects, subs, whole_world(grid, 1))["matches"]


def match_fast(objects: DataFrame, subs: DataFrame, grid: Grid, salts: int = SALTS) -> DataFrame:
    """Dispatch and matching in one join on (cell, term), without workers: for raw speed. The postings are
    written once, as they are counted before they are joined.

    Long posting lists are cut into ``salts`` pieces, and the probes of their (cell, term) repeated for
    each piece, so that a hot place is many tasks' work. Which lists are long is counted first; each
    has over a ten-thousandth of all entries, so there are fewer than 10,000 to broadcast. Many objects
    of short texts meet the subscriptions by cell, and hot cells are cut, see :func:`match_by_cell`.
    """
    freq = settle(term_freq(objects), "freq")
    once = told_apart(objects, subs)
    if once and many(objects):
        return match_by_cell(objects, subs, freq, grid)
    postings = settle(subs_at_cells(subs, freq, grid).select("cell", "term", "sub_id", "dnf", "x0", "x1", "y0", "y1", "clauses"), "postings")
    whole = postings.count()
    long = postings.groupBy("cell", "term").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") * 10_000 > max(whole, 10_000)).select("cell", "term", F.lit(salts).alias("pieces"))
    pieces = F.coalesce("pieces", F.lit(1))
    entries = (_keyed(postings) if once else _masked(postings)).join(F.broadcast(long), ["cell", "term"], "left").withColumn("salt", F.pmod(F.xxhash64("sub_id"), pieces.cast("long")).cast("int")).drop("pieces")
    bits = codes(F.col("terms")).alias("codes") if once else signature(F.col("terms")).alias("bits")
    probes = object_terms(objects.select("obj_id", "x", "y", "terms", bits), grid).drop("terms")
    probes = probes.join(F.broadcast(long), ["cell", "term"], "left")
    probes = probes.withColumn("salt", F.explode(F.sequence(F.lit(0), pieces - 1))).drop("pieces")
    pairs = probes.join(entries, ["cell", "term", "salt"])
    if once:
        return pairs.filter(_settled()).select("sub_id", "obj_id")
    pairs = pairs.filter(_within() & can_match(F.col("bits"), F.col("masks")))
    return _verified(pairs.select("sub_id", "obj_id", "dnf"), objects).select("sub_id", "obj_id").distinct()


def match_inverted_only(objects: DataFrame, subs: DataFrame) -> DataFrame:
    """An index of terms without a grid."""
    postings = subs.join(routing_terms(subs, term_freq(objects)), "sub_id").select("term", "sub_id", "dnf", "x0", "x1", "y0", "y1")
    probes = objects.select("obj_id", "x", "y", signature(F.col("terms")).alias("bits"), F.explode(F.array_distinct("terms")).alias("term"))
    pairs = probes.join(_masked(postings), "term").filter(_within() & can_match(F.col("bits"), F.col("masks")))
    return _verified(pairs.select("sub_id", "obj_id", "dnf"), objects).select("sub_id", "obj_id").distinct()


def match_grid_only(objects: DataFrame, subs: DataFrame, grid: Grid) -> DataFrame:
    """A grid of subscriptions without terms."""
    cells = subs.select("sub_id", "dnf", "x0", "x1", "y0", "y1", F.explode(grid.overlapped(F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1"))).alias("cell"))
    probes = objects.select("obj_id", "x", "y", "terms", grid.cell(F.col("x"), F.col("y")).alias("cell"))
    return probes.join(cells, "cell").filter(_fits()).select("sub_id", "obj_id").distinct()


def run(objects: DataFrame, subs: DataFrame, assignment: Assignment, freq: DataFrame | None = None, drop_unmatched: bool = True) -> dict[str, DataFrame]:
    """Dispatch, matching and merging under an assignment: ``matches`` and the tables in between."""
    freq = freq if freq is not None else term_freq(objects)
    routed_subs = route_subs(subs, assignment, freq)
    tables = {"routed_subs": routed_subs, "live": live_map(routed_subs), "index": build_index(routed_subs)}
    return Run(objects, subs, assignment, freq, drop_unmatched, tables)


class Run(dict):
    """Tables of a run. ``sent``, the objects at their workers, and its ``routed_objects``, ``pairs``, with each worker's repeats,
    and ``matches`` are planned when they are asked for; all of them are made of what was routed."""

    def __init__(self, objects: DataFrame, subs: DataFrame, assignment: Assignment, freq: DataFrame, drop_unmatched: bool, tables: dict[str, DataFrame]):
        super().__init__(tables)
        self.objects, self.subs, self.assignment, self.freq, self.drop_unmatched = objects, subs, assignment, freq, drop_unmatched

    def __missing__(self, name: str) -> DataFrame:
        grid = self.assignment.grid
        if name == "sent":
            self[name] = send_waiting(self.objects, self["live"], grid) if self.drop_unmatched else send_all(self.objects, self.assignment)
        elif name == "routed_objects":
            self[name] = self["sent"].select("obj_id", "worker", "cell")
        elif name == "pairs":
            self[name] = match(self.objects, self["routed_objects"], self["index"], grid)
        elif name == "matches":
            if not told_apart(self.objects, self.subs):
                self[name] = merge(self["pairs"])
            elif many(self.objects):
                self[name] = match_routed(self.objects, self.subs, self["sent"], self["index"], self.freq, grid, self.assignment.places())
            else:
                self[name] = match_once(self.objects, self["sent"], self["index"], grid).select("sub_id", "obj_id")
        else:
            raise KeyError(name)
        return self[name]
