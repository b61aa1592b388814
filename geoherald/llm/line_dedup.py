"""Line dedup by a segment-partition edit join, in DataFrame functions only.

A line that equals an earlier line is removed; what stays is at the first place of its line, in the order
of document id and line number. Of distinct lines, in the order of their hashes, one is removed if it is
within ``edits`` edit operations of one that stays, so every line that goes has a like one left. The edit
join is for lines of ``least`` code points and more (white space at the ends not counted), as two edits
are much in a short line; exact repeats are removed from ``exact_least`` code points on, ``least`` if it
is None. Blank lines are never touched.

The join: two lines at most ``edits`` apart agree in one of the ``edits + 1`` segments that the shorter
is cut into, at a start that can be shifted by a few places only. A line therefore sends one row for
each substring that can be a segment of a line up to ``edits`` shorter; its own segments are among them
and marked. Where these substrings lie depends on the length and its remainder by ``edits + 1`` only, so
they are listed once for each remainder (:func:`segment_places`). Rows carry a hash of segment number and
content, and an id made of 54 bits of the line's hash and its length modulo 1024, which is enough to
check lengths.

A line that is the lowest in all its buckets of equal content stays, and meets all their members; those
within reach go, and both are then settled. After ``rounds`` rounds of this, in which a large group of
like lines costs one pair for each member, all pairs of what is still open are looked at, those first
dropped whose pairs of neighbouring characters differ too much; their order is then settled on the links
alone. Pairs are verified by a banded bit-parallel edit distance. Two lines of one id (a collision of 54
bits) are left alone.

Very frequent lines (1/100,000 of all, so at most 100,000 of them) send rows from their first place only;
their list is broadcast. The texts of lines with company in a bucket are picked by a broadcast list of
places up to ``BROADCAST_ROWS``, by a join beyond.

Results for odd rows: a null text stays null, an empty one empty; a row without an id is left as it is
and takes no part; rows with equal ids are taken for one document. Ties cannot occur, as places differ.
An empty table gives an empty table. Other columns are kept and can have any name.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from geoherald.llm.scratch import discard, store, stored, unused

BROADCAST_ROWS = 400_000
_LENGTHS = 1024
WHITE = " \t\r\f\x0b"


@dataclass(frozen=True)
class LineParams:
    edits: int = 2
    least: int = 24
    exact_least: int | None = None
    rounds: int = 3

    @property
    def counted(self) -> int:
        """Code points of the shortest lines that take part at all."""
        return self.least if self.exact_least is None else max(1, min(self.least, self.exact_least))


#: Exact repeats of all lines but blank ones.
ALL_LINES = LineParams(exact_least=1)


def let(value: Column, body) -> Column:
    """``body`` of ``value``, which is evaluated once however often ``body`` names it."""
    return F.transform(F.array(value), body)[0]


def segment_places(edits: int) -> list[list[tuple[int, int, int, bool]]]:
    """For lines of length ``(edits + 1) * q + r``, by r: segment number i, ``start - q * i``, ``size - q``, own.

    Segments are equally long but for the later ones, which take the remainder. Segment i of a line
    shorter by ``gap`` can be shifted by at most i places by what comes before it, and what comes after
    must make up for the rest of the difference in length. Own segments are those without gap and shift.
    """
    parts, found = edits + 1, []
    for r in range(parts):
        places: dict[tuple[int, int, int], bool] = {}
        for gap in range(parts):
            less, rest = divmod(r - gap, parts)
            plain = parts - rest
            for i in range(parts):
                start, size = less * i + max(0, i - plain), less + (i >= plain)
                for shift in range(max(-i, gap - (edits - i)), min(i, gap + (edits - i)) + 1):
                    places[i, start + shift, size] = places.get((i, start + shift, size), False) or gap == shift == 0
        found.append([(*place, own) for place, own in sorted(places.items())])
    return found


def bucket_rows(lines: DataFrame, edits: int) -> DataFrame:
    """``k, id, own`` for every substring of ``line`` that can be a segment of a line up to ``edits`` shorter."""
    place = lambda p: F.struct(F.lit(p[0]).alias("i"), F.lit(p[1]).alias("start"), F.lit(p[2]).alias("size"), F.lit(p[3]).alias("own"))
    table = F.array(*[F.array(*[place(p) for p in places]) for places in segment_places(edits)])
    q = F.floor(F.col("n") / (edits + 1)).cast("int")
    rows = lines.select("id", "line", "n", q.alias("q"), F.explode(F.get(table, F.col("n") % (edits + 1))).alias("s"))
    start, size = F.col("q") * F.col("s.i") + F.col("s.start"), F.col("q") + F.col("s.size")
    rows = rows.filter((start >= 0) & (start + size <= F.col("n")))
    return rows.select(F.xxhash64("s.i", F.substr("line", start + 1, size)).alias("k"), "id", F.col("s.own").alias("own"))


def within_edits(a: Column, b: Column, edits: int) -> Column:
    """Whether two arrays of characters are at most ``edits`` operations apart.

    Bit t of a word stands for row j - edits + t of the column j of the distance table, rows running
    over ``a`` and columns over ``b``. ``up`` and ``down`` hold the differences between neighbouring
    rows, ``low`` the value in the lowest row of the band. Rows past the end of ``a`` match nothing.
    A column from which the answer cannot come any more leaves the state as it is.
    """
    width = 2 * edits + 1
    full = (1 << width) - 1
    word = lambda v: F.lit(v).cast("long")
    inverse = lambda v: F.bitwise_not(v).bitwiseAND(word(full))

    def step(state: Column, item: Column, rows: Column) -> Column:
        equal = word(0)
        for t in range(width):
            equal = equal.bitwiseOR(F.when(F.get(rows, item["j"] + (t - edits)) == item["c"], word(1 << t)).otherwise(word(0)))
        up, down = state["up"], state["down"]

        def shifted(same: Column) -> Column:
            right = down.bitwiseOR(inverse(same.bitwiseOR(up)))
            left = same.bitwiseAND(up)
            below = F.shiftright(same, 1)
            return F.struct(
                left.bitwiseOR(inverse(below.bitwiseOR(right))).alias("up"),
                below.bitwiseAND(right).alias("down"),
                (state["low"] + F.when(same.bitwiseAND(word(1 << (width - 1))) != 0, 0).otherwise(1)).alias("low"),
            )

        carried = lambda x: (x.bitwiseAND(up) + up).bitwiseXOR(up).bitwiseOR(x).bitwiseOR(down).bitwiseAND(word(full))
        return F.when(state["low"] > 3 * edits, state).otherwise(let(let(equal, carried), shifted))

    def reached(p: Column) -> Column:
        start = F.struct(word(full ^ ((1 << edits) - 1)).alias("up"), word(0).alias("down"), F.lit(edits).alias("low"))
        items = F.transform(p["b"], lambda c, j: F.struct(c.alias("c"), j.alias("j")))
        last = F.aggregate(items, start, lambda state, item: step(state, item, p["a"]))
        # from the lowest row back up to the last row of ``a``
        below = F.size(p["a"]) - F.size(p["b"]) + edits
        mask = word((1 << (2 * edits)) - 1) - (F.call_function("shiftleft", word(1), below) - 1)
        value = lambda s: s["low"] - F.bit_count(s["up"].bitwiseAND(mask)) + F.bit_count(s["down"].bitwiseAND(mask))
        found = let(last, lambda s: (s["low"] <= 3 * edits) & (value(s) <= edits))
        return F.when(F.abs(F.size(p["a"]) - F.size(p["b"])) > edits, F.lit(False)).otherwise(found)

    return let(F.struct(a.alias("a"), b.alias("b")), reached)


def lines_within(x: Column, y: Column, edits: int, block: int = 16) -> Column:
    """Whether two lines are at most ``edits`` operations apart.

    Blocks that both share at their start, and then at their end, are left out first: that never changes
    an edit distance, and leaves few columns to go through.
    """

    def unlike(p: Column, side) -> Column:
        """Code points in the blocks alike on one side, up to the first that differ."""
        blocks = F.floor(F.least(F.length(p["x"]), F.length(p["y"])) / block).cast("int")
        differ = F.filter(F.sequence(F.lit(0), blocks), lambda k: side(p["x"], k) != side(p["y"], k))
        return F.coalesce(F.get(differ, F.lit(0)), blocks) * block

    head = lambda t, k: F.substr(t, k * block + 1, F.lit(block))
    tail = lambda t, k: F.substr(t, F.greatest(F.length(t) - (k + 1) * block + 1, F.lit(1)), F.lit(block))
    letters = lambda t: F.when(F.length(t) == 0, F.array().cast("array<string>")).otherwise(F.split(t, ""))
    both = lambda p, f: F.struct(f(p["x"]).alias("x"), f(p["y"]).alias("y"))
    after = lambda p: let(unlike(p, head), lambda n: both(p, lambda t: F.substr(t, n + 1, F.length(t))))
    before = lambda p: let(unlike(p, tail), lambda n: both(p, lambda t: F.substr(t, F.lit(1), F.length(t) - n)))
    core = let(let(F.struct(x.alias("x"), y.alias("y")), after), before)
    return let(core, lambda p: within_edits(letters(p["x"]), letters(p["y"]), edits))


def bigram_parity(line: Column) -> Column:
    """One bit for each of 64 classes of pairs of neighbouring characters: whether the line has an odd number.

    An edit operation takes away at most two pairs and adds at most two, so it changes at most four bits.
    """
    pairs = F.transform(F.sequence(F.lit(1), F.greatest(F.length(line) - 1, F.lit(1))), lambda i: F.pmod(F.xxhash64(F.substr(line, i, F.lit(2))), F.lit(64)).cast("int"))
    return F.aggregate(pairs, F.lit(0).cast("long"), lambda bits, k: bits.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), k)))


def _lines(docs: DataFrame, key: str, text: str, least: int) -> DataFrame:
    rows = docs.select(F.col(f"`{key}`").alias("key"), F.col(f"`{text}`").cast("string").alias("text")).filter("key is not null")
    rows = rows.select("key", F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    rows = rows.select("key", "pos", F.btrim("line", F.lit(WHITE)).alias("line")).filter(F.length("line") >= least)
    rows = rows.withColumns({"n": F.length("line"), "h1": F.xxhash64("line"), "h2": F.xxhash64(F.lit(2), "line")})
    return rows.withColumn("id", F.col("h1").bitwiseAND(F.lit(-_LENGTHS).cast("long")).bitwiseOR((F.col("n") % _LENGTHS).cast("long")))


def _texts_of(ids: DataFrame, classes: DataFrame, docs: DataFrame, key: str, text: str, params: LineParams) -> DataFrame:
    """``id, h1, h2, line`` of the given ids, read at their first places; without ids that two lines share."""
    places = store(classes.join(ids, "id", "left_semi").select(F.col("first.key").alias("k"), F.col("first.pos").alias("p")), "places")
    if places.count() <= BROADCAST_ROWS:
        places = F.broadcast(places)
    wanted = docs.join(places.select(F.col("k").alias("__k")).distinct(), docs[key] == F.col("__k"), "left_semi")
    found = _lines(wanted, key, text, params.least).join(places, (F.col("key") == F.col("k")) & (F.col("pos") == F.col("p")), "left_semi")
    lines = found.groupBy("id", "h1", "h2").agg(F.first("line").alias("line"))
    alone = lines.groupBy("id").agg(F.count(F.lit(1)).alias("c"), F.first("h1").alias("h1"), F.first("h2").alias("h2"), F.first("line").alias("line"))
    return alone.filter("c = 1").drop("c")


def _verified(pairs: DataFrame, texts: DataFrame, params: LineParams) -> DataFrame:
    """Of ``a, b`` those within reach."""
    left = texts.select(F.col("id").alias("a"), F.col("line").alias("ta"))
    right = texts.select(F.col("id").alias("b"), F.col("line").alias("tb"))
    return pairs.join(left, "a").join(right, "b").filter(lines_within(F.col("ta"), F.col("tb"), params.edits)).select("a", "b")


def _lengthened(shorter: Column, longer: Column) -> Column:
    """By how much the line of one id is longer than that of another, modulo ``_LENGTHS``."""
    mask = F.lit(_LENGTHS - 1).cast("long")
    return F.pmod(longer.bitwiseAND(mask) - shorter.bitwiseAND(mask), F.lit(_LENGTHS))


def _with_company(rows: DataFrame) -> DataFrame:
    """``k, id, own, low`` of the rows whose bucket has another id; ``low`` is the bucket's lowest."""
    bucket = Window.partitionBy("k")
    rows = rows.withColumns({"low": F.min("id").over(bucket), "high": F.max("id").over(bucket)})
    return rows.filter("low <> high").select("k", "id", "own", "low")


def _settled(links: DataFrame) -> DataFrame:
    """``id`` of what goes, for links ``a, b`` with a < b: whatever has a lower neighbour that stays."""
    spark = links.sparkSession
    links, at = stored(links, "links")
    gone = links.select(F.col("b").alias("id")).limit(0)
    while not links.isEmpty():
        stay = links.select("a").distinct().join(links.select(F.col("b").alias("a")).distinct(), "a", "left_anti")
        fresh = store(links.join(stay, "a", "left_semi").select(F.col("b").alias("id")).distinct(), "gone")
        gone = gone.union(fresh)
        open_links = links.join(stay, "a", "left_anti")
        for side in ("a", "b"):
            open_links = open_links.join(fresh.withColumnRenamed("id", side), side, "left_anti")
        links, following = stored(open_links.select("a", "b"), "links")
        discard(spark, at)
        at = following
    discard(spark, at)
    return gone


def _frequent(classes: DataFrame) -> Column:
    """Whether a distinct line is 1/100,000 of all lines or more; at most 100,000 are."""
    whole = classes.agg(F.sum("times")).first()[0] or 0
    return F.col("times") >= max(3, whole / 100_000)


def near_lines(docs: DataFrame, classes: DataFrame, key: str, text: str, params: LineParams) -> DataFrame:
    """``h1, h2`` of the distinct lines within reach of one of a lower id that stays."""
    spark = docs.sparkSession
    hot = classes.filter(_frequent(classes)).select(F.col("h1").alias("g1"), F.col("h2").alias("g2"), "first")
    lines = _lines(docs, key, text, params.least).join(F.broadcast(hot), (F.col("h1") == F.col("g1")) & (F.col("h2") == F.col("g2")), "left")
    lines = lines.filter(F.col("first").isNull() | ((F.col("first.key") == F.col("key")) & (F.col("first.pos") == F.col("pos"))))
    rows, at = stored(_with_company(bucket_rows(lines, params.edits)).select("k", "id", "own").distinct(), "buckets")
    texts = store(_texts_of(rows.select("id").distinct(), classes, docs, key, text, params), "texts")
    gone = rows.select("id").limit(0)

    for _ in range(params.rounds):
        met, met_at = stored(_with_company(rows), "met")
        discard(spark, at)
        rows, at = met.select("k", "id", "own"), met_at
        if met.isEmpty():
            break
        lowest = store(met.groupBy("id").agg(F.max(F.col("id") != F.col("low")).alias("above")).filter("not above").select("id"), "lowest")
        near_in_length = F.least(_lengthened(F.col("low"), F.col("id")), _lengthened(F.col("id"), F.col("low"))) <= params.edits
        pairs = met.filter((F.col("id") != F.col("low")) & near_in_length).select(F.col("low").alias("a"), F.col("id").alias("b")).distinct()
        pairs = pairs.join(lowest.withColumnRenamed("id", "a"), "a", "left_semi")
        fresh = store(_verified(pairs, texts, params).select(F.col("b").alias("id")).distinct(), "near")
        gone = gone.union(fresh)
        rows, at = stored(met.join(lowest.union(fresh), "id", "left_anti").select("k", "id", "own"), "buckets")
        discard(spark, met_at)

    # all pairs of what is open
    signs = texts.select("id", bigram_parity(F.col("line")).alias("sig"))
    marked, marked_at = stored(_with_company(rows).select("k", "id", "own").join(signs, "id"), "marked")
    short = marked.filter("own").select("k", F.col("id").alias("r"), F.col("sig").alias("r_sig"))
    long = marked.select("k", F.col("id").alias("s"), F.col("sig").alias("s_sig"))
    alike = F.bit_count(F.col("r_sig").bitwiseXOR(F.col("s_sig"))) <= 4 * params.edits
    apart = (F.col("r") != F.col("s")) & (_lengthened(F.col("r"), F.col("s")) <= params.edits) & alike
    open_pairs = short.join(long, "k").filter(apart).select(F.least("r", "s").alias("a"), F.greatest("r", "s").alias("b")).distinct()
    if not marked.isEmpty():
        gone = gone.union(_settled(_verified(open_pairs, texts, params)))
    discard(spark, at, marked_at)
    return texts.join(gone, "id", "left_semi").select("h1", "h2")


def repeated_lines(docs: DataFrame, key: str = "doc_id", text: str = "text", params: LineParams = LineParams()) -> DataFrame:
    """``key, drops``: for each document with lines to remove, their numbers from 0."""
    docs = docs.select(F.col(f"`{key}`"), F.col(f"`{text}`"))
    occurrences = store(_lines(docs, key, text, params.counted).select("key", "pos", "h1", "h2", "id", "n"), "lines")
    classes = store(occurrences.groupBy("h1", "h2").agg(F.min(F.struct("key", "pos")).alias("first"), F.count(F.lit(1)).alias("times"), F.min("id").alias("id"), F.min("n").alias("n")), "classes")
    near = near_lines(docs, classes.filter(F.col("n") >= params.least), key, text, params).select(F.col("h1").alias("g1"), F.col("h2").alias("g2"), F.lit(True).alias("near"))
    special = classes.join(near, (F.col("h1") == F.col("g1")) & (F.col("h2") == F.col("g2")), "left").filter("times > 1 or near")
    special = special.select(F.col("h1").alias("c1"), F.col("h2").alias("c2"), "first", F.coalesce("near", F.lit(False)).alias("near"), _frequent(classes).alias("hot"))
    same = (F.col("h1") == F.col("c1")) & (F.col("h2") == F.col("c2"))
    hot = F.broadcast(special.filter("hot"))
    hits = occurrences.join(hot, same).union(occurrences.join(hot, same, "left_anti").join(special.filter("not hot"), same))
    hits = hits.filter(F.col("near") | (F.col("first.key") != F.col("key")) | (F.col("first.pos") != F.col("pos")))
    return hits.groupBy("key").agg(F.collect_set("pos").alias("drops"))


def dedup_lines(docs: DataFrame, key: str = "doc_id", text: str = "text", params: LineParams = LineParams()) -> DataFrame:
    """Every row of ``docs`` with ``text`` without its repeated lines, and ``n_lines, n_removed`` added."""
    k, d = unused("__key", docs.columns), unused("__drops", docs.columns)
    drops = repeated_lines(docs, key, text, params).toDF(k, d)
    rows = docs.select(*[F.col(f"`{c}`") for c in docs.columns if c not in {"n_lines", "n_removed"}])
    rows = rows.join(drops, rows[key] == drops[k], "left")
    body = F.col(f"`{text}`").cast("string")
    lines = F.split(body, "\n")
    shorter = F.array_join(F.filter(lines, lambda x, i: ~F.array_contains(F.col(d), i)), "\n")
    counts = {"n_lines": F.when(body.isNull(), 0).otherwise(F.size(lines)), "n_removed": F.when(F.col(d).isNull(), 0).otherwise(F.size(d))}
    changed = F.when(F.col(d).isNull(), body).otherwise(shorter)
    return rows.withColumns(counts).withColumn(text, changed).select(*[F.col(f"`{c}`") for c in docs.columns if c not in {"n_lines", "n_removed"}], "n_lines", "n_removed")
