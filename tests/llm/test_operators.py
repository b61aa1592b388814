"""The training-data operators against brute force, on odd rows, and on planted cases."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from geoherald.llm import decontaminate, html_text, images, labelled, line_dedup, mixing, near_dedup, quality, registry, suffixes, toxicity, url_rules
from geoherald.llm.components import components

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, texts, source="s"):
    return spark.createDataFrame([(k, t, "en", source, len(t or "")) for k, t in enumerate(texts)], DOCS)


def sentence(rng, n, vocabulary=400):
    return " ".join(f"w{rng.randrange(vocabulary)}" for _ in range(n))


def edited(rng, text, n):
    words = text.split()
    for _ in range(n):
        words[rng.randrange(len(words))] = f"new{rng.randrange(10**6)}"
    return " ".join(words)


# ---------------------------------------------------------------- odd tables

CLASHES = "size target copies taken source_size component_id kept n_shingles spans score __source __key __drops __k n_lines key id line digest item_id".split()


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, an empty and a very long text, repeated rows, and columns named like those the operators use."""
    long = "\n".join(" ".join(f"w{(k * j) % 4999}" for k in range(1, 60)) for j in range(1, 1200))
    texts = [(1, long), (2, "a short text\na short text"), (2, "a short text\na short text"), (3, ""), (4, None), (None, "no id"), (None, "none either"), (5, long)]
    df = spark.createDataFrame([(k, t, None, "s" if t else None, 0) for k, t in texts], DOCS)
    return settled(df.select("*", *[F.lit("clash").alias(c) for c in CLASHES]))


def settled(df):
    from geoherald.llm.scratch import store

    return store(df, "odd")


ROWWISE = {
    "lines": lambda docs: line_dedup.dedup_lines(docs, params=line_dedup.ALL_LINES),
    "near": lambda docs: near_dedup.near_duplicates(docs),
    "mix": lambda docs: mixing.mix_sources(docs),
    "toxic": lambda docs: docs.select(toxicity.toxicity_score(toxicity.Lexicon({"idiot": 2.0}).build(), F.col("text")).alias("s")),
    "html": lambda docs: html_text.extract_text(docs.withColumn("html", F.col("text")).withColumnRenamed("doc_id", "page_id")),
    "urls": lambda docs: url_rules.judge_urls(docs.withColumn("url", F.concat(F.lit("http://x.com/"), "text")), registry.URL_RULES),
}


@pytest.mark.parametrize("name", ROWWISE)
def test_odd_rows_keep_their_number(odd, name):
    out = ROWWISE[name](odd)
    assert out.count() == 8 and len(out.collect()) == 8
    assert ROWWISE[name](odd.filter("doc_id < 0")).count() == 0


def test_odd_rows_of_searches(spark, odd):
    bench = spark.createDataFrame([(1, " ".join(f"w{(k * 7) % 4999}" for k in range(1, 40))), (2, None), (3, "")], "item_id long, text string")
    assert sorted((r.doc_id, r.item_id) for r in decontaminate.find_leaks(odd.drop("item_id"), bench).collect()) == [(1, 1), (5, 1)]
    assert decontaminate.drop_leaking(odd, bench).count() == 6
    assert decontaminate.find_leaks(odd.drop("item_id").filter("doc_id < 0"), bench).count() == 0
    whole = {r.doc_id: r.spans for r in suffixes.repeated_passages(odd).collect()}
    assert set(whole) == {1, 5} and whole[1][0]["start"] == 0 and whole[1][-1]["end"] == 59 * 1199
    lines = {r.doc_id: r.text for r in ROWWISE["lines"](odd).collect() if r.doc_id}
    assert lines[5].strip() == "" and lines[1].count("\n") == 1198 and lines[3] == "" and lines[4] is None
    mixed = ROWWISE["mix"](odd)
    assert mixed.columns[: len(DOCS.split(", "))] == odd.columns[:5] and mixed.filter("doc_id = 1").first().__getitem__("__source") == "clash"


# ---------------------------------------------------------------- near duplicates


def brute_components(texts, shingle, num, den):
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        n = min(shingle, len(w))
        sets.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set())
    label = list(range(len(texts)))

    def find(k):
        while label[k] != k:
            k = label[k]
        return k

    for i, j in itertools.combinations(range(len(texts)), 2):
        both = len(sets[i] & sets[j])
        if both and den * both >= num * len(sets[i] | sets[j]):
            a, b = sorted((find(i), find(j)))
            label[b] = a
    return [find(k) for k in range(len(texts))], [len(s) for s in sets]


def test_near_duplicates_equal_brute_force(spark):
    rng = random.Random(1)
    texts = [sentence(rng, rng.randint(5, 120)) for _ in range(40)]
    base = sentence(rng, 100)
    texts += [edited(rng, base, rng.randint(0, 4)) for _ in range(40)] + [base] * 5
    texts += ["", None, " \t", "one", "one", "ONE", "two words", "a b c", "A B  c\n"]
    rng.shuffle(texts)
    want, sizes = brute_components(texts, 3, 85, 100)
    got = {r.doc_id: r for r in near_dedup.near_duplicates(docs_of(spark, texts), params=registry.OP8).collect()}
    assert [got[k].component_id for k in range(len(texts))] == want
    assert [got[k].n_shingles for k in range(len(texts))] == sizes
    assert all(got[k].kept == (want[k] == k) for k in got)


@pytest.mark.parametrize("hubs", [1, 6])
def test_groups_around_the_threshold(spark, monkeypatch, hubs):
    """Many copies of which a third are linked pair by pair, and documents that share a passage only."""
    monkeypatch.setattr(near_dedup, "BROADCAST_IDS", 0 if hubs == 1 else 100)
    rng = random.Random(4)
    base, passage = sentence(rng, 120), sentence(rng, 60)
    texts = [edited(rng, base, rng.randint(1, 7)) for _ in range(120)] + [f"{passage} {sentence(rng, rng.randint(5, 30))}" for _ in range(40)]
    rng.shuffle(texts)
    want, _ = brute_components(texts, 3, 85, 100)
    params = near_dedup.NearParams(shingle=3, num=85, den=100, hubs=hubs)
    got = {r.doc_id: r.component_id for r in near_dedup.near_duplicates(docs_of(spark, texts), params=params).collect()}
    assert [got[k] for k in range(len(texts))] == want and 10 < len(set(want)) < 150


def test_parities_never_show_too_many_differences(spark):
    import numpy as np

    rng, signer = np.random.default_rng(2), near_dedup.Signer(near_dedup.NearParams())
    for n in (1, 30, 5000):
        a = np.unique(rng.integers(0, 2**63, n, dtype=np.uint64))
        b = np.unique(np.concatenate([a[n // 10 :], rng.integers(0, 2**63, n // 8 + 1, dtype=np.uint64)]))
        shown = sum(bin(int(x)).count("1") for x in (signer.parities(a) ^ signer.parities(b)).view(np.uint64))
        assert shown <= len(np.setxor1d(a, b)) and (n > 100 or shown > 0)


def test_near_duplicates_odd_tables(spark):
    empty = docs_of(spark, ["x"]).filter("doc_id < 0")
    assert near_dedup.near_duplicates(empty).count() == 0
    twice = docs_of(spark, ["a b c d e f"]).union(docs_of(spark, ["a b c d e f"])).withColumn("component_id", F.lit("clash"))
    assert [r.component_id for r in near_dedup.near_duplicates(twice).collect()] == [0, 0]
    no_id = spark.createDataFrame([(None, "a b c"), (3, "a b c"), (None, "z")], "doc_id long, text string")
    assert sorted((r.component_id is None, r.kept) for r in near_dedup.near_duplicates(no_id).collect()) == [(False, False), (False, True), (True, True)]
    assert near_dedup.keep_one_of_each(twice).count() == 2


def test_sketch_estimates_similarity(spark):
    params = near_dedup.NearParams()
    rng = random.Random(3)
    base = sentence(rng, 300, 10**6)
    rows = near_dedup.sign(docs_of(spark, [base, edited(rng, base, 10)]), "doc_id", "text", params).orderBy("key").collect()
    pair = spark.createDataFrame([(rows[0].sketch, rows[1].sketch)], "a array<long>, b array<long>")
    true = (296 - 49) / (296 + 49)
    assert abs(pair.select(near_dedup.estimated_similarity(F.col("a"), F.col("b"), params)).first()[0] - true) < 0.12


def test_components_of_a_chain(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(40)] + [(100, 101)], "a long, b long")
    assert {r.component for r in components(edges).collect()} == {0, 100}
    assert components(edges.filter("a < 0")).count() == 0


# ---------------------------------------------------------------- lines


def levenshtein(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


@pytest.mark.parametrize("edits", [1, 2, 3])
def test_bit_parallel_distance(spark, edits):
    rng = random.Random(edits)
    pairs = []
    for _ in range(150):
        a = "".join(rng.choice("abé") for _ in range(rng.randint(0, 40)))
        b = list(a)
        for _ in range(rng.randint(0, 4)):
            at = rng.randrange(len(b) + 1)
            b[at : at + rng.randint(0, 1)] = rng.choice(["", "a", "z"])
        pairs.append((a, "".join(b)))
    df = spark.createDataFrame(pairs, "a string, b string")
    got = df.select("a", "b", line_dedup.lines_within(F.col("a"), F.col("b"), edits).alias("ok")).collect()
    assert all(r.ok == (levenshtein(r.a, r.b) <= edits) for r in got)


@pytest.mark.parametrize("rounds", [0, 1, 3])
def test_lines_equal_brute_force(spark, monkeypatch, rounds):
    monkeypatch.setattr(line_dedup, "BROADCAST_ROWS", 400_000 if rounds else 0)
    rng = random.Random(5)
    pool = ["".join(rng.choice("abcdefgh ") for _ in range(rng.randint(26, 60))).strip() for _ in range(20)]
    near = []
    for line in pool:
        for _ in range(3):
            b = list(line)
            for _ in range(rng.randint(0, 3)):
                at = rng.randrange(1, len(b) - 1)
                b[at : at + rng.randint(0, 1)] = rng.choice(["", "x", "y"])
            near.append("".join(b).strip())
    lines = pool + near + ["short", "short", ""]
    texts = ["\n".join(rng.choice(lines) for _ in range(rng.randint(1, 5))) for _ in range(40)] + [None, ""]
    docs = docs_of(spark, texts)
    params = line_dedup.LineParams(rounds=rounds)
    places = [(d, k, x.strip(line_dedup.WHITE)) for d, t in enumerate(texts) if t is not None for k, x in enumerate(t.split("\n"))]
    long = [(d, k, x) for d, k, x in places if len(x) >= params.least]
    ids = {r.line: (r.id, r.h1) for r in line_dedup._lines(docs, "doc_id", "text", params.least).select("line", "id", "h1").distinct().collect()}
    first = {}
    for d, k, x in long:
        first.setdefault(x, (d, k))
    stay = []
    for x in sorted(first, key=ids.get):
        if not any(levenshtein(x, y) <= params.edits for y in stay):
            stay.append(x)
    gone = set(first) - set(stay)
    drop = {(d, k) for d, k, x in long if x in gone or first[x] != (d, k)}
    want = [None if t is None else "\n".join(x for k, x in enumerate(t.split("\n")) if (d, k) not in drop) for d, t in enumerate(texts)]
    got = line_dedup.dedup_lines(docs, params=params).orderBy("doc_id").collect()
    assert [r.text for r in got] == want
    assert [r.n_removed for r in got] == [sum(p[0] == d for p in drop) for d in range(len(texts))]


def test_every_line_that_goes_has_one_like_it(spark):
    """A chain, each two edits from the next: what is near a removed line only stays."""
    base = "the quick brown fox jumps over the lazy dog again"
    chain = [base[:k] + "#" * k + base[k:] for k in range(0, 12, 2)]
    out = [r.text for r in line_dedup.dedup_lines(docs_of(spark, chain)).collect()]
    left = [t for t in out if t]
    assert 2 <= len(left) < len(chain)
    assert all(any(levenshtein(x, y) <= 2 for y in left) for x in chain)
    assert all(levenshtein(x, y) > 2 for x, y in itertools.combinations(left, 2))


def test_segments_against_their_definition():
    for edits in (1, 2, 3):
        parts = edits + 1
        own = lambda n: [(i, sum(sizes[:i]), sizes[i]) for sizes in [[n // parts + (i >= parts - n % parts) for i in range(parts)]] for i in range(parts)]  # noqa: B023, E731
        for n in range(4 * parts, 6 * parts):
            found = {(i, n // parts * i + a, n // parts + b): mine for i, a, b, mine in line_dedup.segment_places(edits)[n % parts]}
            assert {p for p, mine in found.items() if mine} == set(own(n))
            for gap in range(parts):
                for i, start, size in own(n - gap):
                    assert {(i, start + shift, size) for shift in range(-i, i + 1) if abs(gap - shift) <= edits - i} <= set(found)


def test_line_keys_are_compiled(spark):
    """The generated methods stay below the size up to which the JVM compiles them."""
    import re

    lines = line_dedup._lines(docs_of(spark, ["x" * 30]), "doc_id", "text", 24)
    plan = spark._jvm.PythonSQLUtils.explainString(line_dedup.bucket_rows(lines, 2)._jdf.queryExecution(), "codegen")
    sizes = [int(x) for x in re.findall(r"maxMethodCodeSize:(\d+)", plan)]
    assert sizes and max(sizes) < 8000


def test_lines_odd_tables(spark):
    empty = docs_of(spark, ["x"]).filter("doc_id < 0")
    assert line_dedup.dedup_lines(empty).count() == 0
    line = "a line that is long enough to count"
    rows = spark.createDataFrame([(None, line, 1), (1, line, 2), (2, line, 3)], "doc_id long, text string, n_lines long")
    assert sorted((r.doc_id or 0, r.text) for r in line_dedup.dedup_lines(rows).collect()) == [(0, line), (1, line), (2, "")]


def test_short_lines_of_the_query(spark, tmp_path):
    """Exact repeats go whatever their length; short lines within two edits and blank lines stay."""
    texts = ["Yes.\nAll rights reserved.\n\nA", "Yes.\nYes!\n\n All rights reserved. \nA\nB", "  \nB\n", None, ""]
    docs_of(spark, texts).write.parquet(f"{tmp_path}/documents.parquet")
    want = [texts[0], "Yes!\n\nB", "  \n", None, ""]
    kept = {r.doc_id: r.text for r in line_dedup.dedup_lines(docs_of(spark, texts), params=line_dedup.LineParams(exact_least=1)).collect()}
    assert [kept[k] for k in range(5)] == want
    got = {r.doc_id: (r.n_removed, r.n_chars) for r in registry.op4_line_dedup(spark, str(tmp_path)).collect()}
    assert [got[k] for k in range(5)] == [(0, len(want[0])), (3, len(want[1])), (1, len(want[2])), (0, None), (0, 0)]


# ---------------------------------------------------------------- passages


def test_passages_equal_brute_force(spark):
    rng = random.Random(8)
    texts = [sentence(rng, rng.randint(0, 200), 10**6) for _ in range(30)]
    passages = [sentence(rng, n, 10**6) for n in (49, 50, 51, 70, 120)]
    for p in passages:
        for k in rng.sample(range(30), 3):
            texts[k] = f"{texts[k]} {p} {sentence(rng, 30, 10**6)}"
    texts += [texts[0], None, "", passages[3] + " q " + passages[3]]
    words = [(t or "").encode().lower().split() for t in texts]
    seen = {}
    for k, w in enumerate(words):
        for i in range(len(w) - 49):
            seen.setdefault(tuple(w[i : i + 50]), []).append((k, i))
    want = {}
    for places in seen.values():
        if len(places) > 1:
            for k, i in places:
                want.setdefault(k, set()).update(range(i, i + 50))
    got = {r.doc_id: {i for s in r.spans for i in range(s["start"], s["end"])} for r in suffixes.repeated_passages(docs_of(spark, texts)).collect()}
    assert got == want


@pytest.fixture
def arrow_rows(spark, request):
    """Rows of an Arrow batch."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, request.param)
    yield
    spark.conf.set(name, before)


@pytest.mark.parametrize("arrow_rows", [10_000, 7], indirect=True)
def test_passages_among_many_contexts(spark, arrow_rows):
    """Two texts share 50 words through a run that many others share with other words on one side."""
    rng = random.Random(12)
    new = lambda n: sentence(rng, n, 10**9)
    texts, pairs = [], []
    for _ in range(8):
        while True:  # until the suffixes kept of the passage start with the run
            left, run, right = new(17), new(16), new(17)
            words = suffixes.word_hashes(suffixes.split_words(f"{left} {run} {right}"), suffixes.WordHashes())
            if suffixes.gram_hashes(words, 16).argmin() == 17:
                break
        pairs += [len(texts), len(texts) + 1]
        texts += [f"{new(40)} {left} {run} {right} {new(40)}" for _ in range(2)]
        texts += [f"{new(60)} {run} {right} {new(40)}" for _ in range(25)] + [f"{new(40)} {left} {run} {new(60)}" for _ in range(25)]
    got = {r.doc_id: [tuple(s) for s in r.spans] for r in suffixes.repeated_passages(docs_of(spark, texts)).collect()}
    assert got == {k: [(40, 90)] for k in pairs}


def test_passages_odd_tables(spark):
    assert suffixes.repeated_passages(docs_of(spark, ["x"]).filter("doc_id < 0")).count() == 0
    text = " ".join(f"w{k}" for k in range(60))
    rows = spark.createDataFrame([(None, text, 1), (1, text, 2), (2, text, 3)], "doc_id long, text string, spans int")
    assert sorted(r.doc_id for r in suffixes.repeated_passages(rows).collect()) == [1, 2]


# ---------------------------------------------------------------- decontamination


def test_leaks_equal_brute_force(spark):
    rng = random.Random(9)
    items = [sentence(rng, n, 10**6) for n in (5, 12, 20, 33, 64, 150)] + ["tiny item", "", None]
    texts = [sentence(rng, rng.choice([3, 50, 3000]), 10**6) for _ in range(12)]
    for k, item in enumerate(items[:6]):
        texts[k] = f"{texts[k]} {item} {sentence(rng, 40, 10**6)}"
        texts[k + 6] = f"{texts[k + 6]} {edited(rng, item, len(item.split()) // 60)} x"
    texts += ["tiny item", None, ""]

    def grams(t):
        w = (t or "").encode().lower().split()
        n = min(5, len(w))
        return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set()

    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    docs = docs_of(spark, texts)
    want = {(d, i) for d, t in enumerate(texts) for i, x in enumerate(items) if grams(x) and 100 * len(grams(t) & grams(x)) >= 80 * len(grams(x))}
    got = {(r.doc_id, r.item_id) for r in decontaminate.find_leaks(docs, bench).collect()}
    assert got == want
    kept = {r.doc_id for r in decontaminate.drop_leaking(docs, bench).collect()}
    assert kept == set(range(len(texts))) - {d for d, _ in want}
    assert decontaminate.find_leaks(docs, bench.filter("item_id < 0")).count() == 0
    assert decontaminate.drop_leaking(docs, bench.filter("item_id < 0")).count() == len(texts)


def test_items_of_every_length_are_found():
    """Items of one to twenty shingles inside long texts, whole and with a fifth of their shingles changed."""
    import numpy as np

    rng, params = random.Random(21), decontaminate.LeakParams()
    cache = decontaminate.WordHashes()
    grams = lambda t: decontaminate.gram_hashes(decontaminate.word_hashes(decontaminate.split_words(t), cache), 5)
    items = [sentence(rng, n, 10**6) for n in range(5, 25) for _ in range(15)]
    index = decontaminate.ItemIndex([(k, np.unique(grams(t))) for k, t in enumerate(items)], params)
    for k, item in enumerate(items):
        inside = f"{sentence(rng, 300, 10**6)} {item} {sentence(rng, 300, 10**6)}"
        assert [x[0] for x in index.verified(grams(inside))] == [k]
        cut = " ".join(item.split()[: -max(0, (len(item.split()) - 4) // 5) or None])
        assert [x[0] for x in index.verified(grams(f"{sentence(rng, 90, 10**6)} {cut} {sentence(rng, 90, 10**6)}"))] == [k]


# ---------------------------------------------------------------- mixing


def test_mix_reaches_its_targets(spark):
    rng = random.Random(10)
    rows = [(k, sentence(rng, rng.randint(1, 30)), "en", rng.choice(["a", "a", "a", "b", "c", None]), 0) for k in range(1500)] + [(1500, None, "en", "d", 0), (1501, "", "en", "a", 0)]
    out = mixing.mix_sources(spark.createDataFrame(rows, DOCS)).toPandas()
    assert len(out) == len(rows) and (out.taken <= 3 * out["size"]).all()
    by = out.groupby(out.source.fillna("~")).agg(target=("target", "first"), taken=("taken", "sum"), size=("source_size", "first"))
    assert abs(by.target.sum() - out["size"].sum()) < 1e-3
    assert (by.target <= 3 * by["size"] + 1e-6).all()
    assert ((by.taken - by.target).abs() <= 0.1 * by.target + 60).all()
    copies = mixing.emit_copies(mixing.mix_sources(spark.createDataFrame(rows, DOCS)))
    assert copies.count() == out.copies.sum()
    assert mixing.mix_sources(spark.createDataFrame([], DOCS)).count() == 0


# ---------------------------------------------------------------- URLs


def test_url_rules(spark):
    urls = [
        ("http://a.com/en/x", "com/en/", "block"), ("https://EXAMPLE.com/en/71?q", "example.com/en/7", "allow"), ("x://www.example.com/en/8", "com/en/", "block"),
        ("http://example.net/de/8/9#f", "example.net/de/8", "block"), ("http://telecom/en/", None, "allow"), ("no scheme com/en/", None, "allow"), (None, None, "allow"),
        ("http://org/es", None, "allow"), ("http://org/es/", "org/es/", "block"), ("http://a.com", None, "allow"), ("http://", None, "allow"), ("http://com?/en/", None, "allow"),
    ]
    df = spark.createDataFrame([(k, u[0], "clash") for k, u in enumerate(urls)], "page_id long, url string, host string")
    got = url_rules.judge_urls(df, registry.URL_RULES).orderBy("page_id").collect()
    assert [(r.rule, r.verdict) for r in got] == [(u[1], u[2]) for u in urls]
    assert got[1].host == "example.com" and got[1].path == "/en/71" and got[6].host == ""


def test_url_rules_have_the_words_of_the_contract(spark):
    assert [(r.verdict, r.host + r.path) for r in registry.URL_RULES] == [("block", "com/en/"), ("allow", "example.com/en/7"), ("allow", "net/de/"), ("block", "example.net/de/8"), ("block", "org/es/")]
    df = spark.createDataFrame([(0, "http://a.net/de/1"), (1, "http://example.net/de/7"), (2, "http://example.net/de/81")], "page_id long, url string")
    got = url_rules.judge_urls(df, registry.URL_RULES, default="block").orderBy("page_id").collect()
    assert [(r.rule, r.verdict) for r in got] == [("net/de/", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block")]


def test_longest_rule_wins_and_allow_wins_a_tie():
    rules = [url_rules.Rule.parse(*r) for r in (("block", "b.c/"), ("allow", "c/x/y"), ("block", "c/x/y"), ("allow", "b.c/x"))]
    trie = url_rules.RuleTrie(rules)
    assert trie.find("a.b.c", "/x").path == "/x"
    assert trie.find("c", "/x/yz").verdict == "allow"
    assert trie.find("d", "/") is None


# ---------------------------------------------------------------- classifiers


def accuracy(spark, folder, scored, label):
    rows = scored.join(spark.read.parquet(f"{folder}/labels.parquet"), "doc_id").filter("held_out").toPandas()
    return (rows.predicted == rows[label]).mean()


def test_toxicity(spark):
    folder = "/root/testdata/sf0.01"
    assert accuracy(spark, folder, registry.op6_toxicity(spark, folder), "toxic") > 0.93
    lexicon = toxicity.Lexicon({"idiot$": 5.0, "mor": 2.0}, exceptions=("class idiot",)).build()
    assert lexicon.hits(toxicity.fold("You 1d10t!!"))
    assert lexicon.hits(toxicity.fold("іdіоt"))
    assert lexicon.hits(toxicity.fold("ídiót morons")) and len(lexicon.hits(toxicity.fold("idiot moron"))) == 2
    assert not lexicon.hits(toxicity.fold("a class idiot here"))
    assert not lexicon.hits(toxicity.fold("idiotic armor"))
    assert lexicon.density(None) == lexicon.density("") == 0.0


def test_toxicity_without_labels(spark):
    docs = docs_of(spark, ["a", None, ""])
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    lexicon = toxicity.train_lexicon(docs, none, F.lit(True))
    assert [r[0] < 0.5 for r in docs.select(toxicity.toxicity_score(lexicon, F.col("text"))).collect()] == [True] * 3


def test_quality(spark):
    folder = "/root/testdata/sf0.01"
    assert accuracy(spark, folder, registry.op10_quality(spark, folder), "quality") > 0.93
    assert len(quality.features("a b. C")) == len(quality.FEATURES) == len(quality.features(None))
    docs = docs_of(spark, ["a", None, ""])
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    ranker = quality.train_ranker(docs, none, F.lit(True))
    assert [round(r[0], 6) for r in docs.select(quality.quality_score(ranker, F.col("text"))).collect()] == [0.7] * 3


def test_quality_learns_from_all_labelled_rows(spark, monkeypatch):
    import numpy as np

    monkeypatch.setattr(quality, "PER_BUCKET", 50)
    rng = random.Random(4)
    docs = docs_of(spark, [sentence(rng, 30) if k % 4 else sentence(rng, 5) + "!?!" for k in range(800)])
    labels = spark.createDataFrame([(k, int(k % 4 > 0), None) for k in range(800)], "doc_id long, quality int, toxic int")
    seen = quality.measured(docs)
    train = settled(seen.join(labels.selectExpr("doc_id as key", "quality as label"), "key"))
    pairs = quality.paired(train, {0: 200, 1: 600}).collect()
    assert {tuple(p.better) for p in pairs} == {tuple(r.x) for r in train.filter("label = 1").collect()}
    assert {tuple(p.worse) for p in pairs} == {tuple(r.x) for r in train.filter("label = 0").collect()}
    ranker = quality.train_ranker(docs, labels, F.lit(True))
    x = np.array([r.x for r in train.collect()])
    wide = quality.Ranker.widened(x)
    assert np.allclose(ranker.mean, wide.mean(axis=0)) and np.allclose(ranker.scale, np.maximum(wide.std(axis=0), 1e-6))
    assert np.isclose(ranker.cut, np.sort(ranker.raw(x))[199])
    wide = lambda side: (quality.Ranker.widened(np.array([p[side] for p in pairs])) - ranker.mean) / ranker.scale
    assert np.allclose(ranker.weights, quality.fit_bradley_terry(wide("better"), wide("worse"), 1e-4), atol=1e-5)


def test_rank_is_exact(spark):
    values = settled(spark.range(3000).select((F.pmod(F.xxhash64("id"), F.lit(1000)) / 7).alias("v")))
    want = sorted(r.v for r in values.collect())
    assert [quality.kth_smallest(values, 3000, k) for k in (1, 2, 900, 1500, 2999, 3000)] == [want[k - 1] for k in (1, 2, 900, 1500, 2999, 3000)]


def test_pairs_teach_an_order():
    import numpy as np

    rng = np.random.default_rng(1)
    better, worse = rng.normal(1, 1, (400, 3)), rng.normal(0, 1, (400, 3))
    weights = quality.fit_bradley_terry(better, worse, 1e-3)
    assert ((better - worse) @ weights > 0).mean() > 0.75


def test_sample_is_bounded_and_stable(spark):
    docs = docs_of(spark, ["t"] * 50)
    labels = spark.createDataFrame([(k, k % 2, None) for k in range(50)], "doc_id long, quality int, toxic int")
    one = labelled.sample_labelled(docs, labels, "quality", F.lit(True), 5)
    assert one.count() == 10
    assert labelled.class_weights({0: 5, 1: 5}, labels, "quality", F.lit(True)) == {0: 5.0, 1: 5.0}


# ---------------------------------------------------------------- pages


def test_html_blocks():
    page = "<html><body><nav><a href='/'>Home</a></nav><p>One &amp; two<br>three <b>four</b><p>Five<script>var x='<p>no</p>'</script><!-- no --></body>"
    blocks = html_text.blocks_of(page)
    assert [b.text for b in blocks] == ["Home", "One & two three four", "Five"]
    assert blocks[0].linked == 4
    assert [b.text for b in html_text.blocks_of('<p>One <a title="abc>link text</a> two</p><p>Three</p>')] == ["One link text two", "Three"]
    assert [(b.text, b.linked) for b in html_text.blocks_of("<p><a href=/x/>linked</a> plain</p><div class='a'/>x")][0] == ("linked plain", 6)
    assert html_text.blocks_of(None) == html_text.blocks_of("") == html_text.blocks_of("<div class='x") == []


def test_html_text_on_unseen_layouts():
    chain = html_text.default_chain()
    wrong = total = 0
    for blocks, labels in html_text.labelled_pages(60, seed=99):
        got = chain.viterbi(html_text.block_features(blocks))
        wrong += sum(a != b for a, b in zip(got, labels))
        total += len(labels)
    assert wrong <= 0.02 * total


def test_html_text_query(spark, folder):
    import html as codec
    import re

    rows = registry.op1_html_text(spark, folder).join(spark.read.parquet(f"{folder}/pages.parquet").select("page_id", "html"), "page_id").collect()
    for r in rows:
        inner = re.search(r"<article>(.*?)(</article>|$)", r.html, re.S)[1]
        plain = re.sub(r"<[^>]*>", "", re.sub(r"</?(p|br|h1)>", " ", inner))
        assert r.text == " ".join(codec.unescape(plain).split()) and r.n_chars == len(r.text)
    odd = spark.createDataFrame([(1, None, "x"), (2, "", "y"), (3, "<p", "z")], "page_id long, html string, text string")
    assert [(r.text, r.n_chars) for r in html_text.extract_text(odd).orderBy("page_id").collect()] == [("", 0)] * 3


def test_viterbi_against_all_labellings():
    rng = random.Random(2)
    for _ in range(20):
        weights = {f"f{k}": (rng.gauss(0, 1), rng.gauss(0, 1)) for k in range(6)}
        chain = html_text.ChainField(weights, tuple(tuple(rng.gauss(0, 1) for _ in range(2)) for _ in range(2)))
        rows = [[f"f{rng.randrange(6)}"] for _ in range(6)]
        score = lambda y: sum(weights[r[0]][k] for r, k in zip(rows, y)) + sum(chain.steps[a][b] for a, b in zip(y, y[1:]))  # noqa: B023, E731
        best = max(itertools.product((0, 1), repeat=6), key=score)
        assert abs(score(best) - score(chain.viterbi(rows))) < 1e-9


# ---------------------------------------------------------------- images


def drawn(n, seed=5):
    import numpy as np

    rng = np.random.default_rng(seed)
    return [[float(x) for x in rng.normal(0, 0.2, 64)] for _ in range(n)]


@pytest.mark.parametrize("bound", [images.BROADCAST_POINTS, 0])
def test_copies_are_found(spark, monkeypatch, bound):
    monkeypatch.setattr(images, "BROADCAST_POINTS", bound)
    vectors = list(enumerate(drawn(30)))
    vectors += [(30, vectors[0][1]), (31, None), (32, [])]
    rows = spark.createDataFrame(vectors, "id long, v array<float>").select("id", images.rendered(F.col("v")).alias("image"))
    got = {r.id: r for r in images.find_copies(rows, F.col("id") % 3 == 0, change=images.edited).collect()}
    assert len(got) == 33 and got[30].class_id == 0 and got[31].class_id is None and got[31].copy_of == []
    found = [k for k in range(0, 30, 3) if k in got[k].copy_of]
    assert len(found) >= 9
    assert sum(len(r.copy_of) for r in got.values()) <= len(found) + 4


def test_both_searches_give_the_same_links(spark, monkeypatch):
    vectors = spark.createDataFrame(list(enumerate(drawn(12, 6))), "id long, v array<float>")
    points = vectors.select("id", images.points_column(images.rendered(F.col("v")), images.ImageParams()).alias("points"))
    asked = vectors.filter("id < 6").select("id", images.points_column(images.edited(images.rendered(F.col("v"))), images.ImageParams()).alias("points"))
    links = lambda: sorted(map(tuple, images.search(asked, points).select("q", "d", "votes").collect()))
    here = links()
    monkeypatch.setattr(images, "BROADCAST_POINTS", 0)
    assert here == links() and len(here) >= 6
    none = asked.filter("id < 0")
    assert images.search(none, points).count() == images.search(points, none).count() == 0


def turned(grid, degrees):
    """About the centre, bilinear, the border repeated."""
    import numpy as np

    h, w = grid.shape
    y, x = np.mgrid[:h, :w] - np.array([(h - 1) / 2, (w - 1) / 2])[:, None, None]
    c, s = np.cos(np.deg2rad(degrees)), np.sin(np.deg2rad(degrees))
    y, x = np.clip(c * y + s * x + (h - 1) / 2, 0, h - 1.01), np.clip(c * x - s * y + (w - 1) / 2, 0, w - 1.01)
    b, a = y.astype(int), x.astype(int)
    return (grid[b, a] * (1 - x + a) + grid[b, a + 1] * (x - a)) * (1 - y + b) + (grid[b + 1, a] * (1 - x + a) + grid[b + 1, a + 1] * (x - a)) * (y - b)


EDITS = {
    "crop": lambda g: g[18:76, 20:78],
    "smaller": lambda g: images.resized(g, 77, 77),
    "larger": lambda g: images.resized(g, 125, 125),
    "quarter turn": lambda g: images.np.rot90(g),
    "turn": lambda g: turned(g, 20),
    "darker": lambda g: g * 0.5 + 10,
    "noise": lambda g: g + images.np.random.default_rng(1).normal(0, 4, g.shape),
    "crop and smaller": lambda g: images.resized(g[10:, :84], 70, 68),
}


@pytest.mark.parametrize("edit", EDITS)
def test_recall_of_edited_copies(edit):
    import pyarrow as pa

    params = images.ImageParams()
    pictures = [images.picture(v) for v in drawn(40, 7)]
    column = lambda all_points: pa.array([[dict(zip((*images._NAMES, "bits"), p)) for p in points] for points in all_points], images._POINT)
    tables = images.QueryTables(list(range(40)), column([images.describe(images.encode(EDITS[edit](images.decode(p))), params) for p in pictures]), params)
    starts, numbers, bits = images._columns(column([images.describe(p, params) for p in pictures]))
    links = [(d, q) for d in range(40) for q, _ in tables.linked(numbers[starts[d] : starts[d + 1]], bits[starts[d] : starts[d + 1]])]
    assert sum(d == q for d, q in links) >= 36
    assert sum(d != q for d, q in links) <= 2


def test_decode_refuses_broken_images():
    assert images.decode(None) is None and images.decode(b"") is None and images.decode(b"P5 9 9 255\nxx") is None
    assert images.decode(images.encode(images.np.full((3, 4), 7.0))).shape == (3, 4)
    assert images.describe(b"junk", images.ImageParams()) == []
