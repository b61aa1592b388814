"""The pipeline: its stages, their columns, and planted cases."""

import random

import corpus_pipeline
from geoherald.llm import registry
from geoherald.llm.scratch import store


def test_stages(spark, folder):
    docs = registry.table(spark, folder, "documents")
    kept = {0: docs.count()}
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES, 1):
        before, docs = docs, store(stage(spark, docs, folder), "stage")
        kept[k] = docs.count()
        if k < 5:
            assert docs.columns == before.columns and docs.dtypes == before.dtypes
    # so few labelled rows may teach the first stage nothing
    # and copies, which lose their repeated lines in the second, may leave the third nothing to find
    assert kept[1] <= kept[0] and kept[2] == kept[1] and kept[3] <= kept[2] and kept[4] < kept[3]
    assert kept[4] > 0.6 * kept[0]


def test_near_stage_keeps_one(spark, folder):
    rng = random.Random(1)
    base = [f"w{rng.randrange(10**6)}" for _ in range(200)]
    copy = base[:100] + ["other"] + base[101:]
    rows = [(1, " ".join(base), "en", "s", 1), (2, " ".join(copy), "en", "s", 1), (3, "something else", "en", "s", 1), (4, None, None, None, None)]
    docs = spark.createDataFrame(rows, registry.table(spark, folder, "documents").schema)
    assert sorted(r.doc_id for r in corpus_pipeline.dedup_documents(spark, docs, folder).collect()) == [1, 3, 4]


def test_leak_stage(spark, folder):
    item = registry.table(spark, folder, "benchmark").filter("length(text) > 100").first().text
    rows = [(1, f"before {item} after", "en", "s", 1), (2, "clean text", "en", "s", 1), (3, None, None, None, None)]
    docs = spark.createDataFrame(rows, registry.table(spark, folder, "documents").schema)
    assert sorted(r.doc_id for r in corpus_pipeline.drop_leaks(spark, docs, folder).collect()) == [2, 3]


def test_whole_run_against_brute_force(spark, tmp_path):
    """No labels, so nothing is toxic; repeated lines, near copies and leaks go, and the rest is mixed."""
    import hashlib

    from test_operators import DOCS, brute_components, edited, sentence

    rng = random.Random(31)
    new = lambda n: sentence(rng, n, 10**6)
    item, footer = new(20), "all rights of this page are reserved by its owner"
    texts = [f"{new(60)}\n{footer}\n{new(10)}" for _ in range(12)]
    base = new(200)
    texts += [base, edited(rng, base, 2), edited(rng, base, 3)]
    texts += [f"{new(30)} {item} {new(30)}", f"{item}", None, ""]
    rows = [(k, t, "en", ["a", "a", "b", "c", None][k % 5], 0) for k, t in enumerate(texts)]
    spark.createDataFrame(rows, DOCS).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")

    seen, cleaned = set(), []
    for t in texts:
        kept = []
        for line in (t or "").split("\n"):
            if not line.strip() or line not in seen:
                kept.append(line)
            seen.add(line)
        cleaned.append(None if t is None else "\n".join(kept))
    labels, _ = brute_components(cleaned, 5, 80, 100)
    left = [k for k in range(len(texts)) if labels[k] == k and item not in (cleaned[k] or "")]
    assert len(left) == 15

    words = {k: len((cleaned[k] or "").split()) for k in left}
    order = sorted({rows[k][3] for k in left}, key=lambda s: (s is None, s or ""))
    size = {s: sum(words[k] for k in left if rows[k][3] == s) for s in order}
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    capped = set()
    while True:
        level = (sum(size.values()) - sum(3 * size[s] for s in capped)) / sum(weight[s] for s in order if s not in capped)
        over = {s for s in order if 3 * size[s] < level * weight[s]} - capped
        if not over:
            break
        capped |= over
    want = {}
    for k in left:
        s = rows[k][3]
        rate = round(min(3 * size[s], level * weight[s]), 6) / size[s]
        draw = int(hashlib.md5(f"7:{k}".encode()).hexdigest()[:13], 16) / 2**52
        want[k] = int(rate) + (draw < rate - int(rate))
    got = {}
    for r in corpus_pipeline.run(spark, str(tmp_path)).collect():
        assert r.text == cleaned[r.doc_id] and (r.text is None or r.n_chars == len(r.text))
        got[r.doc_id] = got.get(r.doc_id, 0) + 1
    assert got == {k: n for k, n in want.items() if n}
