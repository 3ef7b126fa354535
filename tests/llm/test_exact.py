"""Operators with an exact contract, against plain Python on the given tables and on awkward rows."""

import random

import brute
import corpus_pipeline
import pytest
from conftest import DATA

from colsketch.llm import contamination, mixing, near, quality, registry, sharding, substrings
from colsketch.llm.common import table

SF = f"{DATA}/sf0.01"
AWKWARD = "doc_id long, text string, lang string, source string, n_chars long, label string, a string, key string"


def awkward(spark):
    long = " ".join(f"w{i % 977}x{i}" for i in range(30_000))
    base = " ".join(f"b{i}" for i in range(60))
    texts = [None, "", " \t\n", "one", "one", "One", "a b c d", "a b c d", base, base, base + " tail", base.replace("b7 ", "z "), "x " * 50, long, long + " end", "É é\x0bÀ " * 9, "tab\tnewline\nvt\x0bff\x0ccr\r" * 5, "##$ <> | ok\n##$ <> | ok\n\n\n##$ <> | ok", base + " " + base, "été" * 7]
    rows = [(i, t, "en", None if i % 5 == 0 else f"s{i % 3}", None, None, "a", "k") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, AWKWARD), {r[0]: r[1] for r in rows}


def mutated(spark, n=260, seed=3):
    """Groups of near copies with a passage that most texts share."""
    r = random.Random(seed)
    vocabulary = [f"v{i}" for i in range(4000)]
    passage = " ".join(r.choices(vocabulary, k=45))
    texts, base = {}, []
    for i in range(n):
        if i % 13 == 0 or not base:
            base = r.choices(vocabulary, k=r.choice([4, 7, 9, 15, 30, 60, 120, 400]))
        words = list(base)
        for _ in range(r.randrange(0, 1 + len(words) // 25)):
            words[r.randrange(len(words))] = r.choice(vocabulary)
        texts[i] = " ".join(words) + (" " + passage if i % 3 else "")
    return spark.createDataFrame([(i, t) for i, t in texts.items()], "doc_id long, text string"), texts


def whole(spark, name="documents"):
    df = table(spark, SF, name)
    key = "doc_id" if name == "documents" else "item_id"
    return df, {r[0]: r[1] for r in df.select(key, "text").collect()}


@pytest.mark.parametrize("make", [whole, awkward, mutated])
def test_near(spark, make):
    df, texts = make(spark)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near.near_duplicates(df).collect()}
    assert got == brute.near(texts)


def test_near_with_common_blocks(spark, monkeypatch):
    """Common blocks and their slack come into play at small sizes, too."""
    df, texts = mutated(spark, 500, 9)
    monkeypatch.setattr(near, "COMMON", 3)
    monkeypatch.setattr(near, "CELL", 5)
    monkeypatch.setattr(near, "CHUNK", 2000)
    monkeypatch.setattr(near, "OFTEN", 2)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near.near_duplicates(df).collect()}
    assert got == brute.near(texts)


@pytest.mark.parametrize("make", [whole, awkward, mutated])
@pytest.mark.parametrize("base", [10, 5])
def test_substrings(spark, make, base, monkeypatch):
    df, texts = make(spark)
    if base == 5:
        monkeypatch.setattr(substrings, "CHUNK_ROWS", 500)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_text) for r in substrings.remove_repeats(df, base=base, digest=True).collect()}
    assert got == brute.without_repeats(texts)


@pytest.mark.parametrize("make", [whole, awkward])
def test_contamination(spark, make):
    df, texts = make(spark)
    items, plain = whole(spark, "benchmark")
    if make is awkward:
        plain = {1: "one", 2: " ".join(f"b{i}" for i in range(3, 30)), 3: None, 4: "", 5: "É é À É", 6: "a-B c", 7: "b5 b6 b7", 30: "b5 b6 b7"}
        items = spark.createDataFrame(list(plain.items()), "item_id long, text string")
    else:
        items = items.unionByName(items.limit(3))
    rows = contamination.contamination(df, items).selectExpr("doc_id", "n_words", "n_hit", "size(item_ids)", "sha2(array_join(item_ids, ','), 256)", "contaminated").collect()
    assert {r[0]: tuple(r)[1:] for r in rows} == brute.contaminated(texts, plain)


def test_proximity(spark):
    docs = spark.createDataFrame([(1, "alpha x y beta"), (2, "beta alpha"), (3, "alpha " + "z " * 9 + "beta"), (4, None)], "doc_id long, text string")
    terms = spark.createDataFrame([("alpha", 1), ("beta", 2)], "term string, term_id int")
    pairs = spark.createDataFrame([(7, 1, 2)], "pair_id int, first_id int, second_id int")
    got = contamination.Index(docs, terms).proximity(pairs, 3).select("doc_id", "first_pos", "second_pos").collect()
    assert sorted(map(tuple, got)) == [(1, 0, 3), (2, 1, 0)]


@pytest.mark.parametrize("make", [whole, awkward])
def test_quality_figures(spark, make):
    df, texts = make(spark)
    got = {r.doc_id: (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in quality.quality(df).collect()}
    assert got == {i: brute.figures(t) for i, t in texts.items()}


def test_mixing(spark):
    df, texts = whole(spark)
    rows = mixing.mix(df).collect()
    by = {}
    for r in rows:
        assert r["size"] == len(brute.WORDS.findall(texts[r.doc_id])) and 0 <= r.taken <= 3 * r["size"]
        s = by.setdefault(r.source, [0, 0, r.target, r.source_size])
        s[0] += r["size"]
        s[1] += r.taken
    assert all(n == size and taken == int(target) <= 3 * n for n, taken, target, size in by.values())
    assert abs(sum(s[2] for s in by.values()) - sum(s[0] for s in by.values())) < 1e-3
    again = {tuple(r) for r in mixing.mix(df.repartition(5)).collect()}
    assert again == {tuple(r) for r in rows}


@pytest.mark.parametrize("sizes", [[100, 1, 50, 0, 7], [5], [0, 0], [1, 1, 1000, 3, 2, 900], [10**9, 1, 2, 3]])
def test_mixture_targets(spark, sizes):
    weights = [(5, 2, 1)[i % 3] for i in range(len(sizes))]
    df = spark.createDataFrame([(i, n, w) for i, (n, w) in enumerate(zip(sizes, weights, strict=True))], "i int, n long, weight long")
    got, total = [r.target for r in mixing.targets(df).orderBy("i").collect()], sum(sizes)
    want, capped = [0.0] * len(sizes), set()
    while len(capped) < len(sizes):  # reshare until none is above
        left = total - sum(3 * sizes[i] for i in capped)
        w = sum(weights[i] for i in range(len(sizes)) if i not in capped)
        want = [3.0 * sizes[i] if i in capped else left * weights[i] / w for i in range(len(sizes))]
        above = {i for i in range(len(sizes)) if want[i] > 3 * sizes[i]}
        if not above:
            break
        capped |= above
    assert got == pytest.approx(want)


def test_clashing_columns(spark):
    """Columns that operators use inside, or that differ in case alone, pass through."""
    names = ["whole", "Top", "copy_", "cut_key", "cut_id", "CUT_SOURCE", "copy_of_other", "found_id", "part", "n", "key", "size", "at"]
    base = " ".join(f"b{i}" for i in range(40))
    rows = [(i, base if i % 2 else f"text {i} " * 9, f"s{i % 3}" if i % 4 else None, *["x"] * len(names)) for i in range(24)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, " + ", ".join(f"{n} string" for n in names))
    out = mixing.mixed_rows(df)
    assert out.columns == df.columns and out.count() > 0
    for stage in (corpus_pipeline.drop_near_copies, corpus_pipeline.drop_contaminated, corpus_pipeline.drop_toxic, corpus_pipeline.mix_sources):
        assert stage(spark, df, SF).columns == df.columns
    assert corpus_pipeline.drop_near_copies(spark, df, SF).count() == 13


def test_mixed_rows(spark):
    df, _ = awkward(spark)
    plan = {r.doc_id: r.copies for r in mixing.mix(df).collect()}
    out = mixing.mixed_rows(df)
    assert out.columns == df.columns
    got = {}
    for r in out.collect():
        got[r.doc_id] = got.get(r.doc_id, 0) + 1
    empty = {r.doc_id for r in mixing.mix(df).where("size = 0").collect()}
    assert got == {i: n for i, n in {**plan, **dict.fromkeys(empty, 1)}.items() if n}


def test_sharding(spark):
    df, texts = whole(spark)
    limit = 60_000
    rows = sharding.shards(df, limit, step=2).collect()
    assert len(rows) == len(texts)
    by = {}
    for r in rows:
        assert r.bytes == len(texts[r.doc_id].encode()) and len(r.shard) == r.depth
        by.setdefault(r.shard, []).append(r)
    for shard, members in by.items():
        total = sum(r.bytes for r in members)
        assert total == members[0].shard_bytes <= limit
        if shard:  # the parent was too large
            assert sum(r.bytes for r in rows if r.shard.startswith(shard[:-1])) > limit
    one = spark.createDataFrame([(1, "x" * 100)] * 5 + [(2, None)], "doc_id long, text string")
    assert {(r.doc_id, r.oversize) for r in sharding.shards(one, 200).collect()} == {(1, True), (2, False)}


def test_empty_tables(spark):
    df = spark.createDataFrame([], AWKWARD)
    items = spark.createDataFrame([], "item_id long, text string")
    assert near.near_duplicates(df).count() == substrings.remove_repeats(df).count() == 0
    assert contamination.contamination(df, items).count() == quality.quality(df).count() == 0
    assert mixing.mix(df).count() == mixing.mixed_rows(df).count() == sharding.shards(df).count() == 0


def test_registry_names():
    assert {int(k[2:].split("_")[0]) for k in registry.queries() if k.startswith("op")} == set(range(1, 11))
