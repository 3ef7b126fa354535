"""Corpus operators that count over the whole input."""

import math
import random
from collections import Counter

import numpy as np
import pytest

from colsketch.llm import lm, quality, registry


def brute_scores(texts, order, alpha=0.4):
    words = {i: (t or "").split() for i, t in texts.items()}
    grams = {i: Counter(tuple(w[k : k + m]) for m in range(1, order + 1) for k in range(len(w) - m + 1)) for i, w in words.items()}
    every, n, out = sum(grams.values(), Counter()), sum(map(len, words.values())), {}
    for i, w in words.items():
        c, total = every - grams[i], 0.0
        for k in range(len(w)):
            s = alpha ** (order - 1) * max(c[(w[k],)], 1) / n
            for m in range(2, min(order, k + 1) + 1):
                gram = tuple(w[k - m + 1 : k + 1])
                s = alpha ** (order - m) * c[gram] / max(c[gram[:-1]], c[gram]) if c[gram] else s
            total += math.log10(s)
        out[i] = total / max(len(w), 1)
    return out


def test_lm_scores_of_order_three(spark):
    texts = {1: "a b c d a b", 2: "a b c e", 3: "x b c d a b d", 4: None, 5: "a", 6: "q q q q"}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    for order in (1, 2, 3, 4):
        got = {r.doc_id: r.score for r in lm.backoff_scores(df, group_bytes=8, order=order).collect()}
        assert got == pytest.approx(brute_scores(texts, order))


def test_op8_uses_trigrams(spark, tmp_path):
    texts = {1: "a b c d a b", 2: "a b c e", 3: "x b c d a b d"}
    spark.createDataFrame(list(texts.items()), "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    assert {r.doc_id: r.score for r in registry.op8_lm_scoring(spark, str(tmp_path)).collect()} == pytest.approx(brute_scores(texts, 3))


def test_op10_counts_all_trusted_texts(spark, tmp_path, monkeypatch):
    spark.createDataFrame([(i, f"w{i} same") for i in range(40)], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(i, int(i < 30)) for i in range(40)] + [(0, 0), (99, 1), (None, 1)], "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    counted = []
    monkeypatch.setattr(quality, "MAX_LABELLED", 5)
    whole = quality.multinomial
    monkeypatch.setattr(quality, "multinomial", lambda texts, buckets: counted.append(sorted(r.text for r in texts.select("text").collect())) or whole(texts, buckets))
    assert registry.op10_quality_rules(spark, str(tmp_path)).count() == 40
    assert counted[1] == sorted(f"w{i} same" for i in range(30))


def test_op10_threshold_of_all_labelled_texts(spark, tmp_path, monkeypatch):
    r = random.Random(7)
    texts = {i: " ".join(f"{'g' if r.random() < (0.8 if i % 2 else 0.35) else 'b'}{r.randrange(30)}" for _ in range(r.choice([5, 20, 40]))) for i in range(120)}
    spark.createDataFrame(list(texts.items()), "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(i, i % 2) for i in range(100)] + [(3, None), (500, 1)], "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    monkeypatch.setattr(quality, "MAX_LABELLED", 5)
    seen, whole = [], quality.quality
    monkeypatch.setattr(quality, "quality", lambda docs, selector: seen.append(selector) or whole(docs, selector))
    rows = {x.doc_id: x for x in registry.op10_quality_rules(spark, str(tmp_path)).collect()}
    score = {x.doc_id: x.score for x in whole(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), seen[0]).collect()}
    good, bad = (sorted(score[i] for i in range(100) if i % 2 == k and rows[i].n_words >= 20) for k in (1, 0))
    assert len(good) > 20 and len(bad) > 20
    assert seen[0].threshold == pytest.approx(good[0])  # 0.2 % of so few is none
    for lost in (0.1, 0.5):
        scores = spark.createDataFrame([(1, x) for x in good] + [(0, x) for x in bad] + [(0, good[2]), (1, good[2])], "label long, score double")
        more, less = sorted([*good, good[2]]), [*bad, good[2]]
        cuts = more[: int(lost * len(more)) + 1]
        errors = [sum(x < c for x in more) / len(more) + sum(x >= c for x in less) / len(less) for c in cuts]
        assert quality.threshold(scores, lost) == cuts[errors.index(min(errors))]


def test_lm_scores_of_many_random_texts(spark):
    r = random.Random(4)
    texts = {i: " ".join(f"w{min(r.randrange(1, 60), r.randrange(1, 60))}" for _ in range(r.choice([0, 1, 2, 7, 40, 90]))) for i in range(150)}
    texts |= {200: None, 201: "", 202: texts[3], 203: "hot " * 700, 204: "w1 w2 w3 " * 400}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(5, "doc_id")
    for order, group in ((2, 1_000), (3, 300), (3, 8_000_000)):
        got = {r.doc_id: r.score for r in lm.backoff_scores(df, group, order).collect()}
        assert got == pytest.approx(brute_scores(texts, order))
    counts = sorted(r.n for r in lm.count_table(df, 700, 3).collect())
    words = [(t or "").split() for t in texts.values()]
    assert counts == sorted(Counter(tuple(w[k : k + m]) for w in words for m in (1, 2, 3) for k in range(len(w) - m + 1)).values())


def test_lm_packing():
    r = np.random.default_rng(2)
    for n in (0, 1, 9, 4000):
        keys = np.unique(r.integers(0, 1 << 54, n, dtype=np.uint64))
        assert (lm.unpack_keys(lm.pack_keys(keys), len(keys)) == keys).all()
        counts = r.choice([1, 1, 2, 254, 255, 256, 1 << 40], len(keys))
        assert (lm.unpack_counts(lm.pack_counts(counts), len(keys)) == counts).all()


def test_lm_rows_are_linear(spark):
    """Rows between groups and buckets never outnumber n-grams, however many groups there are."""
    df = spark.createDataFrame([(i, f"a{i} b{i}") for i in range(300)], "doc_id long, text string").repartition(2)
    _, asked, words = lm._grouped(df, 20, 2)
    rows = asked.select("grp", "bucket", "n").collect()
    assert words == 600 and len(rows) <= sum(r.n for r in rows) == 900 and len({r.grp for r in rows}) > 100
