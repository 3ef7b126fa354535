"""Benchmark decontamination with a positional inverted index, in DataFrame operations only.

The index has a row for each place at which a term of the test items occurs in the corpus, (term, doc_id, pos), and one
for each document with its number of words. A test window's occurrences come from the postings of its rarest terms
first: their lists, shifted by the terms' offsets in the window, are intersected, and what is left is confirmed on the
postings of all its words. Phrases are exact; `proximity` finds terms within a distance of each other.

Words are runs of ASCII letters and digits and of characters outside ASCII, with A-Z lower-cased. Nulls and empty texts
have no words and neither hit nor contain anything. Repeated item rows are one item (by item_id); rows of documents
with one doc_id are counted together where their words are hit, so doc_id should be a key. A null doc_id hits nothing.
Terms that are equally rare are taken in the order of their place. Very long texts are rows of postings like others; empty
tables of documents or items give no rows or no hits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, stored

_SEPARATORS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
#: Windows whose distinct words exceed this many rows are joined by shuffle instead of broadcast.
BROADCAST_ROWS = 200_000
#: Rarest terms that are intersected before a window is confirmed in full.
RAREST = 3


def lowered(word: Column) -> Column:
    """A-Z to a-z; lower() alone would change letters outside ASCII."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.when(F.octet_length(word) == F.length(word), F.lower(word)).otherwise(F.translate(word, upper, upper.lower()))


def pieces(text: Column) -> Column:
    """Words in order, with an empty string before the first or after the last where separators stand there."""
    return F.split(F.coalesce(text, F.lit("")), _SEPARATORS)


def n_words(text: Column) -> Column:
    p = pieces(text)
    return (F.size(p) - (F.get(p, F.lit(0)) == "").cast("int") - ((F.size(p) > 1) & (F.element_at(p, -1) == "")).cast("int")).cast("long")


def windows(items: DataFrame, width: int) -> DataFrame:
    """(item_id, start, words): each window of `width` words; a shorter item, not without words, is one."""
    words = items.select("item_id", F.transform(F.filter(pieces(F.col("text")), lambda w: w != ""), lowered).alias("words")).where("size(words) > 0").distinct()
    at = F.sequence(F.lit(1), F.greatest(F.size("words") - width + 1, F.lit(1)))
    return words.select("item_id", "words", F.explode(at).alias("start")).select("item_id", "start", F.slice("words", F.col("start"), width).alias("words"))


def _small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def in_docs(rows: DataFrame, found: DataFrame, bits: int = 1 << 23) -> DataFrame:
    """Rows whose hashed doc_id is set in a bit map of those in found, a broadcast of bits / 64 rows at most.

    It lets some others pass, which the join that follows drops; it spares moving the postings of all documents.
    """
    place = f"pmod(xxhash64(doc_id), {bits}L)"
    words = found.selectExpr(f"shiftright({place}, 6) as word", f"shiftleft(1L, cast({place} & 63 as int)) as bit").groupBy("word").agg(F.bit_or("bit").alias("mask"))
    hashed = rows.withColumn("word", F.expr(f"shiftright({place}, 6)")).withColumn("at", F.expr(f"cast({place} & 63 as int)"))
    return hashed.join(F.broadcast(words), "word").where("(shiftrightunsigned(mask, at) & 1) = 1").select(*rows.columns)


class Index:
    """Postings of `terms` (term, term_id) in docs, and the documents' lengths."""

    def __init__(self, docs: DataFrame, terms: DataFrame):
        n = terms.count()
        texts = docs.select("doc_id", "text")
        words = texts.select("doc_id", F.posexplode(pieces(F.col("text"))).alias("pos", "w")).where("w != ''").select("doc_id", "pos", lowered(F.col("w")).alias("term"))
        self.postings = stored(words.join(_small(terms, n), "term").select("term_id", "doc_id", "pos"))
        self.terms = n

    def frequencies(self) -> DataFrame:
        return self.postings.groupBy("term_id").agg(F.count("*").alias("df"))

    def phrases(self, phrases: DataFrame, rarest: int = RAREST) -> DataFrame:
        """phrases (phrase_id, term_ids): (phrase_id, doc_id, start, width) of each place where all terms stand in order."""
        terms = phrases.select("phrase_id", F.size("term_ids").alias("width"), F.posexplode("term_ids").alias("offset", "term_id"))
        ranked = terms.join(F.broadcast(cut(self.frequencies())) if self.terms <= BROADCAST_ROWS else self.frequencies(), "term_id", "left").na.fill(0, ["df"])
        ranked = cut(ranked.selectExpr("*", "row_number() over (partition by phrase_id order by df, offset) as place"))
        rows = ranked.count()
        found = None
        for place in range(1, rarest + 1):
            some = ranked.where(F.col("place") == place).select("phrase_id", "offset", "term_id", "width")
            lists = self.postings.join(_small(some, rows), "term_id").select("phrase_id", "doc_id", (F.col("pos") - F.col("offset")).alias("start"), "width")
            if found is None:
                found = lists
            else:  # a phrase with fewer terms than that has been intersected in full
                short = found.where(F.col("width") < place)
                found = found.where(F.col("width") >= place).join(lists.drop("width"), ["phrase_id", "doc_id", "start"]).unionByName(short)
        found = stored(found.distinct())
        # What is left: every word of the phrase must stand at its place.
        wanted = found.join(_small(terms.drop("width"), rows), "phrase_id").select("phrase_id", "doc_id", "start", "width", (F.col("start") + F.col("offset")).alias("pos"), "term_id")
        near = in_docs(self.postings, found)
        return wanted.join(near, ["doc_id", "pos", "term_id"]).groupBy("phrase_id", "doc_id", "start", "width").agg(F.countDistinct("pos").alias("n")).where("n = width").drop("n")

    def proximity(self, pairs: DataFrame, distance: int) -> DataFrame:
        """pairs (pair_id, first_id, second_id): (pair_id, doc_id, first_pos, second_pos) at most `distance` words apart, in either order.

        Places meet in cells of `distance` words, in their own and the two next to it.
        """
        p = self.postings
        one = p.join(_small(pairs, self.terms), p.term_id == pairs.first_id).select("pair_id", "doc_id", F.col("pos").alias("first_pos"), F.explode(F.array(*[F.floor(F.col("pos") / distance) + k for k in (-1, 0, 1)])).alias("cell"))
        two = p.join(_small(pairs, self.terms), p.term_id == pairs.second_id).select("pair_id", "doc_id", F.col("pos").alias("second_pos"), F.floor(F.col("pos") / distance).alias("cell"))
        near = one.join(two, ["pair_id", "doc_id", "cell"]).where(F.abs(F.col("first_pos") - F.col("second_pos")) <= distance)
        return near.where("first_pos != second_pos").select("pair_id", "doc_id", "first_pos", "second_pos")


def test_terms(wins: DataFrame) -> DataFrame:
    """(term, term_id): the words of the windows, numbered."""
    return cut(wins.select(F.explode("words").alias("term")).distinct().selectExpr("term", "cast(row_number() over (order by term) as int) as term_id"))


def occurrences(docs: DataFrame, items: DataFrame, width: int = 13) -> DataFrame:
    """(doc_id, item_id, start, width) of each window of an item in a document; start counts pieces of the text."""
    wins = cut(windows(items, width))
    terms = test_terms(wins)
    spelled = wins.groupBy("words").agg(F.collect_set("item_id").alias("items")).select("words", "items", F.xxhash64("words").alias("phrase_id"))
    spelled = cut(spelled)
    numbered = spelled.select("phrase_id", F.posexplode("words").alias("at", "term")).join(terms, "term").groupBy("phrase_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "term_id"))), lambda x: x["term_id"]).alias("term_ids"))
    numbered = cut(numbered)
    hits = Index(docs, terms).phrases(numbered)
    return hits.join(_small(spelled.select("phrase_id", "items"), spelled.count()), "phrase_id").select("doc_id", F.explode("items").alias("item_id"), "start", "width")


def covered_words(spans: Column) -> Column:
    """Places inside a sorted array of structs (start, width)."""
    start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(-1).cast("long").alias("end"))

    def step(acc, x):
        end = x["start"].cast("long") + x["width"]
        return F.struct((acc["n"] + F.greatest(end - F.greatest(acc["end"], x["start"].cast("long")), F.lit(0))).alias("n"), F.greatest(acc["end"], end).alias("end"))

    return F.aggregate(spans, start, step, lambda acc: acc["n"])


def contamination(docs: DataFrame, items: DataFrame, width: int = 13, share: int = 20) -> DataFrame:
    """(doc_id, n_words, n_hit, item_ids, contaminated) for each row; contaminated: n_hit > 0 and share * n_hit >= n_words."""
    hits = occurrences(docs, items, width).groupBy("doc_id").agg(covered_words(F.array_sort(F.collect_set(F.struct("start", "width")))).alias("n_hit"), F.collect_set(F.col("item_id").cast("string")).alias("item_ids"))
    sized = docs.select("doc_id", n_words(F.col("text")).alias("n_words"))
    out = sized.join(hits, "doc_id", "left").select("doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).alias("n_hit"), F.array_sort(F.coalesce("item_ids", F.array().cast("array<string>"))).alias("item_ids"))
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (share * F.col("n_hit") >= F.col("n_words")))
