"""Operators that learn: held-out accuracy on the given tables, and awkward rows."""

import random

import pytest
from brute import article
from conftest import DATA
from test_exact import AWKWARD, awkward

from colsketch.llm import extraction, language, lm, registry, toxicity
from colsketch.llm.common import table

SF = f"{DATA}/sf0.1"


def test_toxicity_held_out(spark):
    got = registry.op2_toxicity(spark, SF).where("held_out").join(table(spark, SF, "labels"), "doc_id")
    rows = got.select("toxic", "predicted").collect()
    assert sum(r.toxic == r.predicted for r in rows) / len(rows) > 0.95


def test_misspellings_and_quotes():
    model = toxicity.Model({"stupid": 5.0, "clown": 5.0}, {"lowei": 4.0})
    s = toxicity.Scorer(model)
    assert s.automaton.match("stupid") == ("stupid", 0) and s.automaton.match("stupd") == ("stupid", 1)
    assert s.automaton.match("sstupid") == ("stupid", 1) and s.automaton.match("stopid") == ("stupid", 1)
    assert s.automaton.match("stoped") is None and s.automaton.match("loweix") == ("lowei*", 0)
    bare, quoted = s.figures("you clown")[0], s.figures('they said "you clown" once')[0]
    assert bare[0] > 0 == bare[1] and quoted[1] > 0 == quoted[0]
    for text in ('a 6" pipe is here. you stupid clown. "ok', 'she said "hello" and then left. said you stupid', '"' + "x " * 40 + "clown " + "y " * 40 + '"'):
        assert s.figures(text)[0][1] == 0 < s.figures(text)[0][0]
    for text in ("„you clown“ sagte er", "il dit « you clown »", "“you clown,” he wrote", 'x "clown"'):
        assert s.figures(text)[0][0] == 0 < s.figures(text)[0][1]
    told = toxicity.Scorer(toxicity.Model({"clown": 5.0}, {}, report=frozenset(["reportedly"])))
    assert told.figures("reportedly a clown")[0][:3] == [0.0, 0.0, pytest.approx(1.791759469)]


def test_automaton_against_plain_distance():
    def apart(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            row, old = [i], row
            for j, y in enumerate(b, 1):
                row.append(min(old[j] + 1, row[-1] + 1, old[j - 1] + (x != y)))
        return row[-1]

    r = random.Random(1)
    terms = sorted({"".join(r.choices("abc", k=r.randrange(3, 8))) for _ in range(30)})
    automaton = toxicity.Automaton(dict.fromkeys(terms, 1.0), {})
    for _ in range(4000):
        word = "".join(r.choices("abc", k=r.randrange(1, 9)))
        found = [(apart(word, t), t) for t in terms if word == t or (len(t) >= 5 and apart(word, t) <= 1)]
        best = automaton.match(word)
        assert best == ((min(found)[1], min(found)[0]) if found else None)


def test_report_words_are_learned(spark):
    rows = [(f"you clown number{i} go home", 1) for i in range(12)] + [(f"historians note the word clown{i % 3} as an insult", 0) for i in range(9)] + [("historians note that clown is an insult", 0)] * 6 + [(f"plain text {i}", 0) for i in range(200)]
    model = toxicity.fit(spark.createDataFrame(rows, "text string, label int"), odds=2.0)
    assert "clown" in model.words and "historians" in model.report and "you" not in model.report
    scores = {r.doc_id: r.score for r in toxicity.toxicity(spark.createDataFrame([(1, "you clown go home"), (2, "historians note that clown is an insult")], "doc_id long, text string"), model).collect()}
    assert scores[1] > scores[2]
    assert toxicity.fit(spark.createDataFrame([], "text string, label int")).words == {}


def test_all_segmentations_count():
    """The recursion against a sum over every way to cut a word into pieces."""
    import numpy as np

    table = language.pieces(language.default_vocabulary())
    assert table.longest > 10
    number = {p: k for k, p in enumerate(table.pieces)}
    rng = np.random.default_rng(0)
    p = rng.random((table.n, 2)) + 0.1
    p /= p.sum(axis=0)
    texts = ["the government", "использование", "internationale Verständigung ß", "a", "", "x" * 700]
    model = language.Model(language.default_vocabulary(), ["a", "b"], p)

    def whole(word):
        sums = [np.ones(2)] + [np.zeros(2) for _ in word]
        for end in range(1, len(word) + 1):
            for start in range(max(0, end - table.longest), end):
                k = number.get(word[start:end])
                if k is not None:
                    sums[end] = sums[end] + sums[start] * p[k]
        return np.log(sums[-1])

    import pyarrow as pa

    from colsketch.llm.kernels import blocks

    for _, _, block in blocks(pa.array(texts), language.LETTERS, lower=True):
        got = model.log_likelihoods(block, model.scaled())
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    for text, row in zip(texts, got, strict=True):
        want = np.zeros(2)
        for word in text.translate(lower).split():
            data = word.encode()
            for a in range(0, len(data), language.LONGEST_WORD):
                want += whole(b" " + data[a : a + language.LONGEST_WORD])
        assert np.allclose(row, want)


def test_rare_languages_are_learned(spark):
    from pyspark.sql import functions as F

    from colsketch.llm.common import sample_of_each

    df = spark.createDataFrame([(i, "some text", "en") for i in range(3000)] + [(5000 + i, "autre texte", "fr") for i in range(3)] + [(None, "x", "de"), (7, "y", None)], "doc_id long, text string, lang string")
    got = {r.label: r["count"] for r in sample_of_each(df, "lang", F.lit(True), 100).groupBy("label").count().collect()}
    assert got["fr"] == 3 and 20 < got["en"] < 90 and set(got) == {"en", "fr"}


def test_language_held_out(spark):
    docs = table(spark, f"{DATA}/sf0.01", "documents")
    rows = registry.op9_language_id(spark, f"{DATA}/sf0.01").where("held_out").join(docs, "doc_id").collect()
    assert sum(r.lang == r.lang_pred for r in rows) / len(rows) > 0.95


def test_awkward_rows(spark):
    df, texts = awkward(spark)
    model = language.fit(df.selectExpr("text", "lang as label"))
    got = {r.doc_id: r for r in language.identify(df, model).collect()}
    assert got[0].lang_pred == got[1].lang_pred == "und" and len(got) == len(texts)
    assert {r.doc_id for r in lm.backoff_scores(df).collect()} == set(texts)
    assert toxicity.toxicity(df, toxicity.Model()).where("score = 0").count() == len(texts)
    empty = spark.createDataFrame([], AWKWARD)
    assert lm.backoff_scores(empty).count() == language.identify(empty, None).count() == 0


def test_backoff_scores(spark):
    import math

    docs = spark.createDataFrame([(1, "a b c"), (2, "a b d"), (3, None)], "doc_id long, text string")
    got = {r.doc_id: r.score for r in lm.backoff_scores(docs).collect()}
    # Of the other text: c(a) = 1, c(a b) = 1, c(b) = 1; "c" is unseen and counts once.
    first = math.log10(0.4 * 1 / 6) + math.log10(1 / 1) + math.log10(0.4 * 1 / 6)
    assert got[1] == pytest.approx(first / 3) and got[1] == pytest.approx(got[2]) and got[3] == 0


def test_pages(spark):
    article = "<nav><a>Home</a></nav><div class='ad'>Buy</div><article><h1>T &amp; x</h1><p>One  two<br><p>three <b>four</b></article><footer>f</footer>"
    assert extraction.main_text(f"<html><body>{article}", set()) == "T & x\nOne two\nthree four"
    assert extraction.main_text(None, set()) == extraction.main_text("", set()) == ""
    pages = [(i, "http://h.org/x", f"<html><body><div>Menu of all</div><div>Body {i} text</div><script>x</script></body></html>") for i in range(6)]
    df = spark.createDataFrame([*pages, (9, None, None)], "page_id long, url string, html string")
    got = {r.page_id: r.text for r in extraction.extract(df).collect()}
    assert got == {**{i: f"Body {i} text" for i in range(6)}, 9: ""}


def test_pages_against_articles(spark):
    pages = {r.page_id: r.html for r in table(spark, SF, "pages").collect()}
    got = {r.page_id: r.text for r in registry.op7_html_extraction(spark, SF).collect()}
    assert got == {i: article(h) for i, h in pages.items()}


def test_template_chooses_the_slot(spark):
    def page(i, body):
        return f"<html><body><div class='top'><p>Menu {i % 7}</p></div><div class='page'><h1>Head {i}</h1><div class='text'>{body}</div></div><div class='end'>Seen {i} times</div></body></html>"

    body = [f"<p>{'word %d ' % i * 9}</p><p>Same in all</p><ul><li>{i}.5</li></ul>" for i in range(8)]
    rows = [(i, "http://a.org/%d" % i, page(i, body[i])) for i in range(8)] + [(20, "http://once.org", page(20, "<p>The only page of its host, long enough</p>")), (21, "http://a.org", "<p>no slot</p>"), (22, "http://a.org", "")]
    rows += [(30 + k, "http://same.org", page(1, body[1])) for k in range(4)] + [(30, "http://same.org", page(1, body[1]))]
    df = spark.createDataFrame([(*r, 0) for r in rows], "page_id long, url string, html string, text int")
    got = {r.page_id: r.text for r in extraction.extract(df).collect()}
    for i in range(8):
        assert got[i] == f"Head {i}\n{('word %d ' % i * 9).strip()}\n{i}.5"
    assert got[20] == "Head 20\nThe only page of its host, long enough" and got[21] == "no slot" and got[22] == ""
    assert got[30] == got[33] == f"Head 1\n{('word 1 ' * 9).strip()}\nSame in all\n1.5"
    tokens = {(r.host, r.token) for r in extraction.templates(df).collect()}
    assert ("a.org", "html/body/div.page/div.text/p\n=Same in all") in tokens and not any(h == "once.org" for h, _ in tokens)


def test_classes_decide_what_is_template(spark, monkeypatch):
    """Notes on the same pages are one class and left out; a note with a vector of its own is kept, and so is one in no order."""

    def page(i):
        note = "<p>First fixed note</p><p>Second fixed note</p>" if i % 3 else ""
        alone = "<p>Note of its own</p>" if i % 4 else ""
        swapped = ("<p>One side</p>", "<p>Other side</p>")
        turned = "".join(swapped if i % 2 else swapped[::-1]) if i != 5 else ""
        return f"<html><body><div class='x'><h1>Title {i}</h1><p>{'varied %d ' % i * 12}</p>{note}{alone}{turned}</div></body></html>"

    rows = [(i, "http://c.org/%d" % i, page(i)) for i in range(12)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    for bound in (50_000, 0):
        monkeypatch.setattr(extraction, "BROADCAST_TOKENS", bound)
        got = {r.page_id: r.text for r in extraction.extract(df).collect()}
        for i in range(12):
            want = [f"Title {i}", ("varied %d " % i * 12).strip(), *(["Note of its own"] if i % 4 else [])]
            sides = ["One side", "Other side"] if i % 2 else ["Other side", "One side"]
            assert got[i] == "\n".join(want + (sides if i != 5 else []))
    by = {}
    for r in extraction.classes(extraction.token_sums(df)).collect():
        by.setdefault((r.host, r.class_id), set()).add(r.token.partition("\n=")[2])
    assert any({"First fixed note", "Second fixed note"} <= x for x in by.values()) and not any("Note of its own" in x for x in by.values())


def test_orders_and_nesting():
    table = {"a": (1, 2), "z": (1, 2), "b": (2, 2), "y": (2, 2), "c": (3, 3), "d": (3, 3), "e": (3, 3)}
    good = extraction.orders(list("abybyz"), table)
    assert good[1] == (True, "a\nz", (0, 0)) and good[2] == (True, "b\ny", (1, 1))
    assert extraction.orders(list("abzy"), table)[1][0] != extraction.orders(list("abzy"), table)[2][0]
    assert not extraction.orders(list("byyb"), table)[2][0]
    assert not extraction.orders(list("abyzby"), table)[2][0]  # in two slots
    crossing = extraction.orders(list("cbdye"), table)
    assert crossing[3][0] and not crossing[2][0]
    assert extraction.orders(list("cd"), table)[3][0] is False


def test_markup_that_is_awkward():
    def text(page):
        return extraction.main_text(page, set())

    assert text("<p>Hello <button>Click me</button> world</p>") == "Hello world"
    assert text("<p>Pick <select><option>one<option>two</select> now <span class='ad'>buy</span>end</p>") == "Pick now end"
    assert text('<p class=x">Hello</p><p class="y">World</p>') == "Hello\nWorld"
    assert text("<p title='a > b'>in</p><p data-x=\"1\"class='k'>out</p>") == "in\nout"
    assert text("<article><div class='social-policy'>Policy text</div><div class='share-prices'>Prices</div><div class='share-buttons'>Like</div></article>") == "Policy text\nPrices"
    assert text("<div class='user-comments'><p>me too</p></div><p>a &lt; b</p>") == "a < b"
    assert text("<p>a<b>b</b><i class='sponsored'>x<u>y</u></i>c") == "abc"
    assert text("<scripty>kept</scripty><script>no</script >yes") == "keptyes"


def test_quality_keeps_trusted(spark):
    docs = table(spark, SF, "documents")
    rows = registry.op10_quality_rules(spark, SF).join(table(spark, SF, "labels"), "doc_id").where("not base_failed").collect()
    good = [r.kept for r in rows if r.quality == 1]
    bad = [r.kept for r in rows if r.quality == 0]
    assert docs.count() == 10_000 and sum(good) / len(good) > 0.98 and sum(bad) / len(bad) < 0.5
