"""Main text of web pages by deduction of each host's page template from equivalence classes of tokens.

Tokens of a page are the starts and ends of its block elements, each with the element's path (names and classes from the
root, digits as 0), and its text blocks with their path. Tokens of a host that have the same occurrence vector (the count
on each page) are one class, if half of the host's pages have them, FEWEST at least, and the class LEAST members at least.
A class is valid if its members come in one order, as often as the class occurs, and if it nests: between two of its
members no other class opens without closing, and it always lies in the same slot of the class around it. Pages that
break a class may be a tenth of those that have it; of two classes that cross, the one with fewer members is broken.
The valid classes, nested, are the host's template: their elements bound the slots, and their texts are repeated ones.
A text whose vector is its own belongs to no class and is kept.

The main slot is found from the template alone: of its container elements, those in which more than half of the text lies
that differs between pages form a chain; the first article on it is the main slot, without one the deepest container that
still holds the heading. All blocks of a page inside the main slot are its text, but for those that the template repeats
if the slot is no article and has others. All hosts' elements together give a template, too; its main slot serves hosts of
fewer than FEWEST pages and pages without their host's slot. A page with neither gives all blocks that its host's template
does not repeat. Text in menus, headers, footers, sidebars, notices, adverts, forms, controls, scripts, styles or reader
comments, by element or by class names made of words for such parts alone, is left out of every slot.

Occurrence vectors are never gathered: a vector's signature is a sum of hashes of (page, count), so it is summed by task
first and then by host and token; the checks of a class are counts of its orders and slots. A null or empty page, and one
without text, gives an empty text; an empty table gives no rows. Pages without a host share the host ''. Repeated rows are
extracted each. Texts of any length can be tokens, long ones by their hash. Elements below DEEPEST levels share the path
above them. Ties of containers go to the outer one and then by path, ties of crossing classes to the one that came first.
"""

from __future__ import annotations

import hashlib
import html
import re
from collections.abc import Callable, Iterator
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

#: Attributes as browsers read them: a quote opens a value only after the equals sign.
_ATTRIBUTES = r"(?>[\s/]++|[^\s/>=\"'][^\s/>=]*+(?>\s*+=\s*+(?>\"[^\"]*+\"|'[^']*+'|[^\s>]*+))?+|[^>])*+"
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|textarea|iframe|svg|title)(?=[\s/>])" + _ATTRIBUTES + r">.*?(?:</\1(?=[\s/>])[^>]*>|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)(?![a-zA-Z0-9:-])(" + _ATTRIBUTES + ")>", re.S | re.I)
BLOCKS = frozenset("address article aside blockquote body br center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
DROPPED = frozenset("nav header footer aside form fieldset head button select option optgroup datalist label legend menu dialog".split())
CONTAINERS = frozenset("article main body div section table tbody tr td center".split())
ARTICLES, HEADINGS = frozenset(["article", "main"]), frozenset(["h1", "h2"])
#: Words that name parts around the article, and words that only say which or how such a part is built.
PARTS = frozenset("ad ads advert adverts advertisement advertising banner sponsor sponsored sponsors menu navbar nav navigation sidebar breadcrumb breadcrumbs comment comments replies notice notices cookie cookies consent popup modal newsletter subscribe share social related footer header promo promos".split())
BUILT = frozenset("the site page top main bottom left right list lists link links bar box boxes button buttons btn icon icons widget widgets section area container wrapper wrap inner outer item items block slot unit panel form signup posts stories media global primary secondary sub mobile desktop sticky fixed strip col column row count reply thread user users reader readers and wide small large big".split())
_ATTRIBUTE = re.compile(r"(?:^|[\s/\"'])(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
#: Digits, and what separates levels and tokens, are one character in labels.
_PLAIN = re.compile(r"[\d/\s]+")
#: Share of a host's pages that a token needs, the fewest pages, the fewest members of a class, and the share of the pages with a class that must keep its order and its slot.
SUPPORT, FEWEST, LEAST, KEPT = 0.5, 3, 2, 0.9
#: Texts up to this length stand in tokens as they are, longer ones by their hash.
PLAIN_TEXT = 80
#: Levels of block elements in a path.
DEEPEST = 24
#: The key under which all hosts' pages are taken together; no host name has this character.
EVERY = "*"
#: Templates are broadcast up to this many tokens; beyond that, pages are joined with them by host, in SALTS parts.
BROADCAST_TOKENS, SALTS = 50_000, 16
OPEN, CLOSE, TEXT = "", "/", "="


def host_of(url: str | None) -> str:
    try:
        return (urlsplit(url or "").hostname or "").lower()
    except ValueError:
        return ""


def names_a_part(names: str) -> bool:
    """Whether one of the class names is made of words for parts around the article, with words of building at most."""
    for name in names.lower().split():
        words = [w for w in re.split(r"[_\-\d]+", name) if w]
        if any(w in PARTS for w in words) and all(w in PARTS or w in BUILT for w in words):
            return True
    return False


def page_events(page: str) -> Iterator[tuple[str, str, bool, str]]:
    """(kind, path, dropped, text) of block starts, block ends and text blocks, in page order. A dropped inline element's
    text is in no block."""
    stack: list[tuple[str, str, int, bool, bool]] = [("", "", 0, False, False)]  # name; path, its levels and dropped, as inherited; whether the path is its own
    text: list[str] = []
    at, hidden = 0, 0  # hidden: dropped inline elements that are open

    def flush():
        joined = " ".join(html.unescape("".join(text)).split())
        text.clear()
        return joined

    def closed(k: int) -> Iterator[tuple[str, str, bool, str]]:
        nonlocal hidden
        while len(stack) > k:
            name, path, _, dropped, own = stack.pop()
            if own:
                yield CLOSE, path, dropped, ""
            hidden -= name not in BLOCKS and dropped and not stack[-1][3]

    for m in TOKEN.finditer(page):
        if m.start() > at and not hidden:
            text.append(page[at : m.start()])
        at = m.end()
        name = m[3]
        if not name:
            continue
        name = name.lower()
        if name in BLOCKS and text:
            block = flush()
            if block:
                yield TEXT, stack[-1][1], stack[-1][3], block
        if m[2]:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] == name:
                    yield from closed(k)
                    break
                if name not in ("article", "main", "body", "html") and stack[k][0] in ("article", "main", "body", "nav", "footer", "header", "aside", "form") and stack[k][0] != name:
                    break
        elif name not in VOID and not m[4].endswith("/"):
            if name == "p":  # a paragraph ends the one before it
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k][0] == "p":
                        yield from closed(k)
                        break
                    if stack[k][0] in BLOCKS:
                        break
            attributes = m[4]
            names = " ".join(x for a in _ATTRIBUTE.findall(attributes) for x in a if x) if "=" in attributes else ""
            _, path, levels, above, _ = stack[-1]
            dropped = above or name in DROPPED or bool(names and names_a_part(names))
            own = name in BLOCKS and levels < DEEPEST
            if own:
                label = f"{name}.{_PLAIN.sub('0', names)}" if names else name
                path, levels = f"{path}/{label}" if path else label, levels + 1
            stack.append((name, path, levels, dropped, own))
            hidden += name not in BLOCKS and dropped and not above
            if own:
                yield OPEN, path, dropped, ""
    if at < len(page) and not hidden:
        rest = page[at:]
        cut_at = rest.rfind("<")
        text.append(rest if cut_at < 0 or not re.match(r"</?[a-zA-Z]", rest[cut_at:]) else rest[:cut_at])
    block = flush()
    if block:
        yield TEXT, stack[-1][1], stack[-1][3], block
    yield from closed(1)


def token_of(kind: str, path: str, text: str) -> str:
    if kind == TEXT:
        text = text if len(text) <= PLAIN_TEXT else "#" + hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=12).hexdigest()
        return f"{path}\n={text}"
    return f"{path}\n{kind}"


def _signed(seed: int, n: int) -> int:
    x = ((seed + n) * 0x9E3779B97F4A7C15) & 0xFFFFFFFFFFFFFFFF
    x = ((x ^ (x >> 29)) * 0xBF58476D1CE4E5B9) & 0xFFFFFFFFFFFFFFFF
    return (x ^ (x >> 32)) & ((1 << 40) - 1)


def _vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Parts of (host, token, pages, occurrences, signature, chars), summed over the pages of the task.

    chars counts the text that is not left out, directly in a path or of a token with a text. Pages without tokens don't count.
    """
    total: dict[tuple[str, str], list] = {}

    def out():
        rows = [(h, t, *v) for (h, t), v in total.items()]
        cols = list(zip(*rows, strict=True)) if rows else [[], [], [], [], [], []]
        return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.string()), *(pa.array(c, pa.int64()) for c in cols[2:])], names=["host", "token", "pages", "n", "signature", "chars"])

    def add(host, token, n, signature, chars):
        v = total.setdefault((host, token), [0, 0, 0, 0])
        v[0] += 1
        v[1] += n
        v[2] = (v[2] + signature) & ((1 << 40) - 1)
        v[3] += chars

    for batch in batches:
        for page_id, url, page in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html")), strict=True):
            counts, chars = {"\n": 1, "\n/": 1}, {}  # the first two are the page itself
            for kind, path, dropped, block in page_events(page or ""):
                token = token_of(kind, path, block)
                counts[token] = counts.get(token, 0) + 1
                if block and not dropped:
                    chars[token] = chars.get(token, 0) + len(block)
                    chars[f"{path}\n"] = chars.get(f"{path}\n", 0) + len(block)
            if len(counts) == 2:
                continue
            host, seed = host_of(url), _signed((page_id if page_id is not None else -1) & ((1 << 64) - 1), 1)
            signatures = {n: _signed(seed << 20, n) for n in set(counts.values())}
            for token, n in counts.items():
                add(host, token, n, signatures[n], chars.get(token, 0))
                if "\n=" not in token:
                    add(EVERY, token, n, signatures[n], chars.get(token, 0))
        if len(total) > 300_000:
            yield out()
            total.clear()
    yield out()


def token_sums(pages: DataFrame) -> DataFrame:
    """(host, token, pages, n, signature, chars): the classes' keys of all tokens, for each host and for all hosts together."""
    parts = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html").mapInArrow(_vectors, "host string, token string, pages long, n long, signature long, chars long")
    return parts.groupBy("host", "token").agg(F.sum("pages").alias("pages"), F.sum("n").alias("n"), F.pmod(F.sum("signature"), F.lit(1 << 40)).alias("signature"), F.sum("chars").alias("chars"))


def _for_hosts(pages: DataFrame, rows: DataFrame, schema: str, kernel: Callable, columns: str) -> DataFrame:
    """kernel(batches, known, common) over pages, with the values of rows (host, value) that belong to each page's host.

    known holds all of them by host, up to BROADCAST_TOKENS tokens in all; None says that a page has its host's as a column.
    """
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html")
    every = rows.where(F.col("host") == EVERY).select("value").first()
    common = every.value if every is not None else None
    rows = rows.where(F.col("host") != EVERY)
    n = rows.agg(F.sum(F.expr(columns))).first()[0] or 0
    if n <= BROADCAST_TOKENS:
        sent = pages.sparkSession.sparkContext.broadcast(({r.host: r.value for r in rows.collect()}, common))
        return pages.mapInArrow(lambda it: kernel(it, *sent.value), schema)
    host = F.udf(host_of, "string")("url")
    salted = rows.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    joined = pages.withColumn("host", host).withColumn("salt", F.pmod(F.hash("page_id", "url"), F.lit(SALTS))).join(salted, ["host", "salt"], "left")
    return joined.mapInArrow(lambda it: kernel(it, None, common), schema)


def orders(sequence: list[str], classes: dict[str, tuple[int, int]]) -> dict[int, tuple[bool, str, tuple[int, int]]]:
    """Of each class met on a page: whether its members keep one order and nest, that order, and the (class, place) around it.

    classes: (class, members) by token.
    """
    turn: dict[int, list[str]] = {}  # the order of the first occurrence
    seen: dict[int, int] = {}
    around: dict[int, tuple[int, int]] = {}
    size: dict[int, int] = {}
    broken: set[int] = set()
    stack: list[int] = []

    def fail(c: int):
        broken.add(c)
        while c in stack:
            stack.remove(c)

    for token in sequence:
        known = classes.get(token)
        if known is None:
            continue
        c, size[known[0]] = known
        if c in broken:
            continue
        done = seen.get(c, 0)
        first, place = turn.setdefault(c, []), done % size[c]
        if place == 0:
            outer = (stack[-1], seen[stack[-1]] % size[stack[-1]]) if stack else (0, 0)
            if around.setdefault(c, outer) != outer:
                fail(c)
                continue
            if size[c] > 1:
                stack.append(c)
        else:
            while c in stack and stack[-1] != c:  # the inner one is still open
                fail(min(stack[-1], c, key=lambda x: (size[x], x != c)))
            if c in broken:
                continue
        if len(first) < size[c]:
            if token in first:
                fail(c)
                continue
            first.append(token)
        elif first[place] != token:
            fail(c)
            continue
        seen[c] = done + 1
        if place == size[c] - 1 and size[c] > 1:
            stack.pop()
    for c in stack:
        broken.add(c)
    return {c: (c not in broken, "\n".join(x), around.get(c, (0, 0))) for c, x in turn.items()}


def _orders(batches: Iterator[pa.RecordBatch], known: dict | None, common) -> Iterator[pa.RecordBatch]:
    """(host, class_id, good, form, n): how many pages have a class in each order and slot."""
    maps: dict[str, dict] = {}
    total: dict[tuple, int] = {}

    def classes_of(rows) -> dict[str, tuple[int, int]]:
        return {x["token"]: (x["class_id"], x["size"]) for x in rows or ()}

    every = classes_of(common)
    for batch in batches:
        urls, pages = batch.column("url").to_pylist(), batch.column("html").to_pylist()
        held = batch.column("value").to_pylist() if known is None else None
        for k, page in enumerate(pages):
            sequence = ["\n", *(token_of(kind, path, block) for kind, path, _, block in page_events(page or "")), "\n/"]
            if len(sequence) == 2:
                continue
            host = host_of(urls[k])
            if held is not None:
                mine = classes_of(held[k])
            elif host in maps:
                mine = maps[host]
            else:
                mine = maps[host] = classes_of(known.get(host))
            for name, classes in ((host, mine), (EVERY, every)):
                for c, (good, order, outer) in orders(sequence, classes).items():
                    form = int.from_bytes(hashlib.blake2b(f"{order}\0{outer}".encode("utf-8", "surrogatepass"), digest_size=7).digest())
                    key = (name, c, good, form if good else 0)
                    total[key] = total.get(key, 0) + 1
    cols = list(zip(*((*key, n) for key, n in total.items()), strict=True)) if total else [[]] * 5
    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.string(), pa.int64(), pa.bool_(), pa.int64(), pa.int64()), strict=True)], names=["host", "class_id", "good", "form", "n"])


def classes(tokens: DataFrame, support: float = SUPPORT, fewest: int = FEWEST, least: int = LEAST) -> DataFrame:
    """(host, token, class_id, size, chars) of the tokens of token_sums() that enough pages have, in classes of `least` members or more."""
    sizes = tokens.where("token = '\n'").select("host", F.col("pages").alias("host_pages"))
    enough = tokens.where(F.col("pages") >= fewest).join(F.broadcast(sizes) if sizes.count() <= BROADCAST_TOKENS else sizes, "host").where(F.col("pages") >= F.col("host_pages") * support)
    vector = ["host", "pages", "n", "signature"]
    members = enough.groupBy(*vector).agg(F.count("*").alias("size")).where(F.col("size") >= least)
    return enough.join(members, vector).select("host", "token", F.xxhash64(*vector).alias("class_id"), F.col("size").cast("int").alias("size"), "chars")


def valid_classes(pages: DataFrame, found: DataFrame, kept: float = KEPT) -> DataFrame:
    """(host, class_id) of the classes whose order and slot are the same on the share `kept` of the pages that have them."""
    rows = found.groupBy("host").agg(F.collect_list(F.struct("token", "class_id", "size")).alias("value"))
    forms = _for_hosts(pages, rows, "host string, class_id long, good boolean, form long, n long", _orders, "size(value)")
    forms = forms.groupBy("host", "class_id", "good", "form").agg(F.sum("n").alias("n"))
    share = forms.groupBy("host", "class_id").agg(F.sum("n").alias("all"), F.max(F.when(F.col("good"), F.col("n"))).alias("most"))
    return share.where(F.col("most") >= F.col("all") * kept).select("host", "class_id")


def templates(pages: DataFrame, support: float = SUPPORT, fewest: int = FEWEST) -> DataFrame:
    """(host, token, class_id, own, below): the members of valid classes; host EVERY is all hosts together.

    A token is a path, a line break, and nothing for the start of an element, / for its end, or = and a text. own is the
    number of characters of its text on all pages that is not left out; below, for starts, that of all text in the
    element, and of the host's for the token of the page.
    """
    # Texts of single pages are no template anywhere; they are most of all tokens, and summed away first.
    tokens = cut(token_sums(pages).where((F.col("pages") >= fewest) | (F.col("token").endswith("\n") & (F.col("chars") > 0))))
    at = F.substring_index("token", "\n", 1)
    levels = F.split(at, "/")
    above = F.transform(F.sequence(F.lit(0), F.size(levels)), lambda k: F.array_join(F.slice(levels, 1, k), "/"))
    below = tokens.where(F.col("token").endswith("\n") & (F.col("chars") > 0)).select("host", "chars", F.explode(F.array_distinct(F.when(at == "", F.array(F.lit(""))).otherwise(above))).alias("path"))
    below = below.groupBy("host", F.concat("path", F.lit("\n")).alias("token")).agg(F.sum("chars").alias("below"))
    found = cut(classes(tokens, support, fewest))
    good = found.join(valid_classes(pages, found), ["host", "class_id"], "left_semi")
    own = F.when(F.col("token").contains("\n="), F.col("chars")).otherwise(F.lit(0))
    return good.join(below, ["host", "token"], "left").select("host", "token", "class_id", own.alias("own"), F.coalesce("below", F.lit(0)).alias("below"))


def _element(path: str) -> str:
    return path.rpartition("/")[2].partition(".")[0]


def main_slot(tokens: list[tuple[str, int, int]]) -> str | None:
    """The path of the main slot of one template, given its (token, own, below); None if it has no text at all."""
    fixed: dict[str, int] = {}
    for token, own, _ in tokens:
        if own:
            path = token[: token.index("\n")]
            while True:
                fixed[path] = fixed.get(path, 0) + own
                if not path:
                    break
                path = path.rpartition("/")[0]
    paths = {token[:-1]: below for token, _, below in tokens if token.endswith("\n") and below > 0}
    if not paths:
        return None
    mass = {p: max(0, below - fixed.get(p, 0)) for p, below in paths.items()}
    if not mass.get("", 0):  # all pages are alike
        mass = paths
    chain = sorted((p for p in mass if _element(p) in CONTAINERS and 2 * mass[p] > mass[""]), key=lambda p: (p.count("/"), p))
    for p in chain:
        if _element(p) in ARTICLES:
            return p
    headings = [p for p in mass if _element(p) in HEADINGS]
    for p in reversed(chain):
        if not headings or any(h.startswith(p + "/") for h in headings):
            return p
    return chain[-1] if chain else ""


def main_text(page: str | None, texts: frozenset | set, slots: tuple[str | None, ...] = ()) -> str:
    """The blocks in the first of the slots that the page has, or all; texts that the template repeats stay in articles only,
    or if the slot would be empty without them."""
    left = [(path, block) for kind, path, dropped, block in page_events(page or "") if kind == TEXT and not dropped]
    for slot in slots:
        if slot is not None:
            inside = [(path, block) for path, block in left if not slot or path == slot or path.startswith(slot + "/")]
            if inside:
                varied = inside if _element(slot) in ARTICLES else [b for b in inside if token_of(TEXT, *b) not in texts]
                return "\n".join(block for _, block in varied or inside)
    return "\n".join(block for path, block in left if token_of(TEXT, path, block) not in texts)


def _extracted(batches: Iterator[pa.RecordBatch], known: dict | None, common) -> Iterator[pa.RecordBatch]:
    fallback = common["main"] if common is not None else None
    ready: dict[str, tuple] = {}

    def slot_of(value) -> tuple[str | None, frozenset]:
        return (None, frozenset()) if value is None else (value["main"], frozenset(value["texts"] or ()))

    for batch in batches:
        urls, pages = batch.column("url").to_pylist(), batch.column("html")
        own = batch.column("value").to_pylist() if known is None else None
        texts = []
        for k, url in enumerate(urls):
            if own is not None:
                main, repeated = slot_of(own[k])
            else:
                host = host_of(url)
                if host not in ready:
                    ready[host] = slot_of(known.get(host))
                main, repeated = ready[host]
            texts.append(main_text(pages[k].as_py(), repeated, (main, fallback)))
        yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])


def slots(template: DataFrame) -> DataFrame:
    """(host, main, texts): each host's main slot and the texts that its template repeats.

    A host's tokens are gathered: each is on half of the host's pages at least, so they are no more than two pages' tokens.
    """

    @F.udf("string")
    def chosen(tokens):
        return main_slot([tuple(t) for t in tokens])

    rows = template.groupBy("host").agg(F.collect_list(F.struct("token", "own", "below")).alias("tokens"), F.collect_set(F.when(F.col("own") > 0, F.col("token"))).alias("texts"))
    return rows.select("host", chosen("tokens").alias("main"), "texts")


def extract(pages: DataFrame, template: DataFrame | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) for each row of pages (page_id, url, html)."""
    rows = cut(slots(template if template is not None else templates(pages)).select("host", F.struct("main", "texts").alias("value")))
    return _for_hosts(pages, rows, "page_id long, url string, text string, n_chars long", _extracted, "size(value.texts) + 1")
