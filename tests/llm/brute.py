"""Plain Python versions of the operators' results, for small tables."""

import hashlib
import html.parser
import re
from collections import Counter, defaultdict

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
ITEM_WORDS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def near(docs, words=5, num=75, den=100):
    """docs: {doc_id: text} -> {doc_id: (n_shingles, component)}"""
    sets = {}
    for i, t in docs.items():
        w = WORDS.findall((t or "").translate(LOWER))
        sets[i] = {tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else ({tuple(w)} if w else set())
    parent = {i: i for i in docs}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    where = defaultdict(list)
    for i, s in sets.items():
        for x in s:
            where[x].append(i)
    both = Counter()
    for ids in where.values():
        for a in ids:
            for b in ids:
                if a < b:
                    both[a, b] += 1
    for (a, b), n in both.items():
        if den * n >= num * (len(sets[a]) + len(sets[b]) - n):
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), root(i)) for i in docs}


def without_repeats(docs, window=20):
    words = {i: WORDS.findall(t or "") for i, t in docs.items()}
    first = {}
    for i in sorted(words):
        for k in range(len(words[i]) - window + 1):
            first.setdefault(tuple(words[i][k : k + window]), (i, k))
    out = {}
    for i, w in words.items():
        gone = [False] * len(w)
        for k in range(len(w) - window + 1):
            if first[tuple(w[k : k + window])] < (i, k):
                gone[k : k + window] = [True] * window
        kept = " ".join(x for x, g in zip(w, gone, strict=True) if not g)
        out[i] = (len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest())
    return out


def contaminated(docs, items, width=13):
    wins = defaultdict(set)
    for i, t in items.items():
        w = ITEM_WORDS.findall((t or "").translate(LOWER))
        for k in range(max(1, len(w) - width + 1)) if w else ():
            wins[tuple(w[k : k + width])].add(str(i))
    sizes = sorted({len(x) for x in wins})
    out = {}
    for i, t in docs.items():
        w = ITEM_WORDS.findall((t or "").translate(LOWER))
        hit, found = set(), set()
        for n in sizes:
            for k in range(len(w) - n + 1):
                if (x := tuple(w[k : k + n])) in wins:
                    hit |= set(range(k, k + n))
                    found |= wins[x]
        out[i] = (len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w))
    return out


def figures(text):
    t = text or ""
    w = WORDS.findall(t)
    wins = defaultdict(list)
    for k in range(len(w) - 7):
        wins[tuple(w[k : k + 8])].append(k)
    cover = {p for at in wins.values() if len(at) > 1 for k in at for p in range(k, k + 8)}
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WORDS.search(line):
            dup += line in seen
            seen.add(line)
    n = len(w)
    return (n, sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(cover), n < 20 or 100 * len(cover) > 30 * n)


class _Article(html.parser.HTMLParser):
    """Blocks of the article element, which the given pages all have."""

    ENDS = {"h1", "h2", "h3", "p", "br", "div", "ul", "li", "article", "blockquote", "section", "table", "tr", "td"}

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.inside, self.skip, self.now, self.blocks = False, 0, [], []

    def flush(self):
        text = " ".join("".join(self.now).split())
        self.now.clear()
        if text:
            self.blocks.append(text)

    def handle_starttag(self, tag, attrs):
        if tag in self.ENDS:
            self.flush()
        if tag == "article":
            self.inside = True
        elif tag in ("script", "style", "nav", "aside", "form") or (tag == "div" and self.inside):
            self.skip += 1

    def handle_endtag(self, tag):
        if tag in self.ENDS:
            self.flush()
        if tag == "article":
            self.inside = False
        elif tag in ("script", "style", "nav", "aside", "form") or (tag == "div" and self.inside):
            self.skip -= 1

    def handle_data(self, data):
        if self.inside and not self.skip:
            self.now.append(data)


def article(page):
    parser = _Article()
    parser.feed(page or "")
    parser.close()
    parser.flush()
    return "\n".join(parser.blocks)
