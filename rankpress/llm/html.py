"""Main text of web pages by deduced templates (operator 3).

A page is a sequence of tokens: the starts and ends of its block-level elements, told apart by the path of open elements,
and its words, told apart by the path they stand in. Over the different pages of a host, tokens with the same vector of
occurrence counts form an equivalence class, if they stand on enough pages. A class is valid if its tokens come in one order, round
by round, on every page; tokens that break the order leave it. Valid classes nest: each must lie, in every round, in the same gap
of a class around it, or apart from it; one that overlaps another is dropped. What remains between the template's tokens are the slots.

Each slot has its share of free and of linked text over all pages. The article is the deepest element of the template that holds most
of the free text of the slots on a page; names of elements and classes only weigh in: text under a name such as "sidebar" counts a
quarter, and blocks under such names below the article's element go. Text that stands word by word in the template, and linked text in
slots of links, go from the article where they are a small part of it.

Pages are dealt by host to groups of bounded size, which meet in one task each; a host with more pages than a group holds is dealt to
several groups, each of which deduces the template from its own share of the host, some hundreds of pages. Hosts with fewer than
`support` different pages are pooled within their group. Nothing but the pages themselves is shuffled, once, and they are parsed once.

Null or empty html, or a page without text: empty text. A null url is a host of its own. A page that the template doesn't fit is read
by elements and names alone. Of equally deep candidates the first by path is taken, so reruns agree. Repeated rows are pages each, but
count once in vectors; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from .common import cut, table

#: Fixed values of HTML: elements without content, elements that end an open p, elements whose text isn't markup.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul br".split())
RAW = frozenset("script style noscript template textarea title iframe svg math object select button canvas audio video".split())
#: Elements and name parts that rarely hold the article.
BOILER = frozenset("head nav footer header aside form script style noscript template iframe button select textarea dialog menu title".split())
BOILER_NAME = re.compile(r"(?:^|[-_ ])(?:ads?|advert\w*|sponsor\w*|promo\w*|banner|nav\w*|menu\w*|breadcrumbs?|sidebar\w*|side|footer|foot|header|masthead|cookie\w*|consent|notice\w*|alert|popup|modal|newsletter|subscribe|signup|social|share|sharing|related|recommend\w*|comments?|commentlist|disqus|respond|replies|reply|widget\w*|login|search\w*|pager|pagination|copyright|legal|toolbar|skip)(?:$|[-_ ])", re.I)
_TAG = re.compile(r"<!--.*?(?:-->|$)|<(?:[!?][^>]*>?)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>?", re.S)
_NAME = re.compile(r"(?:^|\s)(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_ROLE = frozenset("navigation banner contentinfo complementary search form dialog alert menu".split())
_BLANK = re.compile(r"\s+")
_ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}


def tokens(source: str | None) -> list:
    """The page in order: a string for the start or end of a block-level element (its path; ends begin with '<'), and for a
    text block (path, paths of the boilerplate elements around it, text, linked).

    A block is the text between two block-level tags, its references decoded and its white space made single spaces.
    """
    out: list = []
    stack: list[tuple[str, str, tuple]] = [("", "", ())]  # element, path, boilerplate paths
    buf: list[str] = []
    linked = plain = 0
    link = 0
    source, at = source or "", 0

    def flush():
        nonlocal buf, linked, plain
        if buf:
            text = _BLANK.sub(" ", entities.unescape("".join(buf))).strip()
            if text:
                _, path, boiler = stack[-1]
                out.append((path, boiler, text, linked > plain))
        buf, linked, plain = [], 0, 0

    def leave(k: int):
        flush()
        out.extend("<" + s[1] for s in reversed(stack[k:]))
        del stack[k:]

    while at < len(source):
        m = _TAG.search(source, at)
        text = source[at : m.start()] if m else source[at:]
        if text:
            buf.append(text)
            if link:
                linked += len(text)
            else:
                plain += len(text.strip())
        if not m:
            break
        at = m.end()
        name = (m[2] or "").lower()
        if not name:
            continue
        if m[1]:
            if name == "a":
                link = max(0, link - 1)
            elif name in BLOCK or name in BOILER:
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k][0] == name:
                        leave(k)
                        break
            continue
        if name in RAW:
            end = re.compile(rf"</{name}(?=[\s/>])", re.I).search(source, at)
            out.append(f"{stack[-1][1]}/{name}")
            stop = source.find(">", end.start()) if end else -1
            at = stop + 1 if stop >= 0 else len(source)
            continue
        if name == "a":
            link += 1
        if name not in BLOCK and name not in BOILER:
            continue
        flush()
        if name in VOID:
            continue
        if name in _ENDS:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] in _ENDS[name]:
                    leave(k)
                    break
                if stack[k][0] in ("ul", "ol", "dl", "table", "select", "menu"):
                    break
        elif stack[-1][0] == "p":
            leave(len(stack) - 1)
        found = _NAME.findall(m[3]) if m[3] else ()
        names = " ".join(v[1] or v[2] or v[3] or "" for v in found).strip()
        role = any(v[0].lower() == "role" and (v[1] or v[2] or v[3]).lower() in _ROLE for v in found)
        shown = _BLANK.sub(" ", names).replace("/", "|")[:80] if names else ""
        path = f"{stack[-1][1]}/{name}" + (f"[{shown}]" if shown else "")
        boiler = role or (name in BOILER and not (name == "header" and any(s[0] in ("article", "main") for s in stack))) or bool(names and name not in ("body", "html", "article", "main") and BOILER_NAME.search(names))
        out.append(path)
        stack.append((name, path, (*stack[-1][2], path) if boiler else stack[-1][2]))
    flush()
    return out


def steady(pages: list[list], support: int = 3, share: float = 0.2) -> list[list]:
    """The pages with the names of classes and ids taken off elements where these names stand on too few pages."""
    seen: Counter = Counter()
    for items in pages:
        seen.update({x[x.rindex("/") :] for x in items if isinstance(x, str) and x[0] != "<" and x[-1] == "]"})
    least = max(support, share * len(pages))
    rare = {x for x, n in seen.items() if n < least}
    if not rare or len(pages) < support:
        return pages
    known: dict = {}

    def plain(path: str) -> str:
        got = known.get(path)
        if got is None:
            got = known[path] = "/".join(x[: x.index("[")] if f"/{x}" in rare else x for x in path.split("/"))
        return got

    return [[plain(x) if isinstance(x, str) else (plain(x[0]), tuple(map(plain, x[1])), *x[2:]) for x in items] for items in pages]


class Template:
    """Nested equivalence classes of a host's pages, and where the text blocks of these pages lie among them."""

    def __init__(self, pages: list[list], support: int = 3, share: float = 0.2):
        """pages: tokens() of different pages. A token must stand on `support` pages and on a `share` of all."""
        self.classes: list[list] = []  # the tokens of each valid class in order
        ids: dict = {}
        tok, page = [], []
        self.starts = []  # position of each block of each page, in words and tags
        for p, items in enumerate(pages):
            row, begins = [], []
            for x in items:
                if isinstance(x, str):
                    row.append(ids.setdefault(x, len(ids)))
                else:
                    begins.append(len(row))
                    path = x[0]
                    row += [ids.setdefault((path, w), len(ids)) for w in x[2].split(" ")]
            tok.append(np.array(row, np.int64))
            page.append(len(row))
            self.starts.append(np.array(begins, np.int64))
        n = len(pages)
        self.base = np.concatenate([[0], np.cumsum(page)]).astype(np.int64)
        self.known: set = set()
        self.bounds: list[tuple[np.ndarray, int]] = []
        if n < support:
            return
        tok = np.concatenate(tok)
        page = np.repeat(np.arange(n), page)
        spot = np.arange(len(tok))
        both, count = np.unique(tok * n + page, return_counts=True)
        on = np.bincount(both // n, minlength=len(ids))
        enough = on >= max(support, int(np.ceil(share * n)))
        keep = enough[both // n]
        both, count = both[keep], count[keep]
        edge = np.flatnonzero(np.concatenate([[True], np.diff(both // n) > 0, [True]])) if len(both) else np.zeros(1, int)
        vectors: dict = defaultdict(list)
        for i, j in zip(edge[:-1].tolist(), edge[1:].tolist()):
            vectors[(both[i:j] % n).tobytes(), count[i:j].tobytes()].append(int(both[i] // n))
        where = enough[tok]
        order = np.lexsort((spot[where], tok[where]))
        at, of = spot[where][order], tok[where][order]
        first = np.searchsorted(of, np.arange(len(ids) + 1))
        names = list(ids)
        groups = [(len(np.frombuffer(v[0], np.int64)), members) for v, members in vectors.items() if len(members) > 1]
        place = lambda t: at[first[t] : first[t + 1]]
        groups.sort(key=lambda g: (-g[0], len(place(g[1][0])), int(place(g[1][0])[0])))
        for _, members in groups:
            rounds = self._ordered(sorted(members, key=lambda t: (int(place(t).sum()), t)), place, page)
            if len(rounds) < 2:
                continue
            flat = np.sort(np.concatenate([place(t) for t in rounds]))
            begin, end = place(rounds[0]), place(rounds[-1])
            if all(self._nests(begin, end, f, k) or self._nests(f[::k], f[k - 1 :: k], flat, len(rounds)) for f, k in self.bounds):
                self.bounds.append((flat, len(rounds)))
                self.classes.append([names[t] for t in rounds])
        self.known = {t for c in self.classes for t in c}

    @staticmethod
    def _ordered(members: list[int], place, page: np.ndarray) -> list[int]:
        """The members that come in one order, round by round."""
        kept: list[int] = []
        for t in members:
            x = place(t)
            if kept:
                first, last = place(kept[0]), place(kept[-1])
                same = page[x[:-1]] == page[first[1:]]
                if not ((last < x).all() and (page[last] == page[x]).all() and (x[:-1][same] < first[1:][same]).all()):
                    continue
            kept.append(t)
        return kept

    @staticmethod
    def _nests(begin: np.ndarray, end: np.ndarray, outer: np.ndarray, k: int) -> bool:
        """Whether the spans lie in one gap of the outer class, or outside its rounds, every time."""
        a, b = np.searchsorted(outer, begin), np.searchsorted(outer, end)
        gap = a % k
        return bool((a == b).all() and (gap == gap[0]).all())

    def slots(self, p: int) -> list[tuple[int, int]]:
        """(class, gap) of the innermost class around each block of page p; (-1, 0) outside of all."""
        at = self.starts[p] + self.base[p]
        best, width = [(-1, 0)] * len(at), np.full(len(at), np.iinfo(np.int64).max)
        for c, (flat, k) in enumerate(self.bounds):
            i = np.searchsorted(flat, at, "right")
            gap = i % k
            inside = gap > 0
            lo = flat[np.minimum(i - gap, len(flat) - 1)]
            hi = flat[np.minimum(i - gap + k - 1, len(flat) - 1)]
            for b in np.flatnonzero(inside & (hi - lo < width) & (lo >= self.base[p])).tolist():
                best[b], width[b] = (c, int(gap[b])), hi[b] - lo[b]
        return best


def _above(path: str):
    """The paths of the elements around, the innermost first, down to the empty one."""
    while path:
        path = path[: path.rindex("/")]
        yield path


def _marked(path: str) -> str:
    """The path up to its first article element, or main element; else the empty string."""
    for mark in ("article", "main"):
        m = re.search(rf"/{mark}(?:\[[^/]*)?(?=/|$)", path)
        if m:
            return path[: m.end()]
    return ""


class Reader:
    """Reads the articles of pages that share a template."""

    def __init__(self, pages: list[list], support: int = 3, named: float = 0.25, most: float = 0.7, minor: float = 0.3):
        """named: weight of text under boilerplate names; most: share of the free text that the article's element holds;
        minor: what makes less than this share of an article can be taken off it."""
        self.named, self.most, self.minor = named, most, minor
        self.template = t = Template(pages, support)
        self.weight: Counter = Counter()
        self.free: dict = defaultdict(lambda: [0, 0])
        self.places = []
        self.n = len(pages)
        self.shared: Counter = Counter()
        for p, items in enumerate(pages):
            blocks = [x for x in items if not isinstance(x, str)]
            where = t.slots(p)
            self.places.append(where)
            for (path, _, text, linked), s in zip(blocks, where):
                self.free[s][linked] += len(text)
            self.shared.update({(b[0], b[2]) for b in blocks})
        self.dull = [[self._fixed(b) for b in items if not isinstance(b, str)] for items in pages]
        for p, items in enumerate(pages):
            blocks = [x for x in items if not isinstance(x, str)]
            for (path, boiler, text, linked), s, dull in zip(blocks, self.places[p], self.dull[p]):
                if not dull and not linked and not self._links(s):
                    self.weight[path] += len(text) * (self.named if boiler else 1)
        self._found: dict = {}

    def _links(self, slot) -> bool:
        free, linked = self.free[slot]
        return slot[0] >= 0 and linked > free

    def _fixed(self, block) -> bool:
        """Whether a block stands in the template word by word, and as a whole on half of the pages."""
        path, _, text, _ = block
        return self.n >= 5 and self.shared[path, text] * 2 >= self.n and all((path, w) in self.template.known for w in text.split(" "))

    def container(self, paths: frozenset, tags: frozenset) -> str:
        """The article's element on pages with these paths of text and these tags of the template."""
        got = self._found.get((paths, tags))
        if got is None:
            mass: Counter = Counter()
            for path in paths:
                for up in _above(path):
                    mass[up] += self.weight[path]
            total = mass[""]
            fit = [p for p, w in mass.items() if p in tags and total and w >= self.most * total]
            got = min(fit, key=lambda p: (-p.count("/"), p)) if fit else ""
            got = _marked(got) or got
            self._found[paths, tags] = got
        return got

    def text(self, p: int, items: list) -> str:
        """The article of page p: its blocks in order, joined by line breaks."""
        blocks = [x for x in items if not isinstance(x, str)]
        tags = frozenset(x for x in items if isinstance(x, str) and x in self.template.known and x[0] != "<")
        place = self.container(frozenset(b[0] for b in blocks), tags) if tags else ""
        size = lambda bs: sum(len(b[2]) for b in bs)
        plain = [b for b in blocks if not b[1]]
        inside = [(b, s, d) for b, s, d in zip(blocks, self.places[p], self.dull[p]) if place and (b[0] + "/").startswith(place + "/") and not any(len(x) > len(place) for x in b[1])]
        if not inside or (plain and size(b for b, _, _ in inside) < self.minor * size(plain)):
            marked = [b for b in plain if _marked(b[0])]
            return "\n".join(b[2] for b in marked or [b for b in plain if not self._fixed(b)])
        rest = [b for b, s, d in inside if not d and not (b[3] and self._links(s))]
        chosen = [b for b, _, _ in inside]
        if size(rest) >= (1 - self.minor) * size(chosen):
            chosen = rest
        return "\n".join(b[2] for b in chosen)


def articles(hosts: list[str], sources: list[str | None], support: int = 3) -> list[str]:
    """The main text of each page of a group; hosts with fewer than `support` different pages are pooled."""
    parsed = [tokens(s) for s in sources]
    same = [xxhash.xxh3_64_intdigest("\n".join(x if isinstance(x, str) else x[2] for x in items).encode("utf-8", "surrogatepass")) for items in parsed]
    different: dict = defaultdict(dict)
    for i, (h, d) in enumerate(zip(hosts, same)):
        different[h].setdefault(d, i)
    pool: dict = {}
    members: dict = defaultdict(list)
    for h, ds in sorted(different.items()):
        if len(ds) >= support:
            members[h] = sorted(ds.items())
        else:
            pool |= ds
    texts: dict = {}  # by host, None for the pool, and digest
    for h, ds in [*members.items(), (None, sorted(pool.items()))]:
        if ds:
            pages = steady([parsed[i] for _, i in ds], support)
            reader = Reader(pages, support)
            texts |= {(h, d): reader.text(k, pages[k]) for k, (d, _) in enumerate(ds)}
    return [texts[h if h in members else None, d] for h, d in zip(hosts, same)]


def _host(url):
    """The host of a url, else the empty string."""
    return F.coalesce(F.lower(F.regexp_extract(url, r"^[a-zA-Z][\w+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)), F.lit(""))


def main_text(pages: DataFrame, group: int = 512, group_chars: int = 16 << 20, sent: int = 1 << 20) -> DataFrame:
    """page_id, url, text, n_chars for each row of pages (page_id, url, html).

    group, group_chars: about how many pages and characters meet in a task. Hosts with more than that are dealt to several groups;
    the table of these hosts is sent to all tasks as long as it has at most `sent` rows, else joined.
    """
    d = pages.select("page_id", "url", "html", _host("url").alias("_host"))
    size = cut(d.groupBy("_host").agg(F.count("*").alias("n"), F.coalesce(F.sum(F.length("html")), F.lit(0)).alias("chars")))
    parts = F.ceil(F.greatest(F.col("n") / group, F.col("chars") / group_chars)).cast("long")
    groups = size.agg(F.greatest(F.sum("n") / group, F.sum("chars") / group_chars)).first()[0] or 0
    large = size.where(parts > 1).select("_host", parts.alias("_parts"))
    d = d.join(F.broadcast(large) if large.count() <= sent else large, "_host", "left")
    row = F.coalesce(F.col("page_id").cast("long"), F.monotonically_increasing_id())
    share = F.xxhash64("_host", F.pmod(F.xxhash64(row, "url"), F.col("_parts")))
    d = d.select("page_id", "url", "html", "_host", F.when(F.col("_parts").isNull(), F.pmod(F.xxhash64("_host"), F.lit(int(groups) + 1))).otherwise(share).alias("_group"))

    def run(t: pa.Table) -> pa.Table:
        texts = articles(t.column("_host").to_pylist(), t.column("html").to_pylist())
        return pa.table({"page_id": t.column("page_id"), "url": t.column("url"), "text": pa.array(texts, pa.string()), "n_chars": pa.array([len(x) for x in texts], pa.int64())})

    kinds = dict(pages.dtypes)
    return d.groupBy("_group").applyInArrow(run, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars long")


def op3(spark, sf_dir):
    return main_text(table(spark, sf_dir, "pages"))


QUERIES = {"op3_html_text": op3}
SQL: dict[str, str] = {}
