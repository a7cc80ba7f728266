"""HTML extraction by template deduction: equivalence classes of tokens with equal occurrence vectors, nested into a template.

A token is an element (its path of tags, classes, ids and, for generic containers, place among like siblings) or a text on
such a path. Its occurrence vector says how often it stands on each page of a host. Vectors aren't built: a token's vector
is known by two sums of hashes of (page, count) over its pages, which partial aggregates form in any order, so a host with a
third of all pages is no hot spot. Pages of a host with the same content are one page. Tokens of a host with equal vectors
form a class, kept with at least ``LEAST_TOKENS`` tokens, on ``LEAST_PAGES`` pages and ``LEAST_SHARE`` of the host's pages.

A second pass over the pages reads each as the sequence of its classes' tokens (an element's start and end are two). It
tells for every class in what order its tokens stand, in which class and after which of that class's tokens each of its
instances begins, whether an instance crosses another's, and how much text lies in each gap. A class is valid if one order
holds on ``ORDER_SHARE`` of its pages and one parent gap for that share of its instances; text in the gaps of others counts
for the gap around them. Valid classes hang in their parents' gaps: that is the template, and gaps with text are its slots.

The article is what stands in the slots of the innermost container that holds ``MAIN_SHARE`` of the text in all slots (links
aside) over the host's pages. Elements break ties: one that says it is the article wins with half of that text. Left out of
it are the template's own texts (in a declared article only those that nearly all of at least ``SURE_PAGES`` pages share)
and elements that by tag, role, class or id are menus, headers, footers, sidebars, notices, adverts, forms, comments or the
like. On pages without that container, and on hosts whose template has none or whose pages agree in nearly all their text,
elements alone decide, page by page: below the one that says it is the article, else below the one with most text.

Pages are read in time linear in their length: a tag that never ends goes with the rest of the page, elements nested deeper
than ``DEPTH`` are taken as siblings.

Defined results: null and empty pages give empty text; pages without a usable URL share the empty host; a repeated row
is extracted like the other and has no vote of its own.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C
from .url_filter import host_path

LEAST_TOKENS, LEAST_PAGES, LEAST_SHARE, SURE_PAGES, SURE_SHARE = 3, 3, 0.5, 8, 0.95
#: Pages that must agree on a class's order and place; text that the article's container must hold, and a declared article.
ORDER_SHARE, MAIN_SHARE, DECLARED_SHARE = 0.95, 0.8, 0.5
#: Share of a host's text that lies outside the template where pages have articles of their own.
OWN_SHARE = 0.1
#: Open elements at a time, as browsers bound them; places among like siblings that are told apart.
DEPTH, PLACES = 512, 8
RAW = frozenset("script style noscript template iframe textarea title xmp noframes svg math select".split())
RAW_END = {x: re.compile(rf"</{x}\s*>", re.I) for x in RAW}
MARKUP, NAME = re.compile(r"<(?=[a-zA-Z/!?])"), re.compile(r"/?([a-zA-Z][a-zA-Z0-9:-]*)")
#: The rest of a tag with paired quotes; possessive, so each position is tried once.
REST = re.compile(r"(?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+>")
ATTRIBUTE = re.compile(r"([a-zA-Z_:][-\w:.]*)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu "
    "nav ol option p pre section summary table tbody td tfoot th thead tr ul".split()
)
CLOSES_P = BLOCK - {"br", "li", "td", "th", "tr", "tbody", "thead", "tfoot", "option", "caption", "body", "html", "head", "legend", "dd", "dt"}
#: A new element of the key closes open elements of the value, up to the named containers.
SAME = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
#: Containers whose path holds their place among like siblings.
GENERIC = frozenset("div section table td ul ol dl".split())
#: Containers that can be the article's.
HOLDER = frozenset("article main section div td center dd form blockquote".split())
INLINE = frozenset("a abbr b bdi bdo big cite code del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var".split())
LEFT_OUT = frozenset("head nav footer aside form button menu dialog object audio video canvas fieldset datalist".split())
ROLES = frozenset("navigation banner contentinfo complementary search form alert alertdialog dialog menu menubar toolbar".split())
MARKED = frozenset(
    "nav navbar navigation menu menus breadcrumb breadcrumbs masthead footer sidebar sidebars aside widget widgets ad ads adv advert adverts advertisement advertisements advertising sponsor sponsored "
    "promo promos promotion banner banners cookie cookies consent gdpr notice notices notification notifications alert alerts popup modal overlay newsletter subscribe subscription signup login search searchbox "
    "comment comments commentlist commentary disqus respond reply replies discussion share sharing social related recommended recommendations pagination pager toolbar disclaimer copyright hidden paywall".split()
)
SITE_HEADER = frozenset(["header", "topbar", "siteheader"])
NAMED = re.compile(r"(?:^|[\s_-])(?:article|post|entry|story|content|main|text)(?:[\s_-](?:body|content|text|area|main|column))?(?:$|[\s_-])", re.I)
WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
#: Names that speak of something else on the page, such as has-sidebar.
STATES = re.compile(r"(?<!\S)(?:has|with|no|without|is|js)[_-]\S*|[_-](?:with|no|without|has)[_-]\S*", re.I)


class Page:
    """Elements and texts of a page, in order, as parallel lists; element 0 stands for the page."""

    def __init__(self, text: str):
        self.parent, self.tag, self.path, self.out, self.sure = [0], [""], [0], [False], [False]
        self.named, self.link, self.soft = [False], [False], [False]
        #: element, text, number of its block
        self.texts: list[tuple[int, str, int]] = []
        #: in order: (1, element) where it starts, (-1, element) where it ends, (0, number of a text)
        self.events: list[tuple[int, int]] = []
        #: open elements of a tag; like siblings so far; elements opened beyond the depth and not ended yet
        self.open: dict[str, int] = {}
        self._like: dict[tuple[int, int], int] = {}
        self._over = 0
        self._read(text)

    def _read(self, text: str) -> None:
        stack, block, at, size = [0], 0, 0, len(text)
        while m := MARKUP.search(text, at):
            lo = m.start()
            if lo > at:
                self._text(stack[-1], text[at:lo], block)
            if text.startswith("<!--", lo):
                end = text.find("-->", lo + 4)
                at = end + 3 if end >= 0 else size
                continue
            name = NAME.match(text, lo + 1)
            if not name:  # a declaration, an instruction or an end without a name
                end = text.find(">", lo)
                at = end + 1 if end >= 0 else size
                continue
            rest = REST.match(text, name.end())
            end = rest.end() - 1 if rest else text.find(">", name.end())
            if end < 0:
                at = size
                continue
            tag, at = name[1].lower(), end + 1
            if text[lo + 1] == "/":
                block += tag in BLOCK
                self._close(stack, tag)
                continue
            if tag in RAW:
                if text[end - 1] != "/":
                    close = RAW_END[tag].search(text, at)
                    at = close.end() if close else size
                continue
            block += tag in BLOCK
            if tag in VOID:
                continue
            if tag in CLOSES_P and self.open.get("p"):
                self._drop(stack, {"p"}, {"button", "table", "div", "article", "section", "main", "td", "blockquote"})
            if tag in SAME and any(self.open.get(x) for x in SAME[tag][0]):
                self._drop(stack, *SAME[tag])
            self._open(stack, tag, text[name.end() : end])
        if at < size:
            self._text(stack[-1], text[at:], block)
        self._pop(stack, 1)

    def _text(self, element: int, text: str, block: int) -> None:
        self.events.append((0, len(self.texts)))
        self.texts.append((element, text, block))

    def _pop(self, stack: list[int], i: int) -> None:
        """Ends the open elements from the i-th on."""
        for e in reversed(stack[i:]):
            self.events.append((-1, e))
            self.open[self.tag[e]] -= 1
        del stack[i:]

    def _open(self, stack: list[int], tag: str, rest: str) -> None:
        names = role = ""
        hidden = body = False
        if rest.strip(" /\n\t"):
            for m in ATTRIBUTE.finditer(rest):
                key, value = m[1].lower(), m[2] or m[3] or m[4] or ""
                if key in ("class", "id"):
                    names += " " + value
                elif key == "role":
                    role = value.lower().strip()
                elif key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
                    hidden = True
                elif key == "itemprop" and value == "articleBody":
                    body = True
        up = stack[-1]
        words = {w.lower() for w in WORDS.findall(STATES.sub(" ", names))} if names else frozenset()
        k = len(self.parent)
        self.parent.append(up)
        self.tag.append(tag)
        path = xxhash.xxh64_intdigest(f"{tag} {' '.join(sorted(re.sub(r'[0-9]+', '0', names).split()))}", self.path[up])
        if tag in GENERIC:
            place = self._like[up, path] = min(self._like.get((up, path), 0) + 1, PLACES)
            path = xxhash.xxh64_intdigest(place.to_bytes(1), path)
        self.path.append(path)
        declared = tag in ("article", "main") or role in ("main", "article") or body
        marked = tag not in ("html", "body", "article", "main") and bool(words & MARKED) or tag == "article" and bool(words & {"comment", "reply", "ad", "related", "promo", "sponsored"})
        header = (tag == "header" or bool(words & SITE_HEADER)) and not any(self.sure[x] for x in stack)
        self.soft.append(marked)
        self.out.append(self.out[up] or tag in LEFT_OUT or role in ROLES or hidden or header and tag not in ("html", "body"))
        self.sure.append(declared and not marked)
        self.named.append(bool(names) and NAMED.search(names) is not None)
        self.link.append(self.link[up] or tag == "a")
        self.events.append((1, k))
        if len(stack) >= DEPTH:
            self.events.append((-1, k))
            self._over += 1
            return
        self.open[tag] = self.open.get(tag, 0) + 1
        stack.append(k)

    def _drop(self, stack: list[int], tags: set[str], until: set[str]) -> None:
        for i in range(len(stack) - 1, 0, -1):
            if self.tag[stack[i]] in tags:
                self._pop(stack, i)
                return
            if self.tag[stack[i]] in until:
                return

    def _close(self, stack: list[int], tag: str) -> None:
        if self._over:
            self._over -= 1
            return
        if not self.open.get(tag):
            return
        for i in range(len(stack) - 1, 0, -1):
            own = self.tag[stack[i]]
            if own == tag:
                self._pop(stack, i)
                return
            if tag in INLINE and own in BLOCK:
                return  # an inline end tag doesn't reach out of its block
            if tag != "html" and tag != "body" and own in ("article", "main", "td", "th", "body") and tag not in BLOCK - {"p"}:
                return

    def texts_seen(self) -> list[tuple[int, int, int]]:
        """Element, token and characters of every text with words, in order."""
        return [(e, self._token(e, w), len(w)) for e, t, _ in self.texts if (w := " ".join(t.split()))]

    def tokens(self) -> dict[int, int]:
        """Count of every token: elements by path, texts by path and words."""
        return dict(Counter(self.path[1:]) + Counter(t for _, t, _ in self.texts_seen()))

    def profile(self) -> dict[int, tuple[int, int, int]]:
        """Count, characters (of texts that elements don't leave out) and kind of every token.

        Kinds: 0 text, 1 element, 2 container, 3 container that says it is the main part, 4 or the article.
        """
        found: dict[int, list[int]] = {}
        for e in range(1, len(self.parent)):
            held = self.tag[e] in HOLDER and not self.out[e]
            x = found.setdefault(self.path[e], [0, 0, 0])
            x[0] += 1
            x[2] = max(x[2], 3 + (self.tag[e] != "main") if held and self.sure[e] else 1 + held)
        for e, token, size in self.texts_seen():
            x = found.setdefault(token, [0, 0, 0])
            x[0] += 1
            x[1] += 0 if self.out[e] else size
        return {t: tuple(x) for t, x in found.items()}

    def _token(self, element: int, words: str) -> int:
        return xxhash.xxh64_intdigest(words, self.path[element] ^ 1)

    def walk(self, classes: dict[int, int], length: dict[int, int]) -> tuple[dict[int, tuple[int, ...] | None], list[tuple[int, int, int]], dict[tuple[int, int], int]]:
        """Orders, places and texts of the classes. classes: token to class; length: tokens of an instance of a class.

        Returns the order of each class on this page (None: it has no one order), (class, parent, gap) of each instance
        (gap: the parent's token before it; parent -1: it crosses another), and characters by (class, gap) of the gaps.
        """
        order: dict[int, tuple[int, ...] | None] = {}
        places: list[tuple[int, int, int]] = []
        text: dict[tuple[int, int], int] = {}
        stack: list[tuple[int, list[int]]] = []
        softly = self.soft[:]
        for e in range(1, len(softly)):
            softly[e] |= softly[self.parent[e]]
        for kind, k in self.events:
            if kind:
                token = self.path[k] ^ (END if kind < 0 else 0)
                c = classes.get(self.path[k])
            else:
                e, t, _ = self.texts[k]
                w = " ".join(t.split())
                if not w:
                    continue
                token = self._token(e, w)
                c = classes.get(token)
                if c is None:
                    if not self.out[e] and not softly[e] and not self.link[e]:
                        gap = (stack[-1][0], stack[-1][1][-1]) if stack else (0, 0)
                        text[gap] = text.get(gap, 0) + len(w)
                    continue
            if c is None:
                continue
            own = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == c), None)
            if own is None:
                places.append((c, stack[-1][0], stack[-1][1][-1]) if stack else (c, 0, 0))
                own = len(stack)
                stack.append((c, []))
            for x, _ in stack[own + 1 :]:
                places.append((x, -1, 0))
                order[x] = None
            del stack[own + 1 :]
            seen = stack[own][1]
            seen.append(token)
            if len(seen) == length[c]:
                found = tuple(seen)
                order[c] = found if order.setdefault(c, found) == found and len(set(found)) == len(found) else None
                stack.pop()
        for c, _ in stack:
            order[c] = None
        return order, places, text

    def main_text(self, template: frozenset[int], sure: frozenset[int], most: frozenset[int] = frozenset(), region: int = 0) -> str:
        """Text of the article. template: the host's template tokens; most: those that nearly all pages have; sure: those of
        them dropped from a declared article; region: the path of the container whose slots hold the article, if known.

        Where no text would be left, a declared article is kept whole, and elsewhere only ``most`` is dropped.
        """
        text = self._main_text(template, sure, region)
        if text or not template:
            return text
        return self._main_text(most, frozenset(), region)

    def _main_text(self, template: frozenset[int], sure: frozenset[int], container: int = 0) -> str:
        n = len(self.parent)
        deduced = [e for e in range(1, n) if self.path[e] == container and not self.out[e]] if container else []
        holds = np.zeros(n, bool)  # the article's container lies below or is this
        holds[deduced] = True
        for e in range(n - 1, 0, -1):
            holds[self.parent[e]] |= holds[e] or self.sure[e]
        out = np.array(self.out)
        for e in range(1, n):
            # a class name alone doesn't leave out what holds the article
            out[e] |= out[self.parent[e]] or (self.soft[e] and not holds[e])
        kept, words = [], np.zeros(n)
        for e, t, block in self.texts:
            if out[e] or not t.strip():
                continue
            token = self._token(e, " ".join(t.split()))
            known = token in template
            kept.append((e, t, block, known, token in sure))
            if not known and not self.link[e]:
                words[e] += len(t)
        inside = np.zeros(n, bool)
        if deduced:
            inside[deduced] = True
            strict = any(self.sure[e] for e in deduced)
        else:
            region, strict = self._by_elements(words, out, bool(template))
            inside[region] = True
        for e in range(1, n):
            inside[e] |= inside[self.parent[e]]
        blocks: dict[int, list[str]] = {}
        for e, t, block, known, certain in kept:
            if inside[e] and not (certain if strict else known):
                blocks.setdefault(block, []).append(html.unescape(t))
        return " ".join(filter(None, (" ".join("".join(x).split()) for x in blocks.values())))

    def _by_elements(self, words: np.ndarray, out: np.ndarray, descend: bool) -> tuple[int, bool]:
        """The element that holds the article of this page alone, and whether it says so."""
        n = len(self.parent)
        total = words.copy()
        for e in range(n - 1, 0, -1):
            total[self.parent[e]] += total[e]
        declared = [e for e in range(1, n) if self.sure[e] and not out[e]]
        if any(self.tag[e] != "main" for e in declared):
            declared = [e for e in declared if self.tag[e] != "main"]
        if region := max(declared, key=lambda e: (total[e], -e), default=0):
            return region, True
        if total[0]:
            named = [e for e in range(1, n) if self.named[e] and not out[e] and total[e] >= 0.4 * total[0]]
            best = max((total[x] for x in named), default=0)
            region = min(named, key=lambda e: (total[e] < 0.8 * best, total[e], -e), default=0)
            if not region and descend:
                # down to the deepest element that still holds most of the page's own text
                for e in range(1, n):
                    if self.parent[e] == region and self.tag[e] in BLOCK - {"p"} and total[e] >= MAIN_SHARE * total[0]:
                        region = e
        return region, False


#: Flips the path of an element into the token of its end.
END = 0x5DEECE66D << 20


def article_container(classes: dict[int, tuple[int, ...]], places: dict[int, tuple[int, int]], text: dict[tuple[int, int], int], kind: dict[int, int]) -> int:
    """Path of the container that holds the article in a host's template, 0 if there is none.

    classes: order of each class that has one; places: parent and gap of each class that has one place; text: characters by
    (class, gap); kind: see :meth:`Page.profile`. Classes with both are nested, the others' texts go to the gaps around them.
    """
    valid = {c for c in classes if c in places}

    def holder(c: int, gap: int) -> tuple[int, int]:
        seen = set()
        while c and c not in valid and c not in seen:
            seen.add(c)
            c, gap = places.get(c, (0, 0))
        return (c, gap) if c in valid else (0, 0)

    slot: dict[tuple[int, int], int] = {}
    for at, size in text.items():
        slot[holder(*at)] = slot.get(holder(*at), 0) + size
    below: dict[tuple[int, int], list[int]] = {}
    for c in sorted(valid):
        below.setdefault(holder(*places[c]), []).append(c)
    # classes from the root on; parents come before what is nested in them
    nested, depth = [c for c in below.get((0, 0), [])], {c: 0 for c in below.get((0, 0), [])}
    for c in nested:
        for gap in classes[c]:
            for x in below.get((c, gap), []):
                if x not in depth:
                    depth[x] = depth[c] + 1
                    nested.append(x)
    held: dict[int, int] = {}
    found = []
    for c in reversed(nested):
        total, start = 0, {}
        for i, token in enumerate(classes[c]):
            if token ^ END in start:
                lo, at = start[token ^ END]
                found.append((total - lo, depth[c], at, token ^ END))
            start[token] = (total, i)
            total += slot.get((c, token), 0) + sum(held.get(x, 0) for x in below.get((c, token), []))
        held[c] = total
    whole = slot.get((0, 0), 0) + sum(held.get(c, 0) for c in below.get((0, 0), []))
    if not whole:
        return 0
    for level in (4, 3):
        declared = [x for x in found if kind.get(x[3]) == level and x[0] >= DECLARED_SHARE * whole]
        if declared:
            return max(declared)[3]
    return max((x[1:] for x in found if kind.get(x[3], 0) == 2 and x[0] >= MAIN_SHARE * whole), default=(0, 0, 0))[2]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _unsigned(values: list[int] | None) -> list[int]:
    return [x & (1 << 64) - 1 for x in values or []]


def _distinct(pages: DataFrame) -> tuple[DataFrame, DataFrame]:
    """One page of each (host, key), and the pages of each host. pages: host, key (hash of the content), html."""
    votes = C.stored(pages.groupBy("host", "key").agg(F.count("*").alias("rows")), "votes")
    repeated = C.small(C.stored(votes.filter("rows > 1").select("host", "key"), "repeated"))
    pages = pages.select("host", "key", "html")
    # only pages that stand in several rows are moved to find one of each
    once = pages.join(repeated, ["host", "key"], "left_semi").groupBy("host", "key").agg(F.first("html").alias("html"))
    return pages.join(repeated, ["host", "key"], "left_anti").union(once), votes.groupBy("host").agg(F.count("*").alias("n"))


def templates(pages: DataFrame) -> DataFrame:
    """Valid-by-support classes of every host that has some: host, n, tokens, classes, kinds, most, agree.

    pages: host, key (hash of the content), html. Rows of a host with one key are one page and vote once; ``n`` counts pages.
    tokens, classes (a number of the token's vector) and kinds run in parallel; most: the tokens on nearly all pages. agree:
    hardly any text is left outside the template, so its tokens can't be told from the articles'.
    """
    return _templates(*_distinct(pages))


def _templates(pages: DataFrame, sizes: DataFrame) -> DataFrame:
    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("html", lambda: None)
        for batch in stream:
            held: dict[tuple[str, int], list[int]] = {}
            for host, key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                for token, (count, size, kind) in Page(text.as_py() or "").profile().items():
                    x = held.setdefault((host, token), [0, 0, 0, 0, 0])
                    code = xxhash.xxh64_intdigest(count.to_bytes(4, "little"), key & (1 << 64) - 1)
                    x[0] += 1
                    x[1] += code >> 32
                    x[2] += code & 0xFFFFFFFF
                    x[3] += size
                    x[4] = max(x[4], kind)
            if held:
                columns = [pa.array([x[k] for x in held.values()], pa.int64()) for k in range(5)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([h for h, _ in held]), pa.array([_signed(t) for _, t in held], pa.int64()), *columns], ["host", "token", "pages", "high", "low", "size", "kind"]
                )

    found = pages.mapInArrow(step, "host string, token bigint, pages bigint, high bigint, low bigint, size bigint, kind bigint")
    # sums of 32-bit halves hold the vectors of up to 2^31 pages a host
    sums = [F.sum(x).alias(x) for x in ("pages", "high", "low", "size")]
    found = C.stored(found.groupBy("host", "token").agg(*sums, F.max("kind").alias("kind")), "tokens")
    sizes = C.small(C.stored(sizes.filter(F.col("n") >= LEAST_PAGES), "hosts"))
    often = found.filter(F.col("pages") >= LEAST_PAGES).join(sizes, "host").filter(F.col("pages") >= LEAST_SHARE * F.col("n"))
    # a class has at most the tokens that half of the host's pages share
    classes = often.groupBy("host", "high", "low", "pages", "n").agg(F.collect_list(F.struct("token", "kind")).alias("x"), F.sum("size").alias("size")).filter(F.size("x") >= LEAST_TOKENS)
    number = F.xxhash64("high", "low", "pages")
    most = F.when(F.col("pages") >= SURE_SHARE * F.col("n"), F.col("x.token")).otherwise(F.array().cast("array<bigint>"))
    known = classes.groupBy("host", "n").agg(
        F.flatten(F.collect_list("x")).alias("x"), F.flatten(F.collect_list(F.transform("x", lambda _: number))).alias("classes"), F.flatten(F.collect_list(most)).alias("most"), F.sum("size").alias("size")
    )
    whole = found.groupBy("host").agg(F.sum("size").alias("whole"))
    agree = (F.col("whole") - F.col("size") < OWN_SHARE * F.col("whole")).alias("agree")
    return known.join(whole, "host").select("host", "n", F.col("x.token").alias("tokens"), "classes", F.col("x.kind").alias("kinds"), "most", agree)


def containers(pages: DataFrame, known: DataFrame) -> DataFrame:
    """host, region: the path of the article's container in each host's nested template (0: none).

    pages: host, html, each page once; known: see :func:`templates`.
    """

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("html", lambda: None)
        kept: dict[str, tuple[dict[int, int], Counter]] = {}
        for batch in stream:
            held: dict[tuple, list[int]] = {}

            def add(key: tuple, n: int, size: int, held=held) -> None:
                x = held.setdefault(key, [0, 0])
                x[0] += n
                x[1] += size

            for k, (host, text) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1), strict=True)):
                if host not in kept:
                    if len(kept) > 1000:
                        kept.clear()
                    tokens, classes, kinds = (batch.column(j)[k].as_py() for j in (2, 3, 4))
                    kept[host] = (dict(zip(_unsigned(tokens), classes, strict=True)), sum((Counter({c: 2 if x else 1}) for c, x in zip(classes, kinds, strict=True)), Counter()))
                order, places, size = Page(text.as_py() or "").walk(*kept[host])
                for c, tokens in order.items():
                    add((host, 1, c, 0, 0, tokens), 1, 0)
                for c, parent, gap in places:
                    add((host, 2, c, parent, gap, ()), 1, 0)
                for (c, gap), n in size.items():
                    add((host, 3, c, 0, gap, ()), 0, n)
            if held:
                columns = [pa.array([x[0] for x in held], pa.string())]
                columns += [pa.array([_signed(x[k]) if k == 4 else x[k] for x in held], pa.int64()) for k in range(1, 5)]
                columns += [pa.array([None if x[5] is None else [_signed(t) for t in x[5]] for x in held], pa.list_(pa.int64()))]
                columns += [pa.array([x[k] for x in held.values()], pa.int64()) for k in (0, 1)]
                yield pa.RecordBatch.from_arrays(columns, ["host", "what", "c", "parent", "gap", "tokens", "n", "size"])

    shared = C.small(known.filter("not agree").select("host", "tokens", "classes", "kinds"), weight=F.size("tokens"))
    seen = pages.select("host", "html").join(shared, "host").mapInArrow(step, "host string, what bigint, c bigint, parent bigint, gap bigint, tokens array<bigint>, n bigint, size bigint")
    seen = C.stored(seen.groupBy("host", "what", "c", "parent", "gap", "tokens").agg(F.sum("n").alias("n"), F.sum("size").alias("size")), "walked")
    # what nearly all pages agree on, of each class
    best = seen.filter("what < 3").groupBy("host", "what", "c").agg(F.max_by(F.struct("parent", "gap", "tokens", "n"), F.struct("n", "gap")).alias("x"), F.sum("n").alias("n"))
    best = best.filter(F.col("x.n") >= ORDER_SHARE * F.col("n")).select("host", "what", "c", "x.parent", "x.gap", "x.tokens", F.lit(0).cast("long").alias("size"))
    best = best.filter("what = 1 and tokens is not null or what = 2 and parent <> -1")
    rows = best.union(seen.filter("what = 3").select("host", "what", "c", "parent", "gap", "tokens", "size"))
    agreed = rows.groupBy("host").agg(F.collect_list(F.struct("what", "c", "parent", "gap", "tokens", "size")).alias("rows"))

    def choose(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("html", lambda: None)
        for batch in stream:
            found = []
            for rows, tokens, kinds in zip(*(batch.column(k).to_pylist() for k in (1, 2, 3)), strict=True):
                order = {r["c"]: tuple(_unsigned(r["tokens"])) for r in rows if r["what"] == 1}
                places = {r["c"]: (r["parent"], *_unsigned([r["gap"]])) for r in rows if r["what"] == 2}
                text = {(r["c"], *_unsigned([r["gap"]])): r["size"] for r in rows if r["what"] == 3}
                found.append(_signed(article_container(order, places, text, dict(zip(_unsigned(tokens), kinds, strict=True)))))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.int64())], ["host", "region"])

    return agreed.join(known.select("host", "tokens", "kinds"), "host").mapInArrow(choose, "host string, region bigint")


def extract(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """id, url, text of every row."""
    host, _ = host_path("_url")
    rows = pages.select(F.col(id_col).alias("_id"), F.col(url_col).alias("_url"), F.col(html_col).alias("html"))
    rows = rows.select("_id", "_url", host.alias("host"), F.xxhash64(F.coalesce("html", F.lit(""))).alias("key"), "html")
    once, sizes = _distinct(rows)
    known = C.stored(_templates(once, sizes), "templates")
    known = C.stored(known.join(containers(once, known), "host", "left").select("host", "n", "tokens", "most", "agree", "region"), "nested")
    known = C.small(known, weight=F.size("tokens"))
    id_type, url_type = (pages.schema[c].dataType.simpleString() for c in (id_col, url_col))
    joined = rows.join(known, "host", "left").select("_id", "_url", "html", "host", "n", "tokens", "most", "agree", "region")

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("html", lambda: None)
        kept: dict[str, tuple] = {}
        for batch in stream:
            out = []
            for text, host, n, tokens, most, agree, region in zip(batch.column(2), *(batch.column(k).to_pylist() for k in (3, 4)), *(batch.column(k) for k in (5, 6, 7, 8)), strict=True):
                if host not in kept:
                    if len(kept) > 1000:
                        kept.clear()
                    known, nearly = (frozenset(_unsigned(not agree.as_py() and y.as_py() or [])) for y in (tokens, most))
                    kept[host] = (known, nearly if (n or 0) >= SURE_PAGES else frozenset(), nearly, (region.as_py() or 0) & (1 << 64) - 1)
                out.append(Page(text.as_py() or "").main_text(*kept[host]))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.string())], [id_col, url_col, "text"])

    return joined.mapInArrow(step, f"`{id_col}` {id_type}, `{url_col}` {url_type}, text string")


def op2_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract digest of :func:`extract` over ``pages``."""
    return extract(C.table(spark, sf_dir, "pages")).select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
