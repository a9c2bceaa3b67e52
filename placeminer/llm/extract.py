"""Main text of pages by consensus host paths (op 7).

Each page's containers are scored by their running text: letters outside links and outside boilerplate, less a
charge for links. The best one, the deepest with nothing but short or link-heavy text outside it, names the path: its generalised path (tags with their stable classes, no positions or ids)
is the page's vote. Votes are added up per host in Spark, and every page is read again
with the winning path of its host; a page without that path falls back to its own best container.

A path travels as a 64-bit hash of its parent's hash and its own tag and classes, so that it costs the same at any depth.
Of several containers with the winning path the one with most running text is the article, with those that hold at least
``PART`` as much (an article in parts); lesser ones are teasers.

Menus, headers, forms, hidden and tagged boilerplate go. So does what has a boilerplate word as a class, id or role of its own.
A word inside a longer class (``notice-board``, ``side-by-side``) says less: such a container stays if it is the
article or main element, or if it holds most of the page's running text.

Only votes (host, path, score) are shuffled, pre-aggregated, so a host with a third of all pages is no
heavier than others. Winners are broadcast as pairs of numbers while they are at most ``BROADCAST_HOSTS`` (8 MB), and beyond that
joined to the pages by host and a salt.

Edge cases: null or empty html gives an empty text; a null url has the host ``""``; unclosed tags are
closed where a following tag implies it or at the end; broken markup is read as text. Very long and very deep pages are read whole, in
time and memory proportional to their length; repeated rows get repeated results; other columns, whatever their names, are not read.
"""

from __future__ import annotations

import html as refs
from collections.abc import Iterator

import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed

BROADCAST_HOSTS = 500_000
SALTS = 64

#: Tag classes of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template title textarea svg math iframe object select button".split())
SKIP = frozenset("nav header footer aside form dialog menu head".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
CONTAINER = frozenset("article main section div td body".split())
CLOSED_BY = {"p": frozenset("p div ul ol dl table section article main aside header footer nav form h1 h2 h3 h4 h5 h6 blockquote pre figure hr address".split()), "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "tr": frozenset(["tr"]), "td": frozenset(["td", "th", "tr"]), "th": frozenset(["td", "th", "tr"]), "option": frozenset(["option"])}
#: Words in classes and ids of what is not the article.
BOILERPLATE = frozenset(
    "ad ads adv advert adverts advertisement advertising banner promo promotion sponsor sponsored cookie cookies consent gdpr notice notices alert popup modal overlay menu nav navbar navigation breadcrumb breadcrumbs"
    " sidebar side aside widget widgets related recommended recommendations footer header masthead topbar comment comments reply replies respond disqus share sharing social newsletter subscribe subscription login signup"
    " search toolbar pagination pager copyright legal disclaimer paywall tagcloud".split()
)
TOKEN = regex.compile(r"<!--.*?(?:-->|\Z)|<(?P<end>/?)(?P<tag>[a-zA-Z][a-zA-Z0-9:-]*)(?P<attrs>(?:[^<>\"']|\"[^\"]*\"|'[^']*')*+)>|<[!?][^>]*>", regex.S)
ATTRIBUTE = regex.compile(r"""\b(class|id|role|hidden|style|aria-hidden)\b(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", regex.I)
WORDS = regex.compile(r"[a-z]+")
#: First words of classes that tell how a page is laid out.
LAYOUT = frozenset("has no not is with without".split())
ARTICLE = frozenset(["article", "main"])
#: Share of the article's running text from which another container with the winning path is a part of it.
PART = 0.3
HARD, WEAK = 2, 1
#: Characters from which text is running text; shorter blocks are if they end a sentence, and link-heavy ones never.
RUNNING = 40
SENTENCE = tuple(".!?…。！？।؟")


def running(block: str, links: int) -> int:
    """Characters of running text in a block."""
    if len(block) >= RUNNING or block.rstrip("\"'”’»)]").endswith(SENTENCE):
        return max(0, len(block) - 2 * links)
    return 0


def classified(attrs: str) -> tuple[str, int]:
    """The stable class of a tag, and whether its attributes mark boilerplate: ``HARD``, ``WEAK`` or 0."""
    name, bad = "", 0
    for m in ATTRIBUTE.finditer(attrs):
        key, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if key in ("class", "id"):
            for token in value.split():
                words = WORDS.findall(token)
                if token in BOILERPLATE:
                    bad = HARD
                elif words and words[0] not in LAYOUT and not BOILERPLATE.isdisjoint(words):
                    bad = max(bad, WEAK)
            if key == "class":
                name = ".".join(sorted(c for c in value.split() if not any(x.isdigit() for x in c)))
        elif key == "hidden" or (key == "aria-hidden" and value == "true") or (key == "style" and "display:none" in value.replace(" ", "")):
            bad = HARD
        elif key == "role" and value in ("navigation", "banner", "contentinfo", "complementary", "search", "dialog", "alert"):
            bad = HARD
    return name, bad


class Container:
    """A container of a page: the hash of its path, the number of the one around it and of the last one inside, whether it lies in an article."""

    __slots__ = ("path", "outer", "last", "inner")

    def __init__(self, path: int, outer: int, number: int, inner: bool):
        self.path, self.outer, self.last, self.inner = path, outer, number, inner


class Page:
    """Blocks of text of a page and the containers around them."""

    def __init__(self, source: str):
        #: Blocks as (text, link characters, number of the innermost container).
        self.blocks: list[tuple[str, int, int]] = []
        self.containers: list[Container] = [Container(0, -1, 0, False)]
        #: The weakly marked element around each block and around each such element, -1 for none.
        self.weak_of: list[int] = []
        self.weak_outer: list[int] = []
        self._read(source)
        self._settle()

    def _read(self, source: str) -> None:
        stack: list[tuple[str, int, bool, int, int]] = []  # tag, path, boilerplate, container, weakly marked element
        opened: dict[str, int] = {}
        absent: set[str] = set()
        text: list[str] = []
        links = [0, 0]  # characters of links in this block, open links
        seen: dict[str, tuple[str, int]] = {}

        def flush() -> None:
            if text:
                block = " ".join("".join(text).split())
                if block:
                    self.blocks.append((block, links[0], stack[-1][3] if stack else 0))
                    self.weak_of.append(stack[-1][4] if stack else -1)
                text.clear()
            links[0] = 0

        def add(piece: str) -> None:
            if not piece or (stack and stack[-1][2]):
                return
            piece = refs.unescape(piece) if "&" in piece else piece
            text.append(piece)
            if links[1]:
                links[0] += len(piece.strip())

        def drop() -> str:
            tag = stack.pop()[0]
            opened[tag] -= 1
            return tag

        def after(tag: str, at: int) -> int | None:
            """The end of the next closing tag, if there is one."""
            close = None if tag in absent else regex.compile(rf"</{tag}\b[^>]*>", regex.I).search(source, at)
            if close is None:
                absent.add(tag)
                return None
            return close.end()

        def past(tag: str, at: int) -> int:
            """Where a marked inline element ends: at its own closing tag, or where the block around it ends."""
            depth, blocks, now = 1, 0, at
            while (m := find(source, now)) is not None:
                name = (m["tag"] or "").lower()
                if name == tag:
                    depth += -1 if m["end"] else 1
                    if not depth:
                        return m.end()
                elif name and name not in INLINE and name not in VOID:
                    blocks += -1 if m["end"] else 1
                    if blocks < 0:
                        return m.start()
                now = m.end()
            return len(source)

        at, find = 0, TOKEN.search
        while (m := find(source, at)) is not None:
            add(source[at : m.start()])
            at = m.end()
            tag = m["tag"]
            if tag is None:
                continue
            tag = tag.lower()
            if m["end"]:
                if tag in INLINE:
                    if tag == "a":
                        links[1] = 0
                elif opened.get(tag):
                    flush()
                    while drop() != tag:
                        pass
                elif tag == "p":
                    flush()
                continue
            if tag == "br":
                add(" ")
                continue
            if tag in VOID:
                if tag == "hr":
                    flush()
                continue
            if tag in RAW:
                end = after(tag, at)
                at = end if end is not None else (len(source) if tag in ("script", "style") else at)
                continue
            attrs = m["attrs"]
            name, bad = seen.get(attrs) or seen.setdefault(attrs, classified(attrs)) if attrs.strip() else ("", 0)
            if tag in INLINE:
                if bad and not attrs.rstrip().endswith("/"):
                    at = past(tag, at)
                elif tag == "a":
                    links[1] = 1
                continue
            flush()
            links[1] = 0
            while stack and stack[-1][0] in CLOSED_BY and tag in CLOSED_BY[stack[-1][0]]:
                drop()
            _, above, gone, inside, weak = stack[-1] if stack else ("", 0, False, 0, -1)
            path = xxhash.xxh64_intdigest(f"{above}>{tag}.{name}") >> 1
            free = tag in ("html", "body") or (bad == WEAK and tag in ARTICLE)
            gone = gone or tag in SKIP or (bad == HARD and not free and tag not in ARTICLE)
            if not gone and bad and not free:
                self.weak_outer.append(weak)
                weak = len(self.weak_outer) - 1
            if tag in CONTAINER and not gone:
                number = len(self.containers)
                self.containers.append(Container(path, inside, number, self.containers[inside].inner or tag in ARTICLE))
                inside = number
            stack.append((tag, path, gone, inside, weak))
            opened[tag] = opened.get(tag, 0) + 1
        add(source[at:])
        flush()
        for c in range(len(self.containers) - 1, 0, -1):  # outer containers come first
            outer = self.containers[self.containers[c].outer]
            outer.last = max(outer.last, self.containers[c].last)

    def _settle(self) -> None:
        """Drop the blocks of marked elements that do not hold most of the page's running text."""
        if not self.weak_outer:
            return
        run, total = [0] * len(self.weak_outer), 0
        for (block, links, _), w in zip(self.blocks, self.weak_of):
            n = running(block, links)
            total += n
            if w >= 0:
                run[w] += n
        for w in range(len(run) - 1, -1, -1):  # outer elements come first
            if self.weak_outer[w] >= 0:
                run[self.weak_outer[w]] += run[w]
        # Inner elements hold no more than outer ones: the innermost decides.
        self.blocks = [b for b, w in zip(self.blocks, self.weak_of) if w < 0 or 2 * run[w] > total]

    def _scores(self) -> tuple[list[float], list[int]]:
        own, run = [0.0] * len(self.containers), [0] * len(self.containers)
        for block, links, c in self.blocks:
            own[c] += len(block) - 2 * links
            run[c] += running(block, links)
        for c in range(len(own) - 1, 0, -1):
            own[self.containers[c].outer] += own[c]
            run[self.containers[c].outer] += run[c]
        return own, run

    def best(self) -> tuple[int, float]:
        """The deepest container outside which the page has no running text, and its score.

        What is left outside is measured against the whole page, so that nested containers cannot add up to a loss;
        inside an article not even a short sentence is left.
        """
        own, run = self._scores()
        best = 0
        for c in range(1, len(own)):
            most = run[c] >= RUNNING or own[c] >= 0.6 * own[0]
            spared = run[c] == run[best] if self.containers[best].inner else run[0] - run[c] < RUNNING
            if own[c] > 0 and most and spared and self._within(c, best):
                best = c
        return best, own[best]

    def _within(self, c: int, outer: int) -> bool:
        return outer <= c <= self.containers[outer].last

    def chosen(self, path: int | None) -> list[int]:
        """The containers whose blocks are the text, given the path that won the host's vote."""
        best = self.best()[0]
        named = [i for i, c in enumerate(self.containers) if path and c.path == path]
        if not named:
            return [best]
        own, run = self._scores()
        first = max(named, key=lambda i: (run[i], own[i], -i))
        parts = [i for i in named if i == first or (run[i] and run[i] >= PART * run[first])]
        # Running text of this page's article beside the host's containers belongs to it.
        if self.containers[best].inner and all(self._within(i, best) for i in parts):
            return [best]
        return parts

    def text(self, path: int | None = None) -> str:
        """Text of the containers with the path, or of the best container."""
        inside = [False] * len(self.containers)
        for i in self.chosen(path):
            inside[i] = True
        for i, c in enumerate(self.containers):
            inside[i] = inside[i] or (c.outer >= 0 and inside[c.outer])
        found = "\n".join(b for b, _, c in self.blocks if inside[c])
        return found if found or not path else self.text()


def host(url: str = "url"):
    return F.lower(F.coalesce(F.regexp_extract(F.col(url), r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1), F.lit("")))


def votes(pages: DataFrame) -> DataFrame:
    """host, path, pages: the winning path of each host, as a hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: dict[tuple[str, int], list[int]] = {}
            for h, source in zip(batch.column("host").to_pylist(), batch.column("html").to_pylist()):
                page = Page(source or "")
                c, score = page.best()
                if c and score > 0:
                    one = out.setdefault((h, page.containers[c].path), [0, 0])
                    one[0] += 1
                    one[1] += int(score)
            yield pa.RecordBatch.from_arrays(
                [pa.array([k[0] for k in out], pa.string()), pa.array([k[1] for k in out], pa.int64()), pa.array([v[0] for v in out.values()], pa.int64()), pa.array([v[1] for v in out.values()], pa.int64())], names=["host", "path", "pages", "score"]
            )

    cast = pages.select(host().alias("host"), "html").mapInArrow(run, "host string, path long, pages long, score long")
    summed = cast.groupBy("host", "path").agg(F.sum("pages").alias("pages"), F.sum("score").alias("score"))
    return summed.groupBy("host").agg(F.max_by("path", F.struct("pages", "score", "path")).alias("path"), F.sum("pages").alias("pages"))


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every row."""
    spark = pages.sparkSession
    winners = checkpointed(votes(pages).select(F.xxhash64("host").alias("host"), "path"))
    few = winners.limit(BROADCAST_HOSTS + 1).toArrow()
    small = len(few) <= BROADCAST_HOSTS
    shared = spark.sparkContext.broadcast(dict(zip(few.column("host").to_pylist(), few.column("path").to_pylist())) if small else None)
    rows = pages.select("page_id", "url", "html", F.xxhash64(host()).alias("__host"))
    if small:
        rows = rows.withColumn("__path", F.lit(None).cast("long"))
    else:
        salted = winners.select(F.col("host").alias("__host"), F.col("path").alias("__path"), F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("__salt"))
        rows = rows.withColumn("__salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int")).join(salted, ["__host", "__salt"], "left").select("page_id", "url", "html", "__host", "__path")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        for batch in batches:
            hosts, paths = batch.column("__host").to_pylist(), batch.column("__path").to_pylist()
            texts = [Page(s).text(known.get(h) if known is not None else p) if s else "" for s, h, p in zip(batch.column("html").to_pylist(), hosts, paths)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("page_id").cast(pa.int64()), batch.column("url"), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["page_id", "url", "text", "n_chars"]
            )

    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
