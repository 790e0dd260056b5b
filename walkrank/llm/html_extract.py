"""Main text of web pages by consensus of host paths.

A first pass scores each page's containers (text outside links, what kind of element it is) and reports
the generalised paths (tags with all their class names and ids, digits masked) of all that hold text. Paths are told apart by their depth and a
digest of the whole path. Spark sums these votes per host
and picks the winning path, the larger sum first, ties to the shallower path, then to the lesser digest. A second pass takes every page's
containers on its host's winning path; a page that has none falls back to its own best container.

Elements that never are main text (navigation, page headers and footers, side bars, notices, adverts, forms,
scripts, styles, reader comments) are left out with all that they hold, inline ones too; names are told by whole words (BAD_WORDS). An article or
post around the winner is taken whole, with its lead. A block is the text between the borders
of block elements; its character references are decoded, its white space becomes one space, blocks without text vanish.

Null or empty html gives an empty text; so does a page whose text is all boilerplate. Pages with a null or
malformed url share one host without a name. Repeated rows give repeated results; extra columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from hashlib import blake2b

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkrank.llm.common import arrow_map, cut
from walkrank.llm.urlfilter import host_of

SALTS = 64
#: Winning paths of at most so many hosts are broadcast.
SMALL = 200_000
TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|textarea|svg|iframe)\b(?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+>.*?(?:</\1\s*>|\Z)"
    r"|<[!?][^>]*+>|</([a-zA-Z][^\s>/]*+)[^>]*+>|<([a-zA-Z][^\s>/]*+)((?:(?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+|[^>]*+))>",
    re.S | re.I,
)
ATTRIBUTE = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
#: Fixed lists of element names.
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img picture source meta link input math mi mn mo ms mtext mspace mrow mfrac msqrt mroot mstyle merror mpadded mphantom mfenced menclose msub msup msubsup munder mover munderover mmultiscripts mprescripts none mtable mtr mtd maction semantics annotation annotation-xml".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
NEVER = frozenset("head nav footer aside form button select option menu dialog audio video canvas map frameset noframes title".split())
CONTAINERS = frozenset("body div article main section td center blockquote content".split())
#: Fixed lists of words: a name (class or id) marks boilerplate if all of its words are in these and one is in the first.
BAD_WORDS = frozenset("ad ads adv advert adverts advertisement advertising adsense banner sponsor sponsored sponsors promo promos promotion nav navbar navigation menu menus breadcrumb breadcrumbs sidebar aside footer header masthead cookie cookies consent notice notices alert alerts popup modal overlay newsletter subscribe subscription signup login search share sharing sharebar social related recommend recommended recommendations comment comments commentlist disqus reply replies respond widget widgets toolbar pagination pager copyright side legal".split())
FILLERS = frozenset("a an the of to and by box boxes bar bars block blocks button buttons link links list lists item items wrap wrapper container inner outer area section sections panel slot unit top bottom left right main site page global primary secondary footer header head content contents body text title posts post articles article entry entries icon icons form field media row col column group holder region module zone label message us on in js id block first last more policy terms small large mobile desktop fixed sticky results".split())
BAD_ROLE = frozenset("navigation banner contentinfo complementary search form dialog alert".split())
WORD = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|[^\W\d_]+")
#: Names of what holds a whole article, its lead included.
WHOLE = frozenset("article post entry story hentry".split())
GOOD_NAME = re.compile(r"article|content|post|entry|story|main|body|text", re.I)


@dataclass
class Page:
    """A page's blocks in order, and its containers."""

    blocks: list[tuple[int, str]] = field(default_factory=list)
    parents: list[int] = field(default_factory=list)
    #: Depth and digest of the whole path, so neither names nor levels are cut off and deep pages stay small.
    paths: list[str] = field(default_factory=list)
    #: The last step of each path.
    steps: list[str] = field(default_factory=list)
    scores: list[float] = field(default_factory=list)


def _named(attributes: str) -> tuple[str, str]:
    """(class and id, role) of an element."""
    names, role = [], ""
    for kind, a, b, c in ATTRIBUTE.findall(attributes):
        if kind.lower() == "role":
            role = (a or b or c).lower()
        else:
            names.append(a or b or c)
    return " ".join(names), role


def _boilerplate(names: str, inner: bool = False) -> bool:
    """Whether one of the names consists of boilerplate words, with or without fillers. "market-share" doesn't, "share-buttons" does. A header
    inside an article (inner), or named after one, is its own."""
    for name in names.split():
        words = [w.lower() for w in WORD.findall(name)]
        own = inner or not WHOLE.isdisjoint(words)
        if any(w in BAD_WORDS and not (own and w == "header") for w in words) and all(w in BAD_WORDS or w in FILLERS for w in words):
            return True
    return False


def _path(above: str, step: str, depth: int) -> str:
    return f"{depth:06d}:{blake2b(f'{above}/{step}'.encode('utf-8', 'replace'), digest_size=16).hexdigest()}"


def parse(text: str | None) -> Page:
    page = Page([], [-1], [_path("", "", 0)], [""], [0.0])
    # open block elements: (tag, container, left out)
    stack: list[tuple[str, int, bool]] = [("", 0, False)]
    buffer: list[str] = []
    linked, in_link = 0, False
    # open inline elements that are left out, and those of their kind inside
    muted: list[str] = []

    def close() -> None:
        nonlocal linked
        muted.clear()
        if buffer:
            block = " ".join(entities.unescape("".join(buffer)).split())
            tag, at, out = stack[-1]
            if block and not out:
                page.blocks.append((at, block))
                page.scores[at] += max(0, len(block) - 2 * linked) * (0.5 if tag in ("li", "td", "th", "dd", "dt") else 1.0)
            buffer.clear()
        linked = 0

    text = text or ""
    pos = 0
    for m in TOKEN.finditer(text):
        if m.start() > pos and not muted:
            piece = text[pos : m.start()]
            buffer.append(piece)
            linked += len(piece) if in_link else 0
        pos = m.end()
        ended, began = m.group(2), m.group(3)
        if began:
            tag = began.lower()
            if tag == "br":
                buffer.append("\n")
            elif tag in INLINE:
                in_link = True if tag == "a" else in_link
                if muted:
                    muted.extend([tag] * (tag == muted[0]))
                elif m.group(4) and tag not in VOID:
                    names, role = _named(m.group(4))
                    if role in BAD_ROLE or _boilerplate(names):
                        muted.append(tag)
            elif tag in VOID:
                close()
            else:
                close()
                in_link = False
                if stack[-1][0] in ("p", "h1", "h2", "h3", "h4", "h5", "h6") or (tag in ("li", "td", "tr", "dt", "dd") and stack[-1][0] == tag):
                    stack.pop()  # these don't hold blocks: the end tag was left out
                _, at, out = stack[-1]
                names, role = _named(m.group(4))
                inner = any(t in ("article", "main") for t, _, _ in stack)
                out = out or tag in NEVER or (tag == "header" and not inner) or role in BAD_ROLE or (bool(names) and tag not in ("body", "html", "article", "main") and _boilerplate(names, inner))
                if tag in CONTAINERS and not out:
                    step = tag + "".join("." + re.sub(r"\d+", "#", x) for x in sorted(names.split()))
                    above = page.paths[at]
                    page.parents.append(at)
                    page.paths.append(_path(above, step, int(above.partition(":")[0]) + 1))
                    page.steps.append(step)
                    page.scores.append(0.0)
                    at = len(page.parents) - 1
                stack.append((tag, at, out))
        elif ended:
            tag = ended.lower()
            if tag in INLINE:
                in_link = False if tag == "a" else in_link
                if muted and tag == muted[0]:
                    muted.pop()
            else:
                close()
                in_link = False
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k][0] == tag:
                        del stack[k:]
                        break
    if pos < len(text) and not muted:
        rest = text[pos:]
        broken = re.search(r"<[a-zA-Z/!]", rest)  # a tag that never ends isn't text
        buffer.append(rest[: broken.start()] if broken else rest)
    close()
    return page


def ranked(page: Page) -> list[tuple[float, str]]:
    """(score, path) of the page's containers with text, the best first; paths of one kind are summed."""
    total = page.scores[:]
    for k in range(len(total) - 1, 0, -1):
        total[page.parents[k]] += 0.6 * total[k]
    found: dict[str, float] = {}
    for k, path in enumerate(page.paths):
        if total[k] > 0:
            last = page.steps[k]
            prior = 3.0 if last.startswith(("article", "main")) else 1.5 if GOOD_NAME.search(last.partition(".")[2]) else 1.0
            found[path] = found.get(path, 0.0) + total[k] * prior
    return sorted(((s, p) for p, s in found.items()), key=lambda x: (-x[0], x[1]))


def _holds_article(step: str) -> bool:
    tag, *names = step.split(".")
    return tag == "article" or any(words and set(words) <= WHOLE | FILLERS and set(words) & WHOLE for words in ({w.lower() for w in WORD.findall(n)} for n in names))


def main_text(page: Page, path: str | None) -> str:
    """Text of the containers on `path`, or of the page's best container if there are none."""
    if path is None or path not in page.paths:
        best = ranked(page)
        if not best:
            return ""
        path = best[0][1]
    # what holds a whole article holds its lead, which may lie beside the winner
    starts = set()
    for k, p in enumerate(page.paths):
        if p == path:
            while page.parents[k] > 0 and _holds_article(page.steps[page.parents[k]]):
                k = page.parents[k]
            starts.add(k)
    inside = [False] * len(page.paths)
    for k in range(len(page.paths)):
        inside[k] = k in starts or (k > 0 and inside[page.parents[k]])
    return "\n\n".join(t for at, t in page.blocks if inside[at])


def votes(pages: DataFrame) -> DataFrame:
    """(host, path, vote): all containers with text, a page's best with vote 1000; summed for each host over a batch."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                b = whole.slice(at, 256)
                found: Counter = Counter()
                for host, text in zip(b.column("host").to_pylist(), b.column("html")):
                    best = ranked(parse(text.as_py()))
                    for score, path in best:
                        found[host, path] += round(1000 * score / best[0][0])
                hosts, paths = zip(*found) if found else ((), ())
                yield pa.RecordBatch.from_arrays([pa.array(hosts, pa.string()), pa.array(paths, pa.string()), pa.array(found.values(), pa.int64())], names=["host", "path", "vote"])

    return arrow_map(pages.select("host", "html"), work, "host string, path string, vote bigint")


def winners(found: DataFrame) -> DataFrame:
    """(host, path): the path with the most votes per host."""
    summed = found.groupBy("host", "path").agg(F.sum("vote").alias("vote"))
    return summed.groupBy("host").agg(F.min(F.struct((-F.col("vote")).alias("v"), "path")).alias("w")).select("host", F.col("w.path").alias("path"))


def extract(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) for every row of pages (page_id, url, html)."""
    rows = pages.select("page_id", "url", F.col("html").cast("string").alias("html"), F.coalesce(host_of(F.col("url").cast("string")), F.lit("")).alias("host"))
    best = cut(winners(votes(rows)))
    if best.limit(SMALL + 1).count() <= SMALL:  # a row a host, of bounded width: pages stay where they are
        met = rows.join(F.broadcast(best), "host", "left").select("page_id", "url", "html", "path")
    else:
        salted = best.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        dealt = rows.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int"))
        met = dealt.join(salted, ["host", "salt"], "left").select("page_id", "url", "html", "path")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                b = whole.slice(at, 256)
                texts = [main_text(parse(t.as_py()), p) for t, p in zip(b.column("html"), b.column("path").to_pylist())]
                yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    kinds = dict(rows.dtypes)
    return arrow_map(met, work, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars bigint")
