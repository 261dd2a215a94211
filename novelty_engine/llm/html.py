"""Main text of a page as the maximum-scoring run of its tokens.

A page becomes a sequence of words and tags.  Words score +1 and tags score below zero; the tag
weights are learned from labelled pages (pages whose own `<article>` or `<main>` element marks
the main text): the more a tag occurs outside marked regions, the more it costs.  One linear
scan (best contiguous sum) finds the content region.  Short blocks at its edges that cost more
than their words are taken back in: the region grows over headings, paragraphs, quotes, figures and
tables that lie beside it in the same parent, over lists too where an element marks the text and past
unwanted elements between them, until another kind of block begins.  Within it, words of elements that are never main text
(menus, forms, notices, adverts, comment sections, scripts, styles) are left out: by element, or by
class, id and role of container elements.  White space in a block becomes one space, and blocks are
joined by two newlines.

Learning counts tags on the executors, in a bounded sample of at most `sample` distinct pages with the
least hashes; only the counts of the elements named here reach the driver.  Extraction reads
whole pages: null, empty or wordless html gives an empty text; a quote opens a value only after an
equals sign, as browsers have it, and one that never closes is an ordinary character; unclosed
tags, comments and scripts reach to the end of their element or of the page.
"""

from __future__ import annotations

import html as markup
import re
from collections import Counter
from collections.abc import Iterator
from math import log

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ship, slices, table

_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:=\s*+(?:"[^"]*"|'[^']*')|[^>=]++|=)*+)(?:>|\Z)|<[!?/][^>]*(?:>|\Z)|[^<]+|<""", re.DOTALL)
_ATTRIBUTE = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.IGNORECASE)
#: HTML elements by their role.
_RAW = {"script", "style", "noscript", "template", "textarea", "title", "iframe", "svg", "math", "xmp"}
_BOILERPLATE = {"nav", "footer", "aside", "form", "head", "button", "select", "menu", "dialog", "object"}
_INLINE = set("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q ruby rb rp rt s samp small span strike strong sub sup time tt u var wbr input meta link".split())
_VOID = set("area base br col embed hr img input link meta param source track wbr".split())
_MARKED = {"article", "main"}
_UNWANTED = re.compile(r"(?:^|[\s_-])(?:ads?|advert\w*|banner|breadcrumbs?|comments?|consent|cookies?|disqus|footer|header|menu|nav\w*|newsletter|notices?|popup|promo\w*|related|respond|share|sharing|sidebar|social|sponsor\w*|subscribe|toolbar|widget)(?:$|[\s_-])", re.IGNORECASE)
#: Elements whose class, id or role may call them unwanted, and blocks that a region may grow over.
_CONTAINERS = set("div section ul ol dl table header fieldset details center iframe ins figure tr td".split())
_TEXT_BLOCKS = set("p h1 h2 h3 h4 h5 h6 blockquote pre figure figcaption table hr address".split())
_LISTS = set("ul ol li dl dt dd table thead tbody tr td th".split())
WORD, DEFAULT_TAG, STEEP, LEAST = 1.0, -2.0, 4.0, 0.05
#: Least weight of list and table tags, and of tags that mark no main text.
LIST_FLOOR, FLOOR = -4.0, -12.0


def tokens(page: str) -> Iterator[tuple[str, str, bool]]:
    """(tag, text, unwanted): tag is '' for text, 'name' or '/name' for tags."""
    at, end = 0, len(page)
    open_unwanted: list[str] = []
    depth: Counter[str] = Counter()
    marked = 0
    while at < end:
        found = _TOKEN.match(page, at)
        at = found.end()
        name = found.group(2)
        if name is None:
            text = found.group(0)
            if not text.startswith(("<!", "<?", "</")):
                yield "", text, bool(open_unwanted)
            continue
        name, closing = name.lower(), bool(found.group(1))
        if name in _MARKED:
            marked = max(0, marked + (-1 if closing else 1))
        if closing:
            within = bool(open_unwanted)
            if name in depth and depth[name] > 0 and open_unwanted:
                depth[name] -= 1
                if not depth[name] and open_unwanted[-1] == name:
                    open_unwanted.pop()
                    depth = Counter({open_unwanted[-1]: 1}) if open_unwanted else Counter()
            yield "/" + name, "", within
            continue
        if name in _RAW:
            close = re.compile(rf"</{re.escape(name)}\s*(?:>|\Z)", re.IGNORECASE).search(page, at)
            at = close.end() if close else end
            yield name, "", True
            continue
        if name in _VOID or found.group(3).rstrip().endswith("/"):
            yield name, "", bool(open_unwanted)
            continue
        if open_unwanted:
            if name == open_unwanted[-1]:
                depth[name] += 1
            elif name in _MARKED and open_unwanted[-1] in ("head", "nav", "header"):  # an unclosed head or menu ends where the article begins
                open_unwanted.clear()
                depth.clear()
        elif name in _BOILERPLATE or name == "header" and not marked or name in _CONTAINERS and any(_UNWANTED.search(next(filter(None, x), "")) for x in _ATTRIBUTE.findall(found.group(3))):
            open_unwanted.append(name)
            depth = Counter({name: 1})
        yield name, "", bool(open_unwanted)


_KNOWN = _RAW | _BOILERPLATE | _INLINE | _VOID | _MARKED | _CONTAINERS | _TEXT_BLOCKS | _LISTS | {"html", "body", "header"}


def tag_counts(page: str) -> Counter[tuple[str, bool]]:
    """How often each known tag stands inside (True) and outside the region that a page marks itself; nothing if it marks none."""
    seen = [(tag, unwanted) for tag, _, unwanted in tokens(page) if tag]
    out: Counter[tuple[str, bool]] = Counter()
    if not any(tag in _MARKED for tag, _ in seen):
        return out
    level = 0
    for tag, unwanted in seen:
        name = tag.lstrip("/")
        if name in _MARKED:
            out[tag, False] += 1
            level = max(0, level + (-1 if tag[0] == "/" else 1))
        elif name in _KNOWN:
            out[tag, bool(level and not unwanted)] += 1
    return out


def weights_of(counts: dict[tuple[str, bool], int]) -> dict[str, float]:
    """Weight of each tag from its counts; a tag without counts weighs DEFAULT_TAG."""
    out = {}
    for tag in {tag for tag, _ in counts}:
        name = tag.lstrip("/")
        weight = -max(LEAST, 1.0 + STEEP * log((counts.get((tag, False), 0) + 1) / (counts.get((tag, True), 0) + 1)))
        out[tag] = weight if name in _MARKED else max(weight, LIST_FLOOR if name in _LISTS else FLOOR)
    return out


def learn(pages: list[str]) -> dict[str, float]:
    """Weight of each tag from pages that mark their main text themselves."""
    return weights_of(sum(map(tag_counts, pages), Counter()))


def _grown(sequence: list[tuple[str, str, bool]], first: int, last: int) -> tuple[int, int]:
    """The region with the text blocks beside it in the same parent."""
    marked = sum(1 if t in _MARKED else -1 if t[:1] == "/" and t[1:] in _MARKED else 0 for t, _, _ in sequence[:first]) > 0 or any(t in _MARKED for t, _, _ in sequence[first:last])
    grows = _TEXT_BLOCKS | _LISTS | _INLINE if marked else _TEXT_BLOCKS | _INLINE

    def walk(at: int, step: int) -> int:
        """Furthest place reached over whole blocks; stops at another kind of tag or at the parent's end, and passes by unwanted elements."""
        reached, level = at, 0
        while 0 <= at < len(sequence):
            tag, _, unwanted = sequence[at]
            name = tag.lstrip("/")
            if unwanted:
                at += step
                continue
            if tag and name not in grows:
                break
            if tag and name not in _VOID and name not in ("p", "li", "dt", "dd", "tr", "td", "th"):  # these may lack an end tag
                level += step if tag[0] != "/" else -step
            if level < 0:
                break
            at += step
            if not level:
                reached = at
        return reached

    return walk(first - 1, -1) + 1, walk(last, 1)


def main_text(page: str | None, weights: dict[str, float]) -> str:
    if not page:
        return ""
    run, start, best, region, sequence = 0.0, 0, 0.0, (0, 0), []
    for tag, text, unwanted in tokens(page):
        if tag:
            score = weights.get(tag, DEFAULT_TAG)
            if tag.lstrip("/") in _INLINE:
                score = max(score, -LEAST)
        elif unwanted:
            score = 0.0
        else:
            text = markup.unescape(text)
            score = WORD * len(text.split())
        sequence.append((tag, text, unwanted))
        if run <= 0:
            run, start = 0.0, len(sequence) - 1
        run += score
        if run > best:
            best, region = run, (start, len(sequence))
    if best > 0:
        region = _grown(sequence, *region)
    blocks, block = [], []
    for tag, text, unwanted in sequence[slice(*region)]:
        if not tag:
            if not unwanted:
                block.append(text)
        elif tag == "br":
            block.append(" ")
        elif tag.lstrip("/") in ("td", "th"):
            block.append(" ")
        elif tag.lstrip("/") not in _INLINE and block:
            blocks.append(block)
            block = []
    blocks.append(block)
    return "\n\n".join(filter(None, (" ".join("".join(x).split()) for x in blocks)))


def train(pages: DataFrame, key: str = "page_id", html: str = "html", sample: int = 400) -> dict[str, float]:
    """Weights from the tags of at most `sample` distinct pages."""
    ship(pages.sparkSession)
    rows = pages.where(F.col(html).isNotNull()).select(F.xxhash64(F.col(key), F.col(html), F.lit(11)).alias("h"), F.col(html).alias("html"))
    chosen = [r["h"] for r in rows.select("h").distinct().orderBy("h").limit(sample).collect()]
    if not chosen:
        return {}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "html"):
            counts = sum(map(tag_counts, batch.column("html").to_pylist()), Counter())
            yield pa.RecordBatch.from_arrays([pa.array([t for t, _ in counts], pa.string()), pa.array([i for _, i in counts], pa.bool_()), pa.array(list(counts.values()), pa.int64())], ["tag", "inside", "n"])

    once = rows.where(F.col("h") <= chosen[-1]).dropDuplicates(["h"]).select("html")
    found = once.mapInArrow(run, "tag string, inside boolean, n bigint").groupBy("tag", "inside").agg(F.sum("n").alias("n"))
    return weights_of({(r["tag"], r["inside"]): r["n"] for r in found.collect()})


def extract(pages: DataFrame, weights: dict[str, float], key: str = "page_id", html: str = "html", keep: tuple[str, ...] = ()) -> DataFrame:
    """(key, *keep, text, n_chars) for every row."""
    names = (key, *keep)
    kept = ", ".join(f"k{i} {pages.schema[c].dataType.simpleString()}" for i, c in enumerate(names))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "html"):
            texts = [main_text(x, weights) for x in batch.column("html").to_pylist()]
            columns = [n for n in batch.schema.names if n != "html"]
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in columns), pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], [*columns, "text", "n_chars"])

    ship(pages.sparkSession)
    out = pages.select(*(F.col(c).alias(f"k{i}") for i, c in enumerate(names)), F.col(html).alias("html")).mapInArrow(run, f"{kept}, text string, n_chars bigint")
    return out.withColumnsRenamed({f"k{i}": c for i, c in enumerate(names)})


def op3_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return extract(pages, train(pages), keep=("url",))
