"""Main text of web pages by a maximum-scoring subsequence.

A page is read as a row of tokens, words and tags. Words score positive, tags
cost what labelled pages say about them: the log odds of standing inside the
main text rather than outside. One linear scan finds the contiguous region with the largest sum. It
grows to the ends of the article or other element that it lies in, and its
blocks, without what sits in boilerplate elements, are the text.
"""

from __future__ import annotations

import html
import math
import re
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reachgraph.llm.common import bound_batches, table

#: Element names of HTML, by what they do to the text around them.
BLOCKS = frozenset(
    "address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form"
    " h1 h2 h3 h4 h5 h6 header hr html li main menu nav ol p pre section summary table tbody tfoot thead tr ul".split()
)
SPACES = frozenset("br td th caption option".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style title textarea noscript template iframe svg noframes xmp object canvas audio video".split())
#: Elements that never hold main text, wherever they stand.
OUT = frozenset("nav footer aside form menu dialog button select label head".split())
#: Words of class, id and role that mark an element as not main text, also as a part of a longer name.
OUT_WORDS = frozenset(
    "ad ads advert adverts advertisement advertising adsense sponsor sponsored promo cookie cookies consent gdpr popup modal menu menubar"
    " nav navbar navigation breadcrumb breadcrumbs sidebar widget widgets footer comment comments disqus newsletter subscribe pagination".split()
)
#: Words that do so alone or beside words of layout only, as they also name what a text is about.
ALONE_WORDS = frozenset(
    "promotion banner notice notices alert overlay aside respond replies reply share sharing social related recommended subscription"
    " signup login search pager toolbar skip complementary contentinfo masthead hidden".split()
)
LAYOUT_WORDS = frozenset("site page post posts article articles story stories link links box bar list block container wrapper section area items item top bottom left right main bottom buttons icons form".split())
HEADER_WORDS = frozenset(("header", "topbar", "site-header"))

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^>\"'])*)(>|\Z)", re.S)
_ATTR = re.compile(r"""([a-zA-Z_:][-\w:.]*)\s*(?:=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""")
_SPLIT = re.compile(r"[^a-z0-9]+")
_MAIN = re.compile(r"<(/?)(article|main)(?=[\s/>])[^>]*>", re.I)

#: Labelled pages: what comes before the main text, the main text, what comes after it.
LABELLED = (
    ("<html><body><nav><ul><li><a>Home</a></li><li><a>News</a></li></ul></nav><div>Top</div><article>",
     "<h1>A title</h1><p>One <b>two</b> three<br>four.</p><p>Five six.</p><h2>Part</h2><p>Seven <a>eight</a> nine.</p><ul><li>First.</li><li>Second.</li></ul><aside><p>Aside.</p></aside><p>Ten.</p><form><label>Mail</label></form><p>Eleven.</p>",
     "</article><footer><p>Imprint</p></footer></body></html>"),
    ("<html><body><div><ul><li><a>Start</a></li><li><a>About</a></li></ul></div><main>",
     "<h1>Name</h1><p>Text <i>of</i> it.</p><blockquote><p>Said so.</p></blockquote><ol><li>First point made.</li><li>Second.</li></ol><p>End.</p>",
     "</main><div><a>Next</a><a>Back</a></div><div><ul><li><a>Other</a></li></ul></div></body></html>"),
    ("<html><body><table><tr><td><a>In</a></td><td><a>Out</a></td></tr></table><section>",
     "<h2>Head</h2><p>Some <em>more</em> words.</p><pre>x = 1</pre><p>And <strong>so</strong> on.</p><h3>Last</h3><p>Bye.</p>",
     "</section><div><span><a>Share</a></span></div></body></html>"),
    ("<html><body><div><a>Up</a></div><div>",
     "<div>First of the texts.</div><div>Second of them.</div><div>Third, with <a>one link</a> in it.</div><table><tr><th>Year</th><td>1999</td></tr><tr><th>Year</th><td>2001</td></tr></table><div>After it.</div>",
     "</div><div><a>Top</a></div></body></html>"),
)

#: What a word scores, one in a link, and by how much log odds count; a tag scores from ``LOWEST`` to 0.
WORD_SCORE, LINK_SCORE, UNIT, LOWEST = 1.0, 0.2, 2.0, -8.0


def tokens(page: str) -> Iterator[tuple[str, str, str]]:
    """(kind, name or text, attributes) with kind text, open or close; raw elements and comments are left out."""
    at, end = 0, len(page)
    while at < end:
        m = _TOKEN.search(page, at)
        if not m:
            yield "text", page[at:], ""
            return
        if m.start() > at:
            yield "text", page[at : m.start()], ""
        at = m.end()
        if not m[2] or not m[4]:  # comment, declaration, or cut off within a tag
            continue
        name = m[2].lower()
        if not m[1] and name in RAW and not m[3].endswith("/"):
            stop = re.compile(rf"</{name}(?=[\s/>]|\Z)[^>]*(?:>|\Z)", re.I).search(page, at)
            at = stop.end() if stop else end
            continue
        yield ("close" if m[1] else "open"), name, m[3]


def _marks(name: str, in_article: bool) -> bool:
    """Whether one name of class, id or role stands for something other than main text."""
    parts = [w for w in _SPLIT.split(name) if w]
    if any(w in OUT_WORDS for w in parts) or name in HEADER_WORDS and not in_article:
        return True
    return any(w in ALONE_WORDS for w in parts) and all(w in ALONE_WORDS or w in LAYOUT_WORDS for w in parts)


def boilerplate(name: str, attributes: str, in_article: bool) -> bool:
    """Whether an element holds no main text, by its name and its class, id and role."""
    if name in OUT or name == "header" and not in_article:
        return True
    if not attributes or name in ("html", "body", "main"):
        return False
    for key, value in _ATTR.findall(attributes):
        key = key.lower()
        if key == "hidden" or key == "aria-hidden" and "true" in value:
            return True
        if key in ("class", "id", "role") and any(_marks(n, in_article) for n in value.strip("\"'").lower().split()):
            return True
    return False


def marked(page: str) -> Iterator[tuple[str, str, bool]]:
    """(kind, name or text, out) of all tokens; ``out`` marks those of boilerplate elements."""
    skip, depth, article = "", 0, 0
    for kind, name, attributes in tokens(page):
        if skip:
            if kind == "text":
                yield kind, name, True
                continue
            if name == skip:
                depth += 1 if kind == "open" and not attributes.endswith("/") else -1 if kind == "close" else 0
                if skip in ("p", "li", "dt", "dd", "option") and kind == "open":
                    depth -= 1  # its start ends the element before it
                if depth > 0:
                    yield kind, name, True
                    continue
                skip = ""
                if kind == "close":
                    yield kind, name, True
                    continue
            elif skip == "p" and name in BLOCKS or name in ("body", "html") and kind == "close":
                skip = ""
            else:
                yield kind, name, True
                continue
        if kind == "open" and name not in VOID and boilerplate(name, attributes, article > 0):
            if not attributes.endswith("/"):
                skip, depth = name, 1
            yield kind, name, True
            continue
        if name in ("article", "main") and kind != "text":
            article += 1 if kind == "open" else -1
        yield kind, name, False


def tag_counts(before: str, inside: str, after: str) -> dict[str, tuple[int, int]]:
    """By tag, how often it stands outside and inside the main text of a labelled page; what boilerplate elements hold does not count."""
    seen: dict[str, list[int]] = {}
    for part, k in ((before, 0), (inside, 1), (after, 0)):
        for kind, name, out in marked(part):
            if kind != "text" and (name in OUT or not out):
                seen.setdefault(f"{kind} {name}", [0, 0])[k] += 1
    return {tag: (out, inn) for tag, (out, inn) in seen.items()}


def labelled_parts(page: str) -> tuple[str, str, str] | None:
    """A page that says itself where its main text is, by one article or main element, as (before, main text, after)."""
    found = list(_MAIN.finditer(page))
    if len(found) != 2 or found[0][1] or not found[1][1] or found[0][2].lower() != found[1][2].lower():
        return None
    return page[: found[0].end()], page[found[0].end() : found[1].start()], page[found[1].start() :]


def weights_of(counts: dict[str, tuple[int, int]], unit: float = UNIT) -> dict[str, float]:
    """Score of each tag: scaled log odds of standing inside the main text rather than outside, never positive."""
    return {tag: max(LOWEST, min(0.0, unit * math.log((inn + 0.5) / (out + 0.5)))) for tag, (out, inn) in counts.items()}


def fit_weights(labelled: Iterable[tuple[str, str, str]], more: dict[str, tuple[int, int]] | None = None) -> dict[str, float]:
    """Scores of tags from labelled pages (before, main text, after) and from further counts.

    Tags that were never seen score slightly negative.
    """
    total: dict[str, tuple[int, int]] = dict(more or {})
    for parts in labelled:
        for tag, (out, inn) in tag_counts(*parts).items():
            a, b = total.get(tag, (0, 0))
            total[tag] = (a + out, b + inn)
    return weights_of(total)


def best_region(scores: list[float]) -> tuple[int, int]:
    """Start and end of the contiguous region with the largest sum; the first such, (0, 0) if none is positive."""
    best = (0.0, 0, 0)
    total, start = 0.0, 0
    for i, s in enumerate(scores):
        if total <= 0:
            total, start = 0.0, i
        total += s
        if total > best[0]:
            best = (total, start, i + 1)
    return best[1], best[2]


def _elements(kept: list[tuple[str, str, bool]]) -> list[tuple[str, int, int]]:
    """(name, start, end) of the block elements; those that are never closed end with the element around them."""
    out, stack = [], []
    for i, (kind, name, _) in enumerate(kept):
        if kind == "text" or name not in BLOCKS or name in VOID:
            continue
        if kind == "open":
            stack.append((name, i))
        elif any(name == n for n, _ in stack):
            while True:
                n, at = stack.pop()
                out.append((n, at, i + (n == name)))
                if n == name:
                    break
    return out + [(n, at, len(kept)) for n, at in stack]


def whole_region(kept: list[tuple[str, str, bool]], start: int, end: int) -> tuple[int, int]:
    """The region up to the ends of the articles it has text of, or else of the main element.

    Where there is neither, the region grows to the ends of the innermost
    element around it, on each side where no link stands in between.
    """
    if start == end:
        return start, end
    elements = _elements(kept)
    for wanted in ("article", "main"):
        touched = [(lo, hi) for name, lo, hi in elements if name == wanted and any(kind == "text" and not out and what.strip() for kind, what, out in kept[max(lo, start) : min(hi, end)])]
        if touched:
            return min(start, *(lo for lo, _ in touched)), max(end, *(hi for _, hi in touched))
    lo, hi = max(((lo, hi) for name, lo, hi in elements if lo <= start and hi >= end and name != "html"), default=(start, end))
    if ("open", "a", False) not in kept[lo:start]:
        start = lo
    if ("open", "a", False) not in kept[end:hi]:
        end = hi
    return start, end


def scores_of(kept: list[tuple[str, str, bool]], weights: dict[str, float]) -> list[float]:
    """Words score, less in links and nothing in boilerplate elements; tags cost what their weights say."""
    scores, link = [], False
    for kind, what, out in kept:
        if kind == "text":
            scores.append(0.0 if out else len(what.split()) * (LINK_SCORE if link else WORD_SCORE))
            continue
        if what == "a":
            link = kind == "open"
        elif what in BLOCKS:
            link = False
        scores.append(weights.get(f"{kind} {what}", -0.5))
    return scores


def extract(page: str | None, weights: dict[str, float]) -> str:
    """Main text of one page: its blocks in page order, two line feeds between them."""
    kept = list(marked(page or ""))
    start, end = whole_region(kept, *best_region(scores_of(kept, weights)))
    blocks, now = [], []
    for kind, what, out in kept[start:end]:
        if kind == "text":
            if not out:
                now.append(html.unescape(what))
        elif what in BLOCKS:
            blocks.append("".join(now))
            now = []
        elif what in SPACES:
            now.append(" ")
    blocks.append("".join(now))
    return "\n\n".join(b for b in (" ".join(b.split()) for b in blocks) if b)


def _count_tags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("tag", pa.string()), ("out", pa.int64()), ("inn", pa.int64())])
    for batch in batches:
        rows = [(tag, *n) for page in batch.column("html").to_pylist() if (parts := labelled_parts(page)) for tag, n in tag_counts(*parts).items()]
        columns = list(zip(*rows, strict=True)) or [[]] * 3
        yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def fit_on_pages(pages: DataFrame, *, id_col: str = "page_id", html_col: str = "html", fit_rows: int = 400) -> dict[str, float]:
    """Scores of tags from the given labelled pages and from at most ``fit_rows`` pages of the table.

    The sample is chosen by a hash of the ids; of its pages those count that name
    their main text by one article or main element. Their tags count as one
    page in ten does, so that pages of one make do not drown the others.
    """
    bound_batches(pages.sparkSession)
    ids = pages.select(F.col(id_col).cast("long").alias("_id")).where("_id is not null").distinct().orderBy(F.xxhash64("_id"), "_id").limit(fit_rows)
    some = pages.select(F.col(id_col).cast("long").alias("_id"), F.col(html_col).cast("string").alias("html")).where("html is not null")
    some = some.join(F.broadcast(ids), "_id").select("html")
    rows = some.mapInArrow(_count_tags, "tag string, out long, inn long").groupBy("tag").agg(F.sum("out").alias("out"), F.sum("inn").alias("inn"))
    return fit_weights(LABELLED, {r.tag: (r.out / 10, r.inn / 10) for r in rows.orderBy("tag").collect()})


def _extract(weights: dict[str, float]):
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [extract(page, weights) for page in batch.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column("page_id"), batch.column("url"), pa.array(texts, type=pa.string()), pa.array(map(len, texts), type=pa.int64())], schema=schema
            )

    return run


def extract_pages(
    pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", weights: dict[str, float] | None = None
) -> DataFrame:
    """page_id, url, text, n_chars: one row per page, in no order.

    A null or empty page, and one without main text, gives an empty text. Null
    ids and urls stay null, repeated rows stay repeated, other columns are not
    read, very long pages are read whole, an empty table gives an empty result.
    Pages may be cut off anywhere, also within a tag or a reference. Without
    ``weights`` these are fitted first, by ``fit_on_pages``.
    """
    bound_batches(pages.sparkSession)
    weights = weights or fit_on_pages(pages, id_col=id_col, html_col=html_col)
    chosen = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return chosen.mapInArrow(_extract(weights), "page_id long, url string, text string, n_chars long")
