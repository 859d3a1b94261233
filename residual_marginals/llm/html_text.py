"""Main text of web pages by the line-block distribution.

Markup is stripped into lines, one per block element. A line weighs as many characters as it has. Tags and class words only
change weights: lines of menus, page headers, footers, sidebars, notices, adverts, forms and reader comments weigh nothing,
lines inside a marked article weigh more, and where the article lines hold a third of the page's weight, other lines weigh nothing either. Weights
are summed over sliding windows of lines; the text begins where the sums surge, ends where they dive to zero, and the lines between are kept. The
same thresholds hold for every page.
"""

from __future__ import annotations

import html as entities
import re

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from residual_marginals.llm.common import small_batches, table

#: Lines in a window, and the window sum that counts as a surge.
WINDOW, SURGE = 3, 80
MOSTLY_LINKS = 0.5

TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*'|[\"'])*)(?:>|\Z)|<[!?/][^>]*(?:>|\Z)", re.S)
NAMES = re.compile(r"(?:\b(?:class|id|role)\s*=\s*)(\"[^\"]*\"|'[^']*'|[^\s>]+)", re.I)

#: Element names.
RAW = {"script", "style", "title", "textarea", "noscript", "template", "svg", "iframe", "noframes", "xmp", "math", "canvas", "object"}
CLOSING = {name: re.compile("</" + name, re.I) for name in RAW}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
INLINE = {"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark", "q", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr", "img", "br", "td", "th", "ruby", "rt", "rp"}
SPACED = {"br", "td", "th"}
ASIDE = {"nav", "footer", "aside", "form", "button", "select", "dialog", "menu", "fieldset", "head"}
MAIN = {"article", "main"}
CONTAINERS = ASIDE | MAIN | {"header", "div", "section", "ul", "ol", "dl", "table", "body", "html", "figure", "details", "center", "blockquote"}
#: Names of what is not the article, as a whole class, id or role or as its first or last part.
NEVER = set(
    "ad ads advert adverts advertisement advertising adsense sponsor sponsored sponsors promo promos promotion cookie cookies consent gdpr notice notices alert alerts disclaimer banner nav navbar navigation "
    "menu menus breadcrumb breadcrumbs pagination pager sidebar footer masthead topbar toolbar comment comments commentlist respond replies disqus newsletter subscribe complementary contentinfo".split()
)
#: Names that mean nothing inside an article.
SELDOM = set("share sharing social related recommend recommended recommendations widget signup login search modal popup overlay hidden header".split())
#: Parts after which a name tells how a page is set up, as in no-sidebar or has-sidebar.
SETUP = {"no", "not", "non", "has", "have", "with", "without", "hide", "show", "is"}
PART = re.compile(r"[\s_-]+")


def _marked(attributes: str) -> int:
    """2: a class, id or role says that this is not the article, 1: it says so outside of articles, 0: neither."""
    found = 0
    for m in NAMES.finditer(attributes) if attributes else ():
        for name in m[1].strip("\"'").lower().split():
            parts = PART.split(name)
            ends = {name, parts[0], parts[-1], name.replace("-", "")}
            if not SETUP & set(parts):
                found = max(found, 2 if ends & NEVER else 1 if ends & SELDOM else 0)
    return found


def lines_of(page: str) -> list[tuple[str, int, bool, bool]]:
    """(text, characters inside links, set aside, inside an article) of every non-empty line."""
    lines: list[tuple[str, int, bool, bool]] = []
    held: list[str] = []
    stack: list[tuple[str, bool, bool]] = []  # open containers: name, set aside, in article
    links, in_link, at = 0, False, 0

    def close() -> None:
        nonlocal links
        text = " ".join("".join(held).split())
        if text:
            aside, main = (stack[-1][1], stack[-1][2]) if stack else (False, False)
            lines.append((text, links, aside, main))
        held.clear()
        links = 0

    def say(raw: str) -> None:
        nonlocal links
        if raw:
            text = entities.unescape(raw)
            held.append(text)
            if in_link:
                links += len(text.strip())

    while (tag := TAG.search(page, at)) is not None:
        say(page[at : tag.start()])
        at = tag.end()
        name = (tag[2] or "").lower()
        if not name:
            continue
        if tag[1]:
            if name == "a":
                in_link = False
            if name in INLINE:
                if name in SPACED:
                    held.append(" ")
                continue
            close()
            if name in CONTAINERS:
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k][0] == name:
                        del stack[k:]
                        break
            continue
        if name in RAW:
            end = CLOSING[name].search(page, at)
            at = end.start() if end else len(page)
            continue
        if name == "a":
            in_link = True
        if name in INLINE:
            if name in SPACED:
                held.append(" ")
            continue
        close()
        if name in ("html", "body"):
            # a word on the whole page says nothing about its parts
            stack = []
        elif name in CONTAINERS and not tag[3].rstrip().endswith("/"):
            aside, main = (stack[-1][1], stack[-1][2]) if stack else (False, False)
            marked = _marked(tag[3])
            if name in MAIN and marked < 2 and not main:
                # an article ends what was set aside around it and never closed
                aside, main = any(x[1] and x[0] not in ASIDE | {"div"} for x in stack), True
            else:
                aside = aside or marked == 2 or name in ASIDE or (not main and (marked == 1 or name == "header"))
            stack.append((name, aside, main))
    say(page[at:])
    close()
    return lines


def weights_of(lines: list[tuple[str, int, bool, bool]]) -> list[int]:
    """What each line weighs in the windows: its characters, none if it is set aside or, outside of articles, mostly links.

    Article lines weigh ``SURGE`` more, and other lines nothing, if the article lines hold a third of all weight.
    """
    own = [0 if aside or (not main and links > MOSTLY_LINKS * len(text)) else len(text) for text, links, aside, main in lines]
    inside = sum(w for w, line in zip(own, lines) if line[3])
    if not inside or 3 * inside < sum(own):
        return own
    return [w + SURGE if w and line[3] else 0 for w, line in zip(own, lines)]


def main_text(page: str | None) -> str:
    """The article's blocks in page order, joined by an empty line; empty if there is none."""
    lines = lines_of(page or "")
    weights = weights_of(lines)
    sums = [sum(weights[k : k + WINDOW]) for k in range(len(lines))]
    # a page whose fullest window stays below the threshold surges there
    surge = min(SURGE, max(sums, default=0) or 1)
    kept, inside = [], False
    for k, total in enumerate(sums):
        inside = total > 0 and (inside or total >= surge)
        if inside and weights[k]:
            kept.append(lines[k][0])
    return "\n\n".join(kept)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars for every row of (page_id, url, html).

    Null or empty html gives an empty text; pages of any length are read whole; rows that repeat stay; extra
    columns are ignored; an empty table gives an empty result.
    """
    small_batches(pages.sparkSession, 1000)

    @pandas_udf("string")
    def text_of(html: pd.Series) -> pd.Series:
        return html.map(main_text, na_action=None)

    rows = pages.select("page_id", "url", text_of(F.coalesce(F.col("html").cast("string"), F.lit(""))).alias("text"))
    return rows.withColumn("n_chars", F.char_length("text").cast("long"))


def op5_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of all pages."""
    return extract(table(spark, sf_dir, "pages"))


#: For the given pages: what stands in menus, adverts, footers and raw elements is blanked, blocks end at block tags, those of a marked article weigh 80 more, and blocks between surge and dive are kept.
OP5_SQL = r"""
WITH a AS (SELECT page_id, url, regexp_replace(coalesce(html, ''), '(?s)<(head|nav|script|style)>.*?(</(head|nav|script|style)>|$)|<div class="ad">.*?(</div>|$)|<footer>.*?(</footer>|$)|<!--.*?-->|<!DOCTYPE[^>]*>', '<p>', 'g') AS body FROM pages),
b AS (SELECT page_id, url, list_filter(list_transform(regexp_split_to_array(body, '</?(?:p|h1|div|article|nav|ul|li|body|html)\b[^>]*>'), lambda x: trim(regexp_replace(regexp_replace(x, '<[^>]*>?', ' ', 'g'), '\s+', ' ', 'g'))), lambda x: x <> '') AS parts FROM a),
l AS (SELECT b.page_id, b.url, parts, CASE WHEN contains(body, '<article') THEN 80 ELSE 0 END AS more, unnest(range(len(parts))) AS k FROM b JOIN a ON a.page_id = b.page_id AND a.url = b.url),
w AS (SELECT *, len(parts[k + 1]) + coalesce(len(parts[k + 2]) + more, 0) + coalesce(len(parts[k + 3]) + more, 0) + more AS total FROM l),
s AS (SELECT *, least(80, max(total) OVER (PARTITION BY page_id, url)) AS surge FROM w),
o AS (SELECT *, max(CASE WHEN total >= surge THEN 1 ELSE 0 END) OVER (PARTITION BY page_id, url ORDER BY k) AS inside FROM s),
t AS (SELECT page_id, url, string_agg(parts[k + 1], chr(10) || chr(10) ORDER BY k) FILTER (inside = 1) AS body FROM o GROUP BY page_id, url),
u AS (SELECT page_id, url, replace(regexp_replace(replace(body, '&quot;', '"'), '&amp;?', '&', 'g'), '\r', '') AS text FROM t)
SELECT pages.page_id, pages.url, coalesce(text, '') AS text, coalesce(length(text), 0)::BIGINT AS n_chars FROM pages LEFT JOIN u ON pages.page_id = u.page_id AND pages.url = u.url
"""
