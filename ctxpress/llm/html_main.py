"""Main text of web pages by the distribution of text over line blocks.

Markup is stripped to lines, one for each block element; what its markup names as menu, header, footer, sidebar, notice,
advert, form, script, style or comment leaves empty lines behind. Text lengths are summed over a sliding window of lines. Text
surges where a window first holds something and dives where windows are empty again; what stands between is kept if the
window sums get high enough. Lines inside and outside articles are surveyed apart; the side with more text is the main one,
where that of articles counts double. A name alone never drops the element that holds all articles of a page or, on pages
without one, most of the text.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

WINDOW, SURGE, GAP = 3, 60, 3

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:\"[^\"]*\"|'[^']*'|[^>\"'])*)(>|\Z)", re.S)
ATTRIBUTE = re.compile(r"""([a-zA-Z_:][-\w:.]*)\s*(?:=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
PART = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])|\d+")

# Elements and names by their role in a page.
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
DROPPED = frozenset("script style textarea title xmp iframe noembed noframes noscript template head nav footer aside form menu dialog button select svg math canvas object audio video map datalist fieldset search".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset("address article blockquote body center caption dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul aside".split())
OPTIONAL_END = {"p": BLOCKS, "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "tr": frozenset(["tr", "tbody"]), "td": frozenset(["td", "th", "tr"]), "th": frozenset(["td", "th", "tr"])}
ROLES = frozenset("navigation banner contentinfo complementary search dialog alertdialog alert form menu menubar toolbar note".split())
NAMES = frozenset(
    "ad ads adv advert adverts advertisement advertising advertorial adslot adsense sponsor sponsored sponsors promo promos promotion banner nav navbar navigation menu menus submenu sidebar sidebars breadcrumb breadcrumbs "
    "footer header masthead topbar cookie cookies consent gdpr notice notices alert alerts popup modal overlay newsletter subscribe subscription signup login signin share sharing social related recommended recommendations "
    "comment comments commentlist respond reply replies disqus discussion pagination pager toolbar widget widgets skip outbrain taboola copyright disclaimer paywall feedback".split()
)
KEPT = frozenset(["article", "main", "body", "html", "h1"])


def attributes(raw: str) -> dict[str, str]:
    return {m[1].lower(): html.unescape(m[2] or m[3] or m[4] or "") for m in ATTRIBUTE.finditer(raw)}


def is_boilerplate(tag: str, raw: str, in_article: bool) -> bool:
    if tag in DROPPED:
        return True
    if tag == "header":
        return not in_article
    if not raw or tag in ("html", "body"):
        return False
    a = attributes(raw)
    if "hidden" in a or a.get("aria-hidden", "").lower() == "true" or "display:none" in a.get("style", "").replace(" ", "").lower():
        return True
    if a.get("role", "").lower() in ROLES:
        return True
    return is_named(tag, a, in_article)


def is_named(tag: str, a: dict[str, str], in_article: bool) -> bool:
    if tag in KEPT and not (tag == "article" and in_article):
        return False
    return any(p.lower() in NAMES for k in ("class", "id") for p in PART.findall(a.get(k, "")))


class _Lines:
    """Lines of text with what is known of each: inside an article, and how much of it is link text."""

    def __init__(self):
        self.text, self.marked, self.linked = [], [], []
        self.now, self.link = [], 0

    def close(self, marked: bool) -> None:
        t = " ".join(html.unescape("".join(self.now)).split())
        if t:
            self.text.append(t)
            self.marked.append(marked)
            self.linked.append(self.link / len(t))
        self.now, self.link = [], 0

    def gap(self) -> None:
        self.text += [""] * GAP
        self.marked += [False] * GAP
        self.linked += [0.0] * GAP


def _tokens(page: str) -> list[tuple]:
    """(start, end, tag, closing, attributes); a raw element is one token up to its end tag."""
    out, at = [], 0
    while m := TOKEN.search(page, at):
        tag = (m[2] or "").lower()
        at = m.end()
        if tag in RAW and not m[1] and not m[3].endswith("/"):
            end = re.compile(rf"</{tag}\s*[^>]*(?:>|\Z)", re.I).search(page, at)
            at = end.end() if end else len(page)
            out.append((m.start(), at, "", False, ""))
        else:
            out.append((m.start(), at, tag, bool(m[1]), m[3] or ""))
    return out


def _closings(tokens: list[tuple]) -> dict[int, int]:
    """For each token that opens an element, the index after the one that closes it; one pass, however much is left open."""
    opened, out = {}, {}
    for j, (_, _, tag, closing, _) in enumerate(tokens):
        if tag and not closing:
            opened.setdefault(tag, []).append(j)
        elif tag and opened.get(tag):
            out[opened[tag].pop()] = j + 1
    return out


def _end_of(tokens: list[tuple], i: int, closings: dict[int, int]) -> int:
    """Index after the element that opens at token i; i + 1 if it is never closed."""
    tag, depth, until = tokens[i][2], 0, OPTIONAL_END.get(tokens[i][2])
    if not until and tag != "head":
        return closings.get(i, i + 1)
    for j in range(i, len(tokens)):
        other, closing = tokens[j][2], tokens[j][3]
        if other == tag:
            depth += -1 if closing else 1
            if depth == 0:
                return j + 1
        if j > i and until and ((other in until and not closing) or (closing and other in BLOCKS and other != tag)):
            return j
        if tag == "head" and other == "body":
            return j
    return i + 1


class _Shares:
    """How much text and how many articles lie before each token."""

    def __init__(self, page: str, tokens: list[tuple]):
        ends = [0, *(t[1] for t in tokens)]
        texts = [len(page[e:t[0]].strip()) for e, t in zip(ends, tokens)]
        self.text = np.r_[0, np.cumsum(texts, dtype=np.int64)]
        self.articles = np.r_[0, np.cumsum([t[2] == "article" and not t[3] for t in tokens], dtype=np.int64)]
        self.whole = self.text[-1] + len(page[ends[-1] :].strip())

    def is_main(self, i: int, j: int) -> bool:
        """Whether tokens i to j hold all articles or, where there are none, over half of the text."""
        if self.articles[-1]:
            return self.articles[j] - self.articles[i] == self.articles[-1]
        return (self.text[j] - self.text[i + 1]) * 2 > self.whole


def by_name_only(tag: str, raw: str, in_article: bool) -> bool:
    """Boilerplate, but for its class and id it would not be."""
    a = attributes(raw)
    bare = " ".join(f'{k}="{v}"' for k, v in a.items() if k not in ("class", "id") and '"' not in v)
    return is_named(tag, a, in_article) and not is_boilerplate(tag, bare, in_article)


def lines_of(page: str) -> _Lines:
    lines, tokens, at, i, article, link = _Lines(), _tokens(page), 0, 0, 0, 0
    shares = closings = None
    while i < len(tokens):
        start, end, tag, closing, raw = tokens[i]
        piece = page[at:start]
        lines.now.append(piece)
        if link:
            lines.link += len(piece.strip())
        at, i = end, i + 1
        if not tag:
            continue
        if not closing and tag not in VOID and not raw.endswith("/") and is_boilerplate(tag, raw, article > 0):
            closings = _closings(tokens) if closings is None else closings
            j = _end_of(tokens, i - 1, closings)
            spared = False
            if j > i and tag != "article" and by_name_only(tag, raw, article > 0):
                shares = shares or _Shares(page, tokens)
                spared = article == 0 and shares.is_main(i - 1, j)
            if not spared and (j > i or tag in DROPPED):
                if tag in BLOCKS or tag in DROPPED:
                    lines.close(article > 0)
                    lines.gap()
                at = max(at, tokens[j - 1][1] if tokens[j - 1][3] or j == i else tokens[j][0])
                i = j
                continue
        if tag in BLOCKS:
            lines.close(article > 0)
            if tag == "article":
                article = max(0, article + (-1 if closing else 1))
        elif tag == "br":
            lines.now.append(" ")
        elif tag == "a":
            link = max(0, link + (-1 if closing else 1))
    lines.now.append(page[at:])
    lines.close(article > 0)
    return lines


def main_lines(text: list[str], marked: list[bool], linked: list[float], window: int = WINDOW, surge: int = SURGE) -> list[int]:
    """Lines between the first surge and the last dive, of those inside or those outside articles, where there is more text.

    Where markup has named boilerplate, and inside articles, any text left is a surge.
    """
    plain = surging_lines([0 if k > 0.6 or m else len(t) for t, m, k in zip(text, marked, linked)], window, 1 if "" in text else surge)
    own = surging_lines([len(t) if m else 0 for t, m in zip(text, marked)], window, 1)
    return own if own and 2 * sum(len(text[i]) for i in own) >= sum(len(text[i]) for i in plain) else plain


def surging_lines(sizes: list[int], window: int, surge: int) -> list[int]:
    own = np.array(sizes)
    if not own.any():
        return []
    sums = np.convolve(own, np.ones(window, int))[window - 1 :]  # of the line and those after it
    filled = np.r_[False, own > 0, False]
    back = np.convolve(filled.astype(int), np.ones(window, int))[: len(filled)]
    ahead = np.convolve(filled.astype(int)[::-1], np.ones(window, int))[: len(filled)][::-1]
    busy = (back > 0) & (ahead > 0)
    edge = np.flatnonzero(np.diff(np.r_[0, busy[1:-1].astype(int), 0]))
    # stretches whose empty runs are shorter than the window
    high = [(lo, hi) for lo, hi in edge.reshape(-1, 2).tolist() if sums[lo:hi].max() >= surge]
    return [i for i in range(high[0][0], high[-1][1]) if own[i]] if high else []


def main_text(page: str | None) -> str:
    """The article's blocks in page order, two line feeds apart; empty for null, empty and textless pages."""
    if not page:
        return ""
    lines = lines_of(page)
    keep = main_lines(lines.text, lines.marked, lines.linked)
    if not keep:  # nothing surges: a short page is all there is
        keep = [i for i, t in enumerate(lines.text) if t and lines.linked[i] <= 0.6]
    return "\n\n".join(lines.text[i] for i in keep)


def extract_main_text(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) for every row of ``pages`` (page_id, url, html); other columns are left out."""

    def f(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [main_text(h.as_py()) for h in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    kind = pages.schema["page_id"].dataType.simpleString()
    return pages.select("page_id", "url", "html").mapInArrow(f, f"page_id {kind}, url string, text string, n_chars long")


def op4_main_text(spark, sf_dir: str) -> DataFrame:
    """All rows of ``pages``; null, empty, broken and very long pages give what ``main_text`` says, rows are neither lost nor merged."""
    return extract_main_text(spark.read.parquet(f"{sf_dir}/pages.parquet"))
