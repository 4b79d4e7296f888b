"""Main text of web pages: the contiguous region of tokens with the greatest total score.

Words score positive, those in links less, and tags negative, with weights learnt from labelled pages. What stands in
marked boilerplate (menus, adverts, notices, ...) scores nothing: it is no evidence for the ends of the region, and it
is left out of the text wherever it stands.
"""

from __future__ import annotations

import html as entities
import math
import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from itertools import accumulate

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from .html_labels import LABELLED

#: Elements whose inside is never text; of the raw ones an unclosed one takes the rest of the page, as in browsers.
RAW = frozenset("script style textarea iframe".split())
OPAQUE = RAW | frozenset("title noscript template svg math select button object audio video canvas".split())
#: The inside of a tag. A quoted value may hold `>`; a quote that is never closed is a character like others.
_INSIDE = r"(?:=\s*\"[^\"<>]*+\"|=\s*'[^'<>]*+'|=\s*\"[^\"]*+\"(?=[\s/>])|=\s*'[^']*+'(?=[\s/>])|[^>])*+"
TOKEN = re.compile(rf"<!--(?:-?>|.*?(?:--!?>|\Z))|<!\[CDATA\[.*?(?:\]\]>|\Z)|<(?P<close>/?)(?P<name>[a-z][a-z0-9:-]*)(?P<attrs>{_INSIDE})(?:>|\Z)|<[!?/][^>]*(?:>|\Z)", re.S | re.I)
MARKS = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
#: Elements that end one block and begin another.
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main nav ol option p pre section summary table tbody tfoot thead tr ul".split()
)
BREAK = frozenset("br td th".split())
#: Elements that hold others; these are followed from their start to their end. Others only if they bear a mark.
HOLDER = frozenset("article aside body center details dialog div dl fieldset figure footer form header main nav ol section table tbody td tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: What an element's name, or a word of its class, id or role, says of its inside.
BY_NAME = {"nav": "menu", "menu": "menu", "header": "header", "footer": "footer", "aside": "sidebar", "form": "form", "dialog": "notice"}
BY_MARK = {
    w: kind
    for kind, words in {
        "menu": "nav navbar navigation menu menubar breadcrumb breadcrumbs pagination pager toolbar tabs skip",
        "header": "header masthead topbar logo",
        "footer": "footer contentinfo colophon copyright",
        "sidebar": "sidebar aside complementary widget widgets related recommended rail",
        "ad": "ad ads adv advert advertisement adverts adbox adslot banner sponsor sponsored promo promotion dfp",
        "notice": "cookie cookies consent gdpr notice alert modal popup overlay newsletter subscribe subscription paywall share sharing social",
        "form": "form search searchbox login signup",
        "comments": "comment comments commentlist reply replies respond disqus discussion reviews",
    }.items()
    for w in words.split()
}
#: With one of these words beside it, "header" is that of the article.
OF_CONTENT = frozenset("article content entry main post story title".split())


#: Marks that begin so tell of the layout, not of the element.
OF_LAYOUT = ("has-", "with-", "no-", "without-", "layout-", "col-")


def kind_of(name: str, attrs: str) -> str | None:
    if attrs:
        marks = [t for m in MARKS.finditer(attrs) for t in (m[1] or m[2] or m[3] or "").lower().split() if not t.startswith(OF_LAYOUT)]
        words = {w for t in marks for w in re.split(r"[^a-z0-9]+", t)}
        if name in ("article", "main") and words & OF_CONTENT:
            return None
        for w in sorted(words):
            kind = BY_MARK.get(w)
            if kind and not (kind in ("header", "footer") and words & OF_CONTENT) and name not in ("body", "html"):
                return kind
    return BY_NAME.get(name)


def runs(page: str) -> Iterator[tuple[str, str | None, str, int]]:
    """In page order ("text", kind of the place or None, text, offset), with ("link", ...) for text of links, and
    ("open" | "close" | "opaque", kind of the place, name, offset). A tag that opens or closes boilerplate is of its kind."""
    stack: list[tuple[str, str | None]] = []
    unclosed: set[str] = set()
    at, kind, link = 0, None, False
    while m := TOKEN.search(page, at):
        if m.start() > at:
            yield "link" if link else "text", kind, page[at : m.start()], at
        at, name = m.end(), (m["name"] or "").lower()
        if not name:
            continue
        if name in OPAQUE and not m["close"] and not m["attrs"].endswith("/") and name not in unclosed:
            end = re.compile(rf"</{name}(?=[\s/>])[^>]*>", re.I).search(page, at)
            if end or name in RAW:
                at = end.end() if end else len(page)
                yield "opaque", kind, name, m.start()
                continue
            unclosed.add(name)
        if name == "a" or name in BLOCK:
            link = name == "a" and not m["close"]
        if m["close"]:
            before = kind
            if any(n == name for n, _ in stack):
                while stack.pop()[0] != name:
                    pass
                kind = stack[-1][1] if stack else None
            yield "close", before, name, m.start()
            continue
        if name in BLOCK and stack and stack[-1][0] in ("p", "li", "dt", "dd") and (name == stack[-1][0] or stack[-1][0] == "p"):
            stack.pop()
            kind = stack[-1][1] if stack else None
        own = kind_of(name, m["attrs"])
        if own == "header" and name == "header" and any(n in ("article", "main") for n, _ in stack):
            own = None  # the article's own
        if name in ("article", "main") and own is None and kind in ("ad", "notice", "menu", "header"):
            inner = None  # what was never closed ends here
        else:
            inner = kind or own
        if (name in HOLDER or own) and name not in VOID and not m["attrs"].endswith("/"):
            stack.append((name, inner))
            kind = inner
        yield "open", inner, name, m.start()
    if at < len(page):
        yield "link" if link else "text", kind, page[at:], at


def _ratios(inside: Counter, outside: Counter) -> dict[str, float]:
    n_in, n_out = sum(inside.values()) + 1, sum(outside.values()) + 1
    return {k: math.log((inside[k] + 0.5) / n_in) - math.log((outside[k] + 0.5) / n_out) for k in inside | outside}


def learn(pages: list[tuple[str, str, str]]) -> tuple[dict[str, float], dict[str, float]]:
    """Of pages as (before, content, after): weights of tags by name, always negative, and of words ("text", "link"),
    always positive: log ratios of the shares that the content and the unmarked rest of the pages have of them."""
    tags, words = (Counter(), Counter()), (Counter(), Counter())
    for before, content, after in pages:
        for what, kind, value, at in runs(before + content + after):
            outside = not len(before) <= at < len(before) + len(content)
            if what in ("text", "link"):
                if kind is None:
                    words[outside][what] += len(value.split())
            elif kind is None:
                tags[outside][value] += 1
    weights = {t: max(-2.0, min(-0.1, w)) for t, w in _ratios(*tags).items()}
    return weights, {k: max(0.05, min(1.0, w)) for k, w in _ratios(*words).items()}


learnt_weights = lru_cache(maxsize=1)(lambda: learn(LABELLED))
#: Of a tag that the labelled pages lack.
OTHER_TAG = -0.5


def best_region(gains: list[float]) -> tuple[int, int]:
    """The run (start, end) of the greatest sum, the first and shortest of several; empty if no sum is above 0. Kadane's scan."""
    best, best_at, total, start = 0.0, (0, 0), 0.0, 0
    for i, gain in enumerate(gains):
        if total <= 0:
            total, start = 0.0, i
        total += gain
        if total > best:
            best, best_at = total, (start, i + 1)
    return best_at


#: Share of the region's words that an article element must hold for the region to be taken to its ends.
HELD = 0.8


def _to_block_ends(seen: list, region: tuple[int, int]) -> tuple[int, int]:
    """No block is cut: the region goes on to the next tag that ends a block."""
    a, b = region
    while a and (seen[a - 1][0] in ("text", "link") or seen[a - 1][2] not in BLOCK):
        a -= 1
    while b < len(seen) and (seen[b][0] in ("text", "link") or seen[b][2] not in BLOCK):
        b += 1
    return a, b


def _to_article(seen: list, region: tuple[int, int]) -> tuple[int, int]:
    """The least article element that holds nearly all words of the region, else the region."""
    count = list(accumulate((len(v.split()) if w in ("text", "link") and k is None else 0 for w, k, v, _ in seen), initial=0))
    begun, spans = [], []
    for i, (what, kind, value, _) in enumerate(seen):
        if value == "article" and kind is None:
            if what == "open":
                begun.append(i)
            elif what == "close" and begun:
                spans.append((begun.pop(), i))
    spans += [(i, len(seen)) for i in begun]
    a, b = region
    held = [(s, e) for s, e in spans if count[max(a, min(b, e))] - count[min(b, max(a, s))] >= HELD * (count[b] - count[a])]
    return min(held, key=lambda x: x[1] - x[0], default=region)


def main_text(page: str | None) -> str:
    """Words outside marked boilerplate score positive, tags there negative; one scan finds the region with the greatest
    sum, which is taken to the ends of its blocks, and of an article element that holds nearly all of its words. Of that
    the text outside menus, headers, footers, sidebars, notices, adverts, forms and comments is returned: references
    decoded, white space made one space, blocks joined by two line ends."""
    tag_weights, word_weights = learnt_weights()
    seen = list(runs(page or ""))
    gains = [0.0 if kind else len(value.split()) * word_weights[what] if what in word_weights else tag_weights.get(value, OTHER_TAG) for what, kind, value, _ in seen]
    region = best_region(gains)
    if region[1]:
        region = _to_article(seen, _to_block_ends(seen, region))
    blocks, parts = [], []
    for what, kind, value, _ in seen[slice(*region)]:
        if what in ("text", "link"):
            if kind is None:
                parts.append(entities.unescape(value) if "&" in value else value)
        elif value in BLOCK:
            blocks.append("".join(parts))
            parts = []
        elif value in BREAK:
            parts.append(" ")
    blocks.append("".join(parts))
    return "\n\n".join(b for b in (" ".join(b.split()) for b in blocks) if b)


@F.pandas_udf(StringType())
def _main_texts(pages: pd.Series) -> pd.Series:
    return pages.map(main_text)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per input row: id, url, text, n_chars (code points).

    Null, empty and tag-only pages have an empty text; repeated rows come back as often; no page is cut. Other columns
    are not read; an empty table gives an empty result. Each row is worked on alone, without a shuffle.
    """
    done = pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), _main_texts(F.col(html_col).cast("string")).alias("text"))
    return done.select(F.col("id").alias(id_col), F.col("url").alias(url_col), "text", F.length("text").cast("long").alias("n_chars"))
