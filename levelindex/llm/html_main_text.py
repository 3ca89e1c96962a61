"""Main text of web pages: the contiguous region of tokens with the largest sum of weights.

A page becomes words and tags.  A word counts by the kind of element it stands in, a tag by its
name: weights are log-odds of being inside the article, learned from pages whose own markup labels
the article (`article` or `main`), over a prior that words are positive, tags negative, and words
in navigation, forms, notices, adverts or comments negative.  One scan finds the region
with the largest sum; inside it the words with negative weight are left out again.

Character references are decoded, white space inside a block becomes one space, blocks are joined
by one space.  Scripts, styles and comments never give words.  The fit uses at most `label_pages`
pages, picked by a hash of their address and key.  Cases: null or empty html gives an empty text;
unclosed and stray tags are allowed; repeated rows are kept.
"""

from __future__ import annotations

import html
import math
import re
from collections import Counter, defaultdict
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelindex.llm.common import small_batches

# Element names by their role in HTML.
RAW = ("script", "style", "noscript", "template", "iframe", "textarea", "select", "button", "option", "title", "head")
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
LEADING = frozenset("nav header footer aside form dialog menu fieldset".split())
LABELS = ("article", "main")
#: Parts of class names, ids and roles that mark what is not the article.
SIGNS = re.compile(r"(?:^|[^a-z])(?:ad|ads|advert\w*|banner|sponsor\w*|promo\w*|nav\w*|menu\w*|breadcrumb\w*|sidebar\w*|aside|footer\w*|header|masthead|cookie\w*|consent\w*|notice\w*|popup\w*|modal\w*|newsletter\w*|subscribe\w*|comment\w*|discussion|disqus\w*|respons(?:e|es)|replies|reply|share\w*|social\w*|related|recommend\w*|widget\w*|toolbar\w*|login\w*|search|hidden|legal|copyright)(?:$|[^a-z])", re.I)
TOKEN = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[(.*?)\]\]>|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|([^<]+|<(?![a-zA-Z/!?]))", re.S)
#: Where TOKEN fails: an end tag without a name up to its ">", and a tag with a quote left open up to the next ">".
LOOSE = re.compile(r"(?:</(?![a-zA-Z])[^>]*|<()(/?)([a-zA-Z][^\s/>]*)([^>]*)((?!))?)>")
NAMES = re.compile(r"""\b(class|id|role)\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+)""", re.I)
HIDDEN = re.compile(r"""\bhidden\b|display\s*:\s*none|aria-hidden\s*=\s*["']?true""", re.I)


@dataclass(frozen=True)
class HtmlSettings:
    label_pages: int = 1500
    prior: float = 8.0
    word: float = 1.0
    tag: float = -0.3
    outside: float = -0.4
    seed: int = 3


def kind_of(name: str, attributes: str) -> str | None:
    """A container's kind, if words in it must be told from others."""
    if name in LEADING:
        return name
    if name in LABELS:
        return None
    if attributes:
        for _, value in NAMES.findall(attributes):
            if found := SIGNS.search(value.strip("\"'")):
                return "." + found.group(0).strip(" \"'-_").lower()
        if HIDDEN.search(attributes):
            return ".hidden"
    return None


def tokens_of(page: str):
    """Text pieces and tags in order: (kind of container or "", piece, tag name or None, inside a labelled article)."""
    open_: list[tuple[str, str | None, bool]] = []
    kind, labelled, at, n = "", 0, 0, len(page)
    while at < n:
        m = TOKEN.match(page, at) or LOOSE.match(page, at)
        if m is None and page.startswith("</", at) and not re.match("[a-zA-Z]", page[at + 2 : at + 3]):  # no tag follows
            begin, at = at, n if (found := page.find("<", at + 1)) < 0 else found
            yield kind, html.unescape(page[begin:at]), None, labelled > 0
            continue
        if m is None:  # an unfinished tag at the end of the page
            break
        at = m.end()
        cdata, close, name, attributes, text = m.groups()
        if text is not None:
            yield kind, html.unescape(text), None, labelled > 0
            continue
        if name is None:
            if cdata:
                yield kind, cdata, None, labelled > 0
            continue
        name = name.lower()
        if close:
            for i in range(len(open_) - 1, -1, -1):
                if open_[i][0] == name:
                    labelled -= sum(x[0] in LABELS for x in open_[i:])
                    del open_[i:]
                    break
            else:
                yield kind, "", name, labelled > 0
                continue
            kind = next((x[1] for x in reversed(open_) if x[1]), "")
            yield kind, "", name, labelled > 0
            continue
        if name in RAW:
            end = re.compile(rf"</{name}\b[^>]*>", re.I).search(page, at)
            if name != "head" and not attributes.rstrip().endswith("/"):
                at = end.end() if end else n
            elif name == "head" and end:
                at = end.end()
            yield kind, "", name, labelled > 0
            continue
        if name not in VOID and not attributes.rstrip().endswith("/"):
            own = kind_of(name, attributes)
            # elements without a needed end tag would pile up; only containers matter for the kind
            if own or name in LABELS or name not in INLINE and name != "p":
                open_.append((name, own, False))
            labelled += name in LABELS
            kind = own or kind
        yield kind, "", name, labelled > 0


class Weights:
    def __init__(self, words: dict[str, float], tags: dict[str, float], s: HtmlSettings):
        self.words, self.tags, self.s = words, tags, s

    def word(self, kind: str) -> float:
        return self.words.get(kind, self.s.outside if kind else self.s.word)

    def tag(self, name: str) -> float:
        return self.tags.get(name, self.s.tag)


def learn(pages: list[str], s: HtmlSettings) -> Weights:
    """Log-odds of words by kind and of tags by name, inside against outside labelled articles."""
    seen: dict[str, Counter] = {"w": Counter(), "t": Counter()}
    total = Counter()
    for page in pages:
        rows = list(tokens_of(page))
        if not any(r[3] for r in rows):
            continue
        for kind, text, name, inside in rows:
            group, key, n = ("w", kind, len(text.split())) if name is None else ("t", name, 1)
            seen[group][key, inside] += n
            total[group, inside] += n
    out = defaultdict(dict)
    for group, base in (("w", s.word), ("t", s.tag)):
        ends = (s.word * 2, s.outside * 2) if group == "w" else (0.0, s.tag * 2)
        for key in {k for k, _ in seen[group]}:
            inside, outside = seen[group][key, True], seen[group][key, False]
            start = s.outside if group == "w" and key else base
            odds = math.log((inside + 1) / (outside + 1))
            weight = (s.prior * start + (inside + outside) * odds) / (s.prior + inside + outside)
            out[group][key] = min(max(weight, ends[1]), ends[0] if group == "t" or not key else s.outside / 4)
    if "" in out["w"]:
        out["w"][""] = max(out["w"][""], s.word / 2)
    return Weights(dict(out["w"]), dict(out["t"]), s)


def main_text(page: str, weights: Weights) -> str:
    """Text of the best region, negative words left out."""
    pieces, best, run, begin, keep = [], 0.0, 0.0, 0, (0, 0)
    for kind, text, name, _ in tokens_of(page):
        if name is None:
            w = weights.word(kind)
            pieces.append((text, w > 0, False))
            run += w * len(text.split())
        else:
            pieces.append(("", False, name not in INLINE))
            run += weights.tag(name)
        if run <= 0:
            run, begin = 0.0, len(pieces)
        elif run > best:
            best, keep = run, (begin, len(pieces))
    out = []
    for text, good, block in pieces[keep[0] : keep[1]]:
        if block:
            out.append(" ")
        elif good:
            out.append(text)
    return " ".join("".join(out).split())


def extract(pages: DataFrame, s: HtmlSettings = HtmlSettings(), id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    rows = pages.select(pages[id_col].cast("long").alias("page_id"), pages[url_col].cast("string").alias("url"), F.coalesce(pages[html_col].cast("string"), F.lit("")).alias("html"))
    labelled = rows.where(F.lower("html").rlike("<(article|main)[ >]"))
    hashed = labelled.withColumn("h", F.xxhash64("url", "page_id", F.lit(s.seed)))
    some = hashed.select("h").distinct().orderBy("h").limit(s.label_pages)
    sample = hashed.join(F.broadcast(some), "h", "left_semi").groupBy("h").agg(F.min("html").alias("html"))
    weights = learn([r.html for r in sample.toLocalIterator()], s)
    words, tags = weights.words, weights.tags

    def run(batches):
        own = Weights(words, tags, s)
        for batch in small_batches(batches, "html"):
            texts = [main_text(h or "", own) for h in batch.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], ["page_id", "url", "text", "n_chars"])

    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
