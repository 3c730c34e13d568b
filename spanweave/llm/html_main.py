"""Main text of web pages by the maximum-scoring subsequence of weighted tokens.

A page is read as a stream of tokens, words and block tags.  A word's score is the probability that it is content, from
weights learned on labelled pages of the word itself and of the elements and classes around it, less one half; a tag's score
is zero or negative, the more the rarer it is within content.  One linear scan finds the contiguous run of tokens with the
greatest sum; as blocks are kept or left as a whole, a run begins and ends with a block.  The run is the text, but for the
elements in it that are not the article's by what they are (menus, headers and footers of the page, sidebars, notices, adverts, forms,
comments): those are taken out of the page before it is read as article text, and break a run only by a small, bounded amount.

Labelled pages are those whose own markup names the content (an article or main element): a bounded sample of pages
(``SAMPLE``, by hash) is counted, words inside against words outside, by the word and by the names of the elements and classes
around it.

Defined results: a null, empty or word-free page has an empty text; broken markup is read as browsers do for the common
cases (unclosed paragraphs and list items end at the next block, stray end tags are ignored, an open end closes at the end);
character references are decoded; text of script, style, template and similar elements never counts.  Repeated rows give
repeated results; extra columns are not read.
"""

from __future__ import annotations

import html as markup
import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Labelled pages that weights come from, occurrences that a name or word needs, and letters of a word that is counted.
SAMPLE, LEAST_SEEN, LONGEST_TERM = 1000, 20, 40

# Element names by their role.
#: Left out with all they hold; those of the second line to the end of the page where they are never closed.
HIDDEN = frozenset("noscript template svg select option button head".split())
RAW = frozenset("script style textarea title iframe".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CONTENT = frozenset(("article", "main"))
WHOLE = frozenset(("html", "body", "article", "main"))
NEVER = frozenset("nav aside footer form menu dialog search fieldset".split())
#: Words of class, id and role values that name what an article is not.
ASIDE = frozenset("ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments commentlist consent cookie cookies disclaimer discussion disqus footer gdpr login menu modal nav navbar navigation navigasi newsletter notice notices overlay pager pagination popup promo promoted promotion related replies reply respond share sharing sidebar signup skip social sponsor sponsored subscribe subscription teaser toolbar widget widgets contentinfo complementary".split())

# A tag ends at the first > outside a quoted attribute value; quotes elsewhere are characters like others.
_TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*+)((?>(?:[^>=]++|=\s*+(?:"[^"]*+"|'[^']*+'|))*+))>""", re.S)
_NAMES = re.compile(r"""(?:^|\s)(?:class|id|role)\s*=\s*("[^"]*"|'[^']*'|[^\s>]+)""", re.I)
_HIDDEN = re.compile(r"""(?:^|\s)(?:hidden(?=\s|$|=)|aria-hidden\s*=\s*["']?true|style\s*=\s*["'][^"']*display\s*:\s*none)""", re.I)
_WORD = re.compile(r"[a-z]+")


@dataclass
class Block:
    """Text of one block with the names around it, the tags before it, and whether it lies in a content element or in what is never content."""

    text: str
    names: tuple[str, ...]
    tags: tuple[str, ...]
    inside: bool
    never: bool
    words: list[str] = field(init=False)

    def __post_init__(self) -> None:
        self.words = self.text.lower().split()


@dataclass(eq=False)
class Element:
    """An open element: whether it is never content, or only if it neither holds what is nor most of the page's words."""

    name: str
    names: tuple[str, ...]
    hard: bool
    soft: bool
    holds: bool = False
    words: int = 0


def attribute_names(attributes: str) -> list[str]:
    return [w for value in _NAMES.findall(attributes) for w in value.lower().strip("\"'").split()]


def is_aside(name: str) -> bool:
    """Whether a whole class, id or role value says that: all its parts do, so no-sidebar and comments-open don't."""
    parts = _WORD.findall(name)
    return bool(parts) and ASIDE.issuperset(parts)


def blocks(page: str) -> Iterator[Block]:
    """The blocks of a page in order; white space within one is single, and empty ones are left out."""
    stack: list[Element] = []
    parts: list[str] = []
    tags: list[tuple[str, tuple[Element, ...]]] = []
    found: list[tuple[str, tuple[Element, ...], list[tuple[str, tuple[Element, ...]]]]] = []
    at, end, unclosed = 0, len(page), set()
    last = page.rfind(">") + 1  # no tag ends behind it

    def flush() -> None:
        text = " ".join(markup.unescape("".join(parts)).split())
        parts.clear()
        if text:
            found.append((text, tuple(stack), tags.copy()))
            tags.clear()

    while at < end:
        m = _TAG.search(page, at, last) if at < last else None
        parts.append(page[at : m.start() if m else end])
        if not m:
            break
        at = m.end()
        if m[2] is None:
            continue
        closing, name = bool(m[1]), m[2].lower()
        if (name in RAW or name in HIDDEN) and not closing and not m[3].rstrip().endswith("/"):
            close = None if name in unclosed else re.compile(rf"</{re.escape(name)}\b[^>]*>", re.I).search(page, at)
            if close:
                at = close.end()
            else:
                unclosed.add(name)
                at = end if name in RAW else at
        elif name == "br":
            parts.append(" ")
        elif name in BLOCK:
            flush()
            around = tuple(stack)
            if closing:
                where = next((k for k in range(len(stack) - 1, -1, -1) if stack[k].name == name), None)
                if where is not None:
                    del stack[where:]
            else:
                while stack and stack[-1].name in {"p", "h1", "h2", "h3", "h4", "h5", "h6"} or stack and stack[-1].name == name == "li":
                    stack.pop()
                if name in CONTENT or name == "h1":
                    for e in stack:
                        e.holds = e.holds or name in CONTENT or e.name == "header"
                if name not in VOID:
                    names = attribute_names(m[3])
                    inside = any(e.name in CONTENT for e in stack)
                    hard = name in NEVER and name != "form" or bool(_HIDDEN.search(m[3]))
                    soft = name not in WHOLE and any(map(is_aside, names)) or name == "form" or (name == "header" and not inside)
                    stack.append(Element(name, (f"in:{name}", *(f"is:{n}" for n in names)), hard, soft))
                    around += (stack[-1],)
            tags.append((name, around))
    flush()
    total = 0
    for text, around, _ in found:
        n = len(text.split())
        total += n
        for e in around:
            e.words += n
    never = lambda around: any(e.hard or e.soft and not e.holds and 2 * e.words <= total for e in around)
    held: list[str] = []
    for text, around, before in found:
        held += [t for t, x in before if not never(x)]  # what is left out anyway must not part what stands around it
        names = tuple(dict.fromkeys(n for e in around for n in e.names))
        yield Block(text, names or ("none",), tuple(held), any(e.name in CONTENT for e in around), never(around))
        held = []


@dataclass(frozen=True)
class Weights:
    """Log odds of content for each name around a word and for each word, with those of none, and the score of each tag."""

    prior: float
    names: dict[str, float]
    tags: dict[str, float]
    terms: dict[str, float] = field(default_factory=dict)

    def word(self, b: Block, term: float = 0.0) -> float:
        """Score of one word of a block, -0.5 to 0.5."""
        odds = self.prior + term + sum(self.names.get(n, 0.0) for n in b.names)
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, odds)))) - 0.5

    def words(self, b: Block) -> float:
        """Sum of the scores of a block's words."""
        known = Counter(round(self.terms[w], 1) for w in b.words if w in self.terms)
        return (len(b.words) - known.total()) * self.word(b) + sum(n * self.word(b, t) for t, n in known.items())


def counted(pages: Iterator[str]) -> Counter:
    """(kind, name, inside) -> words for kinds "word", "term" and "name", occurrences for kind "tag"; pages without a content element count nothing."""
    out: Counter = Counter()
    for page in pages:
        found = list(blocks(page))
        if not any(b.inside for b in found):
            continue
        for b in found:
            yes = b.inside and not b.never
            out["word", "", yes] += len(b.words)
            for w in b.words:
                if len(w) <= LONGEST_TERM:
                    out["term", w, yes] += 1
            for n in b.names:
                known = n[3:] in NEVER or is_aside(n[3:])
                # The label itself is no evidence for pages that lack it, and a plain element is not to blame for the advert in it.
                if n[3:] not in CONTENT and (known or not b.never):
                    out["name", n, yes] += len(b.words)
            for t in b.tags:
                out["tag", t, yes] += 1
    return out


def weights_of(counts: dict[tuple[str, str, bool], int]) -> Weights:
    """Smoothed weights; names and words seen too seldom have none.  With nothing counted, every word is content."""
    every = {yes: counts.get(("word", "", yes), 0) + 1.0 for yes in (True, False)}
    names, tags, terms = {}, {}, {}
    for kind, name, _ in counts:
        a, b = counts.get((kind, name, True), 0), counts.get((kind, name, False), 0)
        odds = lambda: math.log((a + 1) / every[True]) - math.log((b + 1) / every[False])  # noqa: B023, E731
        if kind == "name" and a + b >= LEAST_SEEN:
            names[name] = max(-4.0, min(4.0, odds()))
        elif kind == "term" and a + b >= LEAST_SEEN:
            terms[name] = max(-1.0, min(1.0, odds()))
        elif kind == "tag":
            tags[name] = -(b + 0.1) / (a + b + 0.2) if b > a else 0.0
    names |= {f"in:{c}": 4.0 for c in CONTENT}
    return Weights(0.5, names, tags, terms)


def main_text(page: str | None, weights: Weights) -> str:
    """Blocks of the best run, one to a line."""
    found = list(blocks(page)) if page else []
    scores = []
    for b in found:
        total = weights.words(b)
        worth = max(-5.0, 0.1 * -len(b.words)) if b.never else max(-25.0, total)
        scores.append((max(-1.0, sum(weights.tags.get(t, 0.0) for t in b.tags)), worth))
    best, best_run, total, start = 0.0, (0, 0), 0.0, 0
    for k, (tags, worth) in enumerate(scores):
        if total + tags <= 0:
            total, start = 0.0, k
        else:
            total += tags
        total += worth
        if total > best:
            best, best_run = total, (start, k + 1)
    return "\n".join(b.text for b in found[best_run[0] : best_run[1]] if not b.never)


def fit(pages: DataFrame, *, html: str = "html", sample: int = SAMPLE) -> Weights:
    """Weights from at most ``sample`` distinct pages whose markup names the content, those with the smallest hashes.  Only counts by name reach the driver, no pages."""
    hashed = pages.select(F.xxhash64(html).alias("h"), F.col(html).alias("html")).where(F.col("html").rlike(r"(?i)<(?:article|main)\b"))
    last = hashed.select("h").distinct().orderBy("h").limit(sample).agg(F.max("h")).first()[0]
    if last is None:
        return weights_of({})
    few = hashed.where(F.col("h") <= last).dropDuplicates(["h"]).select("html")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: Counter = Counter()
        for batch in batches:
            total += counted(p.as_py() for p in batch.column(0))
        if total:
            kinds, names, inside = zip(*total, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(kinds), pa.array(names), pa.array(inside), pa.array(list(total.values()), pa.int64())], names=["kind", "name", "inside", "n"])

    sums = few.mapInArrow(run, "kind string, name string, inside boolean, n bigint").groupBy("kind", "name", "inside").agg(F.sum("n").alias("n"))
    heard = F.sum("n").over(Window.partitionBy("kind", "name"))
    seen = sums.withColumn("heard", heard).where(~F.col("kind").isin("name", "term") | (F.col("heard") >= LEAST_SEEN)).collect()
    return weights_of({(r["kind"], r["name"], r["inside"]): r["n"] for r in seen})


def extracted(pages: DataFrame, weights: Weights, *, html: str = "html") -> DataFrame:
    """``pages`` with text in place of its html.  No shuffle."""
    kept = [c for c in pages.columns if c not in (html, "text")]
    source = pages.select(*kept, html)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = pa.array([main_text(p.as_py(), weights) for p in batch.column(len(kept))], pa.string())
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], texts], names=[*kept, "text"])

    fields = ", ".join(f"`{c}` {source.schema[c].dataType.simpleString()}" for c in kept)
    return source.mapInArrow(run, f"{fields}{', ' if fields else ''}text string")
