"""Secrets in texts, as column expressions only.

Three base kinds are found by pattern.  The method adds strings that look random: candidate runs of a character class are
scanned by a window of fixed width that carries the count of every character of the class's alphabet: a step takes one from
the count of the character that leaves, adds one to that of the character that enters, and changes two terms of the entropy;
a candidate is reported from the start of its first window at or above the class's threshold
to the end of its last, without what base spans cover.  Allow-listed candidates (words, numbers, identifiers of public
forms) are not reported.

Positions come from running sums in blocks of about the square root of the number of matches, and texts are cut from blocks
of fixed length, so a long text with many matches costs little more than in proportion to its length.

Spans are (start, end) in code points, end exclusive.  Defined results: a null text counts as empty, an empty text has no
spans; rows and other columns stay as they are, but for columns that have a result's name, which are replaced.
"""

from __future__ import annotations

import math
import string
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .native import let

# The base kinds with their patterns, in the order in which they are listed.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
BASE = (("assign", ASSIGN), ("access", "AKIA[A-Z0-9]{14,}"), ("hex", "[0-9a-f]{16,}"))
LEAST_VALUE = 12
KINDS = ("assign", "access", "hex", "entropy_hex", "entropy_base64", "entropy_lower", "entropy_upper", "entropy_letters")


#: Candidates that look random and are not secret: canonical UUIDs, hyphened words, dates and times, names of samples; each as a whole.
WORDS = r"^[A-Za-z]+([-_/][A-Za-z]+)*[-_/]?[0-9]{0,4}$"
ALLOW = (r"^[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}$", WORDS, r"^[0-9]{4}-[0-9]{2}-[0-9]{2}([T_-]?[0-9]{2,9}(-?[0-9]{2})*Z?)?$", r"(?i)^([a-z]+[-_/])*(example|sample|placeholder|changeme)([-_/][a-z]+)*[-_/]?[0-9]{0,4}$")


@dataclass(frozen=True)
class CharacterClass:
    """Candidates of one class, made of ``alphabet``: the runs that ``pattern`` matches and ``needs`` accepts; ``width`` characters a window."""

    kind: str
    alphabet: str
    pattern: str
    needs: str
    width: int
    threshold: float
    allow: tuple[str, ...] = ALLOW


CLASSES = (
    # Lower-case runs of this length are base spans as a whole.
    CharacterClass("entropy_hex", string.digits + "ABCDEF", r"(?<![0-9A-Za-z])[0-9A-F]{20,}(?![0-9A-Za-z])", r"(?=.*[0-9])(?=.*[A-F])", 16, 2.6),
    CharacterClass("entropy_base64", string.digits + string.ascii_letters + "+/_-", r"(?<![0-9A-Za-z+/_-])[0-9A-Za-z+/_-]{20,}(?![0-9A-Za-z+/_-])", r"(?=.*[0-9])(?=.*[a-z])(?=.*[A-Z])", 20, 3.6),
    # Digits stand between letters, as they do not in a word with a number after it; G to Z part these from hex.
    CharacterClass("entropy_lower", string.digits + string.ascii_lowercase, r"(?<![0-9A-Za-z+/_-])[0-9a-z]{20,}(?![0-9A-Za-z+/_-])", r"(?=.*[g-z])(?=.*[0-9]+[a-z]+[0-9])", 20, 3.4),
    CharacterClass("entropy_upper", string.digits + string.ascii_uppercase, r"(?<![0-9A-Za-z+/_-])[0-9A-Z]{20,}(?![0-9A-Za-z+/_-])", r"(?=.*[G-Z])(?=.*[0-9]+[A-Z]+[0-9])", 20, 3.4),
    # Letters alone look random when case changes as it does not in joined words.
    CharacterClass("entropy_letters", string.ascii_letters, r"(?<![0-9A-Za-z+/_-])[A-Za-z]{20,}(?![0-9A-Za-z+/_-])", r"(?=.*[A-Z]{2})(?=.*[A-Z][a-z]{1,2}[A-Z])(?=(?:.*[a-z][A-Z]){3})", 20, 3.6, tuple(a for a in ALLOW if a != WORDS)),
)


def running(values: Column, join: Callable[[Column, Column], Column], start: int) -> Column:
    """For each place of an int array, ``join`` over the values up to it.

    Growing an array value by value copies it each time, so it is done within blocks of about the square root of the size.
    """

    def scan(xs: Column, first: Column) -> Column:
        zero = F.struct(first.alias("at"), F.array().cast("array<int>").alias("out"))
        step = lambda acc, x: F.struct(join(acc["at"], x).alias("at"), F.concat(acc["out"], F.array(join(acc["at"], x))).alias("out"))
        return F.aggregate(xs, zero, step, lambda acc: acc["out"])

    def whole(xs: Column) -> Column:
        block = F.ceil(F.sqrt(F.size(xs))).cast("int")
        cut = lambda width: F.transform(F.sequence(F.lit(1), F.size(xs), width), lambda at: F.slice(xs, at, width))

        def by_block(blocks: Column) -> Column:
            totals = F.transform(blocks, lambda b: F.aggregate(b, F.lit(start), join))
            return let(scan(totals, F.lit(start)), lambda upto: F.flatten(F.transform(blocks, lambda b, k: scan(b, F.when(k > 0, F.get(upto, k - 1)).otherwise(F.lit(start))))))

        return F.when(F.size(xs) > 0, let(let(block, cut), by_block)).otherwise(F.array().cast("array<int>"))

    return let(values, whole)


NO_SPANS = "array<struct<start:int,kind:int,end:int>>"


def matches(text: Column, pattern: str) -> Column:
    """array<struct<hit,end>> of the leftmost, non-overlapping matches, from the lengths of matches and of what lies between."""
    hits, gaps = F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.split(text, pattern, -1)
    lengths = lambda p: F.transform(p["hits"], lambda h, k: F.char_length(h) + F.char_length(F.get(p["gaps"], k)))
    return let(F.struct(hits.alias("hits"), gaps.alias("gaps")), lambda p: F.zip_with(p["hits"], running(lengths(p), lambda a, b: a + b, 0), lambda h, e: F.struct(h.alias("hit"), e.alias("end"))))


def span(start: Column, kind: int, end: Column) -> Column:
    return F.struct(start.alias("start"), F.lit(kind).alias("kind"), end.alias("end"))


def pattern_spans(text: Column, pattern: str, kind: int) -> Column:
    """array<struct<start,kind,end>> of the matches."""
    return F.transform(matches(text, pattern), lambda m: span(m["end"] - F.char_length(m["hit"]), kind, m["end"]))


def _guarded(text: Column, guard: str, spans: Column) -> Column:
    """No spans where ``guard`` finds nothing: one scan of the text instead of several."""
    return F.when(text.rlike(guard), spans).otherwise(F.array().cast(NO_SPANS))


def base_spans(text: Column) -> Column:
    (_, assign), (_, access), (_, hexa) = BASE
    # A match whose value is too short is dropped, yet what it covers is not looked at again.
    values = F.regexp_extract_all(text, F.lit(assign), F.lit(2))
    long_enough = let(values, lambda v: F.filter(pattern_spans(text, assign, 0), lambda s, i: F.char_length(F.get(v, i)) >= LEAST_VALUE))
    found = F.concat(
        _guarded(text, r"(?i:password|passwd|secret|token|api_?key)[\"']?\x20*[:=]", long_enough),
        _guarded(text, access, pattern_spans(text, access, 1)),
        _guarded(text, hexa, pattern_spans(text, hexa, 2)),
    )
    return F.sort_array(found)


#: Entropy terms are whole numbers of this fraction, so that adding and taking away leaves no rounding behind.
UNIT = 1 << 40


def hot_part(candidate: Column, alphabet: str, width: int, threshold: float) -> Column:
    """struct<first,last>: offsets of the first and last window at or above the threshold (null: none).

    With S the sum of n log2 n over a window's counts n, its entropy is log2(width) - S / width.  The accumulator carries
    the counts, S and the answer; a step looks up two counts and changes both.
    """
    terms = [round(n * math.log2(n) * UNIT) if n else 0 for n in range(width + 1)]
    weight = lambda n: F.get(F.array(*map(F.lit, map(int, terms))).cast("array<bigint>"), n)
    most = F.lit(int((math.log2(width) - threshold) * width * UNIT) + width).cast("bigint")
    places = F.transform(F.split(candidate, ""), lambda c: F.call_function("locate", c, F.lit(alphabet)) - 1)
    mark = lambda total, at, old: F.when(total <= most, at).otherwise(old)
    none = F.lit(None).cast("int")

    def walk(at: Column) -> Column:
        head = F.slice(at, 1, width)
        counts = F.transform(F.sequence(F.lit(0), F.lit(len(alphabet) - 1)), lambda k: F.size(F.filter(head, lambda p: p == k)))
        with_total = lambda c: let(F.aggregate(c, F.lit(0).cast("bigint"), lambda t, n: t + weight(n)), lambda t: F.struct(c.alias("counts"), t.alias("total"), mark(t, F.lit(0), none).alias("first"), mark(t, F.lit(0), none).alias("last")))

        def step(acc: Column, i: Column) -> Column:
            def moved(ends: Column) -> Column:
                out, into = ends["out"], ends["into"]
                a, b = F.get(acc["counts"], out), F.get(acc["counts"], into)
                total = F.when(out == into, acc["total"]).otherwise(acc["total"] - weight(a) + weight(a - 1) - weight(b) + weight(b + 1))
                counts = F.when(out == into, acc["counts"]).otherwise(F.transform(acc["counts"], lambda n, k: n + F.when(k == into, F.lit(1)).when(k == out, F.lit(-1)).otherwise(F.lit(0))))
                return let(total, lambda t: F.struct(counts.alias("counts"), t.alias("total"), F.coalesce(acc["first"], mark(t, i, none)).alias("first"), mark(t, i, acc["last"]).alias("last")))

            return let(F.struct(F.get(at, i - 1).alias("out"), F.get(at, i + (width - 1)).alias("into")), moved)

        steps = F.when(F.size(at) > width, F.sequence(F.lit(1), F.size(at) - width)).otherwise(F.array().cast("array<int>"))
        return F.aggregate(steps, let(counts, with_total), step, lambda acc: F.struct(acc["first"].alias("first"), acc["last"].alias("last")))

    return let(places, walk)


def in_blocks(spans: Column) -> Column:
    """array<struct<low,high,spans>>: spans ordered by start, in blocks of about the square root of their number."""
    block = F.ceil(F.sqrt(F.size(spans))).cast("int")
    cut = F.transform(F.sequence(F.lit(1), F.size(spans), block), lambda at: F.slice(spans, at, block))
    named = F.transform(cut, lambda b: F.struct(F.array_min(F.transform(b, lambda s: s["start"])).alias("low"), F.array_max(F.transform(b, lambda s: s["end"])).alias("high"), b.alias("spans")))
    return F.when(F.size(spans) > 0, named).otherwise(F.array().cast(f"array<struct<low:int,high:int,spans:{NO_SPANS}>>"))


def outside(hot: Column, blocks: Column, kind: int) -> Column:
    """The parts of a span that no base span covers; ``blocks`` holds the base spans in order of start."""
    none = F.array().cast(NO_SPANS)
    near = F.flatten(F.transform(F.filter(blocks, lambda b: (b["low"] < hot["end"]) & (hot["start"] < b["high"])), lambda b: b["spans"]))
    met = F.filter(near, lambda b: (b["start"] < hot["end"]) & (hot["start"] < b["end"]))
    zero = F.struct(hot["start"].alias("at"), none.alias("out"))
    step = lambda acc, b: F.struct(F.greatest(acc["at"], b["end"]).alias("at"), F.when(b["start"] > acc["at"], F.concat(acc["out"], F.array(span(acc["at"], kind, b["start"])))).otherwise(acc["out"]).alias("out"))
    return F.aggregate(met, zero, step, lambda acc: F.when(acc["at"] < hot["end"], F.concat(acc["out"], F.array(span(acc["at"], kind, hot["end"])))).otherwise(acc["out"]))


def entropy_spans(text: Column, blocks: Column, cls: CharacterClass) -> Column:
    """Spans of one character class without allow-listed candidates: of each hot span the parts outside base spans."""
    number = KINDS.index(cls.kind)

    def look(m: Column) -> Column:
        fine = m["hit"].rlike(cls.needs)
        for allowed in cls.allow:
            fine = fine & ~m["hit"].rlike(allowed)
        start = m["end"] - F.char_length(m["hit"])
        hot = let(hot_part(m["hit"], cls.alphabet, cls.width, cls.threshold), lambda h: F.when(h["first"].isNotNull(), F.struct((start + h["first"]).alias("start"), (start + h["last"] + cls.width).alias("end"))))
        return F.when(fine, hot)

    hot_spans = F.filter(F.transform(matches(text, cls.pattern), look), lambda s: s.isNotNull())
    return _guarded(text, cls.pattern, F.flatten(F.transform(hot_spans, lambda s: outside(s, blocks, number))))


def scan(docs: DataFrame, *, text: str = "text") -> DataFrame:
    """``docs`` with base_spans and all_spans: array<struct<start,kind,end>>, kind being a position in KINDS, ordered by start, then kind.  No shuffle."""
    whole = F.coalesce(F.col(text), F.lit(""))
    with_base = docs.withColumn("base_spans", base_spans(whole))
    base = F.col("base_spans")
    both = let(in_blocks(base), lambda blocks: F.sort_array(F.concat(base, *(entropy_spans(whole, blocks, c) for c in CLASSES))))
    return with_base.withColumn("all_spans", both)


def span_text(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


#: Code points of the blocks that parts of a text are cut from.
BLOCK = 512


def redacted(text: Column, spans: Column, mark: str = "[SECRET]") -> Column:
    """The text with every span replaced by ``mark``; spans that overlap become one."""

    def part(blocks: Column, start: Column, end: Column) -> Column:
        first = F.floor(start / BLOCK).cast("int")
        some = F.array_join(F.slice(blocks, first + 1, F.floor(end / BLOCK).cast("int") - first + 1), "")
        return F.substring(some, start - first * BLOCK + 1, end - start)

    def joined(x: Column) -> Column:
        before = lambda k: F.when(k > 0, F.get(x["upto"], k - 1)).otherwise(F.lit(0))
        piece = lambda s, k: let(before(k), lambda at: F.when(s["start"] >= at, F.concat(part(x["blocks"], at, s["start"]), F.lit(mark))).otherwise(F.lit("")))
        last = part(x["blocks"], F.element_at(x["upto"], -1), F.char_length(text))
        return F.array_join(F.concat(F.transform(spans, piece), F.array(last)), "")

    upto = running(F.transform(spans, lambda s: s["end"]), lambda a, b: F.greatest(a, b), 0)
    blocks = F.regexp_extract_all(text, F.lit(f"(?s).{{1,{BLOCK}}}"), F.lit(0))
    return F.when(F.size(spans) > 0, let(F.struct(blocks.alias("blocks"), upto.alias("upto")), joined)).otherwise(text)
