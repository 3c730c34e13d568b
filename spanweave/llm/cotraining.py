"""Quality classifier by co-training on two views.

The content view sees the text alone: hashed character trigrams, and shares and rates of capitals, signs, digits, lines,
repeated words and repeated trigrams, each cut into quantile bins.  The metadata view sees what the record says without its
text: language, source, both together, and size.  Both are logistic regressions.  In each round every view labels the
unlabelled documents of which it is most sure, as many of each class as the labels' ratio asks, and they join the *other*
view's training set.  On labelled documents held out from training the two views' log odds are combined by one more logistic
regression, in which each class weighs as it does among all labels, so that a score is a probability; it scores every document.

Training uses a bounded sample by hash of the id (``LABELLED``) of the labelled documents only.  Every document is turned into
packed features once; from them come the quantiles, over all documents, and in each round both views' odds for the whole
unlabelled table, whose most certain documents alone reach the driver.  Every document is scored, on its whole text.

Defined results: null texts count as empty and get a score like any other; null language, source or size is a value of its own,
and so is a size where there is no such column; several labels of a document count once, good if any says so, and of rows that
repeat a labelled id one teaches.  With labels of one class only, or none, every document scores 1.  Repeated rows score alike;
input columns pass through and a column named quality_score is replaced.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import settle, small_batches

#: A document is good from this probability on.
GOOD_FROM = 0.5
LABELLED, ROUNDS, EACH_ROUND = 6000, 3, 300
WIDTH, BINS, HASHED, SIZES = 4096, 8, 256, 48
MEASURES = 10
#: Log odds from which on a view is sure.
SURE = 3.0
#: Weight of a measure's bin beside trigrams of unit length.
BIN_WEIGHT = np.float32(0.35)
CONTENT_WIDTH, METADATA_WIDTH = WIDTH + MEASURES * (BINS + 1), 3 * HASHED + SIZES


Row = tuple[np.ndarray, np.ndarray]


def trigram_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """(positions, counts) of the hashed character trigrams."""
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.uint32)
    if len(codes) < 3:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    mixed = (codes[:-2] * np.uint32(0x9E3779B1) + codes[1:-1] * np.uint32(0x85EBCA77) + codes[2:] * np.uint32(0xC2B2AE3D)) * np.uint32(0x27D4EB2F)
    counts = np.bincount(mixed >> np.uint32(20), minlength=WIDTH)
    where = np.flatnonzero(counts)
    return where, counts[where]


def unit(counts: np.ndarray) -> np.ndarray:
    """Log counts of unit length."""
    values = np.log1p(counts.astype(np.float32))
    return values / np.sqrt((values * values).sum()) if len(values) else values


def layout(text: str) -> np.ndarray:
    """The content view's measures."""
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), dtype=np.uint8)
    n = max(len(raw), 1)
    kinds = np.bincount(raw, minlength=256)
    capitals, digits, lines = kinds[65:91].sum(), kinds[48:58].sum(), kinds[10]
    signs = kinds[33:48].sum() + kinds[58:65].sum() + kinds[91:97].sum() + kinds[123:127].sum()
    spaces = kinds[32] + lines
    words = text.split()
    distinct = len(set(words))
    repeated = sum(len(zlib.compress(raw[k : k + (1 << 20)].tobytes(), 1)) for k in range(0, len(raw), 1 << 20))
    return np.array([np.log1p(len(text)), capitals / n, digits / n, signs / n, lines / n, spaces / n, distinct / max(len(words), 1), np.log1p(n / max(lines + 1, 1)), repeated / n, (kinds[46] + kinds[44]) / n])


def metadata_row(lang: str | None, source: str | None, size: int | None) -> Row:
    """The metadata view of a record: hashed language, source and both, and the size's power of two."""
    place = lambda value: zlib.crc32(repr(value).encode()) % HASHED
    of_size = 0 if size is None else min(SIZES - 1, 1 + max(0, int(size)).bit_length())
    where = np.array([place(("lang", lang)), HASHED + place(("source", source)), 2 * HASHED + place((lang, source)), 3 * HASHED + of_size])
    return where, np.ones(4, dtype=np.float32)


def content_row(where: np.ndarray, counts: np.ndarray, measures: np.ndarray, edges: np.ndarray) -> Row:
    """The content view of a text from its trigram counts and measures; ``edges`` holds the bins' borders, a row for each measure."""
    bins = (measures[:, None] >= edges).sum(axis=1)
    return np.concatenate([where, WIDTH + np.arange(MEASURES) * (BINS + 1) + bins]), np.concatenate([unit(counts), np.full(MEASURES, BIN_WEIGHT)])


@dataclass(frozen=True)
class Logistic:
    weights: np.ndarray
    bias: float

    def odds(self, rows: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
        return np.array([self.weights[w] @ v for w, v in rows]) + self.bias if rows else np.zeros(0)


def fit_logistic(rows: list[Row], y: np.ndarray, width: int, *, steps: int = 150, rate: float = 0.5, decay: float = 1e-5, weights: tuple[float, float] = (0.5, 0.5), start: Logistic | None = None) -> Logistic:
    """Adam on all rows at once; ``weights`` are what class 0 and class 1 weigh in all."""
    at = np.repeat(np.arange(len(rows), dtype=np.int32), [len(w) for w, _ in rows])
    where, values = np.concatenate([w for w, _ in rows]).astype(np.int32), np.concatenate([v for _, v in rows]).astype(np.float32)
    share = np.clip(y.mean(), 1e-9, 1 - 1e-9)
    cost = np.where(y == 1, weights[1] / share, weights[0] / (1 - share)) / len(rows)
    w, b = (start.weights.copy(), start.bias) if start else (np.zeros(width), 0.0)
    m, s = np.zeros(width + 1), np.zeros(width + 1)
    for step in range(1, steps + 1):
        z = np.bincount(at, values * w[where], minlength=len(rows)) + b
        gap = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) * cost
        g = np.append(np.bincount(where, values * gap[at], minlength=width) + decay * w, gap.sum())
        m, s = 0.9 * m + 0.1 * g, 0.99 * s + 0.01 * g * g
        move = rate * (m / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.99**step)) + 1e-8) * min(1.0, 2 - 2 * step / steps + 0.02)
        w, b = w - move[:-1], b - move[-1]
    return Logistic(w, float(b))


@dataclass(frozen=True)
class Model:
    """Both views, the content view's bins, and the calibrated combination of their log odds."""

    content: Logistic
    metadata: Logistic
    edges: np.ndarray
    mix: tuple[float, float, float]

    def probability(self, content: list[Row], metadata: list[Row]) -> np.ndarray:
        a, b = np.clip(self.content.odds(content), -20, 20), np.clip(self.metadata.odds(metadata), -20, 20)
        return 1 / (1 + np.exp(-np.clip(self.mix[0] * a + self.mix[1] * b + self.mix[2], -30, 30)))


class Training:
    """Both views' training sets, growing by what the other view is sure of.  ``y`` holds 1 or 0; a fifth of the rows is held out for calibration."""

    def __init__(self, content: list[Row], metadata: list[Row], y: np.ndarray, good: float) -> None:
        self.held, self.good = list(zip(content[::5], metadata[::5], y[::5].tolist(), strict=True)), good
        rows = [(c, m, int(v)) for k, (c, m, v) in enumerate(zip(content, metadata, y, strict=True)) if k % 5]
        self.sets: dict[str, list[tuple[Row, float]]] = {"content": [(c, v) for c, _, v in rows], "metadata": [(m, v) for _, m, v in rows]}
        self.taken: dict[str, set[int]] = {"content": set(), "metadata": set()}
        self.models: dict[str, Logistic] = {}
        self.refit({"content", "metadata"})

    def refit(self, views: set[str]) -> None:
        """Fits the named views; later fits begin at the former one and are short."""
        widths = {"content": CONTENT_WIDTH, "metadata": METADATA_WIDTH}
        for v in sorted(views):
            rows, old = self.sets[v], self.models.get(v)
            self.models[v] = fit_logistic([r for r, _ in rows], np.array([y for _, y in rows], dtype=float), widths[v], start=old, steps=40 if old else 150, rate=0.1 if old else 0.5)

    def add(self, view: str, key: int, row: Row, label: int) -> bool:
        if key in self.taken[view]:
            return False
        self.taken[view].add(key)
        self.sets[view].append((row, label))
        return True

    def calibration(self) -> dict[str, tuple[float, float]]:
        """For each view the line from its log odds to those among held-out documents: what a view merely learned by heart gives it no confidence."""
        out, y = {}, np.array([y for *_, y in self.held], dtype=float)
        for k, v in enumerate(("content", "metadata")):
            odds = np.clip(self.models[v].odds([r[k] for r in self.held]), -20, 20)
            line = fit_logistic([(np.zeros(1, dtype=int), np.array([o])) for o in odds], y, 1, rate=0.1, decay=1e-3, weights=(1 - self.good, self.good))
            out[v] = (max(0.0, float(line.weights[0])), line.bias)
        return out

    def model(self, edges: np.ndarray) -> Model:
        a, b = (np.clip(self.models[v].odds([r[k] for r in self.held]), -20, 20) for k, v in enumerate(("content", "metadata")))
        y = np.array([y for *_, y in self.held], dtype=float)
        mix = fit_logistic([(np.arange(2), np.array(p)) for p in zip(a, b, strict=True)], y, 2, rate=0.1, decay=1e-3, weights=(1 - self.good, self.good))
        return Model(self.models["content"], self.models["metadata"], edges, (*mix.weights.tolist(), mix.bias))


def record(docs: DataFrame) -> list[Column]:
    """The metadata columns; a size is asked of no text."""
    size = F.col("n_chars").cast("bigint") if "n_chars" in docs.columns else F.lit(None).cast("bigint")
    return [F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), size.alias("size")]


def featured(docs: DataFrame) -> DataFrame:
    """(doc_id, key, where, counts, layout, lang, source, size) of every document, trigrams packed; documents with equal features have equal keys."""
    source = docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text"), *record(docs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh64_intdigest

        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                keys, where, counts, layouts = [], [], [], []
                for t, *about in zip(*(part.column(k).to_pylist() for k in (1, 2, 3, 4)), strict=True):
                    w, c = trigram_counts(t)
                    m = layout(t)
                    where.append(w.astype("<u2").tobytes())
                    counts.append(c.astype("<u4").tobytes() if len(c) and c.max() > 255 else c.astype("u1").tobytes())
                    layouts.append(m.tolist())
                    keys.append(xxh64_intdigest(where[-1] + counts[-1] + m.tobytes() + repr(about).encode()))
                signed = pa.array(np.array(keys, dtype=np.uint64).view(np.int64))
                yield pa.RecordBatch.from_arrays([part.column(0), signed, pa.array(where, pa.binary()), pa.array(counts, pa.binary()), pa.array(layouts, pa.list_(pa.float64())), *part.columns[2:]], names=["doc_id", "key", "where", "counts", "layout", "lang", "source", "size"])

    return small_batches(source).mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, key bigint, where binary, counts binary, layout array<double>, lang string, source string, size bigint")


PACKED = ("where", "counts", "layout", "lang", "source", "size")


def unpacked(where: bytes, counts: bytes, measures: list[float], lang: str | None, source: str | None, size: int | None, edges: np.ndarray) -> tuple[Row, Row]:
    """Both views' rows."""
    w = np.frombuffer(where, "<u2")
    return content_row(w, np.frombuffer(counts, "u1" if len(counts) == len(w) else "<u4"), np.array(measures), edges), metadata_row(lang, source, size)


def bin_edges(features: DataFrame) -> np.ndarray:
    """Quantiles of each measure over all documents."""
    shares = np.linspace(0, 1, BINS + 2)[1:-1].tolist()
    found = features.agg(*[F.percentile_approx(F.col("layout")[k], shares, 10_000).alias(f"m{k}") for k in range(MEASURES)]).first()
    return np.array([list(q) for q in found])


def sample_ids(labels: DataFrame, labelled: int) -> DataFrame:
    """(doc_id, y): the labelled ids with the smallest hashes, half of each class where there are as many.  At most ``labelled`` rows."""
    some = [labels.where(F.col("y") == c).orderBy(F.xxhash64("doc_id")).limit(labelled // 2) for c in (0, 1)]
    return some[0].unionByName(some[1])


def odds_of(features: DataFrame, models: dict[str, Logistic], edges: np.ndarray) -> DataFrame:
    """(doc_id, key, content, metadata): each view's log odds for every document.  No shuffle."""
    source = features.select("doc_id", "key", *PACKED)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [unpacked(*r, edges) for r in zip(*(c.to_pylist() for c in batch.columns[2:]), strict=True)]
            a, b = models["content"].odds([r for r, _ in rows]), models["metadata"].odds([r for _, r in rows])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(a, pa.float64()), pa.array(b, pa.float64())], names=["doc_id", "key", "content", "metadata"])

    return small_batches(source).mapInArrow(run, f"doc_id {features.schema['doc_id'].dataType.simpleString()}, key bigint, content double, metadata double")


def most_sure(odds: DataFrame, labels: DataFrame, good: float, each: int = EACH_ROUND, calibration: dict[str, tuple[float, float]] | None = None) -> list[tuple[str, int, int]]:
    """(view to teach, key, label): the documents of the whole unlabelled table of which each view is most sure, at most ``each`` a view; sure are calibrated log odds beyond ``SURE``."""
    line = calibration or {"content": (1.0, 0.0), "metadata": (1.0, 0.0)}
    known = labels.select("doc_id").hint("merge")
    free = settle(odds.join(known, "doc_id", "left_anti").groupBy("key").agg(F.first("content").alias("content"), F.first("metadata").alias("metadata")))
    n_good = int(each * good)
    out = []
    for view, other in (("content", "metadata"), ("metadata", "content")):
        sure = F.col(view) * line[view][0] + line[view][1]
        best = free.where(sure > SURE).orderBy(F.desc(view), "key").limit(n_good).select("key").collect()
        worst = free.where(sure < -SURE).orderBy(view, "key").limit(each - n_good).select("key").collect()
        out += [(other, r["key"], 1) for r in best] + [(other, r["key"], 0) for r in worst]
    return out


def fit(docs: DataFrame, labels: DataFrame, *, labelled: int = LABELLED, rounds: int = ROUNDS, each: int = EACH_ROUND) -> Model | None:
    """The model, or None where the labels don't have both classes.  Features are settled once; what the driver gathers are the labelled sample and each round's choice."""
    known = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.max(F.when(F.col("quality") >= 1, 1).otherwise(0)).alias("y"))
    share = known.agg(F.avg("y")).first()[0]
    if share in (None, 0.0, 1.0):
        return None
    features = settle(featured(docs))
    taught = features.join(F.broadcast(sample_ids(known, labelled)), "doc_id").select("doc_id", F.struct("key", "y", *PACKED).alias("row"))
    rows = [r["row"] for r in taught.groupBy("doc_id").agg(F.min("row").alias("row")).orderBy("row.key", "row.y").collect()]
    y = np.array([r["y"] for r in rows])
    if not {0, 1} <= set(y.tolist()):
        return None
    edges = bin_edges(features)
    content, metadata = zip(*[unpacked(*(r[c] for c in PACKED), edges) for r in rows], strict=True)
    training = Training(list(content), list(metadata), y, share)
    del rows, content, metadata
    for _ in range(rounds):
        chosen = most_sure(odds_of(features, training.models, edges), known, training.good, each, training.calibration())
        if not chosen:
            break
        keys = docs.sparkSession.createDataFrame([(k,) for k in sorted({k for _, k, _ in chosen})], "key bigint")
        found = {r["key"]: dict(zip(("content", "metadata"), unpacked(*(r[c] for c in PACKED), edges), strict=True)) for r in features.join(F.broadcast(keys), "key").dropDuplicates(["key"]).select("key", *PACKED).collect()}
        training.refit({view for view, key, label in chosen if training.add(view, key, found[key][view], label)})
    return training.model(edges)


def scored(docs: DataFrame, model: Model | None) -> DataFrame:
    """``docs`` with quality_score, the probability that a document is good.  No shuffle."""
    kept = [c for c in docs.columns if c != "quality_score"]
    if model is None:
        return docs.select(*kept).withColumn("quality_score", F.lit(1.0))
    about = [c.alias(f"{c_name}") for c, c_name in zip(record(docs), ("about lang", "about source", "about size"), strict=True)]
    source = docs.select(*kept, *about)
    text = kept.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts = [t or "" for t in part.column(text).to_pylist()]
                content = [content_row(*trigram_counts(t), layout(t), model.edges) for t in texts]
                metadata = [metadata_row(*r) for r in zip(*(c.to_pylist() for c in part.columns[len(kept) :]), strict=True)]
                found = model.probability(content, metadata)
                yield pa.RecordBatch.from_arrays([*part.columns[: len(kept)], pa.array(found, pa.float64())], names=[*kept, "quality_score"])

    return small_batches(source).mapInArrow(run, T.StructType([*(source.schema[c] for c in kept), T.StructField("quality_score", T.DoubleType())]))
