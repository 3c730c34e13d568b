"""Cross-entropy difference of documents under two matched n-gram models.

Tokens are those of one public vocabulary that both models share.  Both models are bigrams with Witten-Bell smoothing: a
context seen c times with t different followers gives (c(w) + t p(w)) / (c + t), where p is the unigram share with one added
to every count.  The target model counts the labelled good documents; the background model counts a sample of all documents
that is matched in size.  Tables hold every bigram of those documents, so they grow with the corpus, and are nowhere
gathered.  A document's score is its mean loss under the target less that under the background, in bits a token: the lower,
the more it is like the target.  A model that counted a document scores it by the counts of all the others.

Data flow.  Documents are dealt by hash into blocks of about ``BLOCK`` characters.  A block counts its own distinct bigrams and sends
them, packed, to the buckets of their contexts; a bucket adds up what all blocks sent, and answers each block with the sums
for its own bigrams; the block then scores its documents.  So what travels are texts, once, and each block's distinct bigrams,
and a task holds one block or one bucket.  In each block the documents with the smallest hashes, as many tokens as its
targets have, are the background's share.

Defined results: a null or empty text, or one without tokens, has null losses and score; a document with several labels is a
target if any of them is 1; without any target document the target model is uniform and so is the background.  Repeated rows
count and score as often as they stand.  Other columns are not read.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .word_tokens import WordTokens, word_tokens

#: Characters of a block on average; places that copies of an id are dealt to.
BLOCK, SALTS = 1 << 22, 8
#: Besides bigrams (context << 16 | token), keys of a context's total and of its number of followers, and of all tokens.
TOTAL, FOLLOWERS, EVERY = 0xFFFF, 0xFFFE, np.uint32(0xFFFFFFFF)
PACKED = "block bigint, doc_id {}, bucket bigint, keys binary, target binary, background binary"


@dataclass
class Block:
    """The documents of a block as bigrams: for each token its document and the place of its bigram among the distinct ones, which are sorted."""

    sizes: np.ndarray
    whose: np.ndarray
    keys: np.ndarray
    place: np.ndarray
    target: np.ndarray
    background: np.ndarray

    @staticmethod
    def of(texts: list[str], hashes: np.ndarray, target: np.ndarray, words: WordTokens) -> Block:
        ids, ends = words.encode(texts)
        sizes = np.diff(ends, prepend=0)
        context = np.concatenate([[0], ids[:-1]]).astype(np.uint32)
        context[(ends - sizes)[sizes > 0]] = words.size + 1  # nothing before the first token
        keys, place = np.unique(context << np.uint32(16) | ids.astype(np.uint32), return_inverse=True)
        order = np.argsort(hashes, kind="stable")
        before = np.cumsum(sizes[order]) - sizes[order]
        background = np.zeros(len(sizes), dtype=bool)
        background[order] = before < sizes[target].sum()
        return Block(sizes, np.repeat(np.arange(len(sizes), dtype=np.int32), sizes), keys, place.astype(np.int32), target, background)

    def counts(self, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(keys, target, background) of all distinct keys of the block, those of neither model included: they ask."""
        word = (self.keys & np.uint32(0xFFFF)).astype(np.int64)
        words = np.unique(word)
        columns = []
        for role in (self.target, self.background):
            pairs = np.bincount(self.place[role[self.whose]], minlength=len(self.keys))
            single = np.bincount(word, weights=pairs, minlength=1 << 16)[words]
            columns.append(np.concatenate([pairs, single, [self.sizes[role].sum()]]).astype(np.uint32))
        return np.concatenate([self.keys, np.uint32(size << 16) | words.astype(np.uint32), [EVERY]]), *columns

    def losses(self, keys: np.ndarray, counts: np.ndarray, role: np.ndarray, size: int) -> np.ndarray:
        """Mean loss of each document in bits a token; ``counts`` belong to ``keys``, which are sorted."""
        if not len(self.whose):
            return np.full(len(self.sizes), np.nan)
        high, low = keys >> np.uint32(16), keys & np.uint32(0xFFFF)
        single, total, after = (np.zeros(1 << 16, dtype=np.int64) for _ in range(3))
        for table, some, index in ((single, high == size, low), (total, low == TOTAL, high), (after, low == FOLLOWERS, high)):
            table[index[some]] = counts[some]
        every = int(counts[np.searchsorted(keys, EVERY)])
        pair = counts[np.searchsorted(keys, self.keys)].astype(np.int64)
        context, word = (self.keys >> np.uint32(16)).astype(np.int64), (self.keys & np.uint32(0xFFFF)).astype(np.int64)
        loss = _bits(pair, single[word], total[context], after[context], every, size)[self.place]
        own = np.flatnonzero(role[self.whose])
        if len(own):  # counted by the model: each document's counts are taken out again
            whose, place = self.whose[own].astype(np.int64), self.place[own].astype(np.int64)
            mine, at, n_pair = np.unique(whose * len(self.keys) + place, return_inverse=True, return_counts=True)
            doc, place = np.divmod(mine, len(self.keys))
            # Distinct bigrams are ordered by document, then context, so contexts lie in runs; words are put in order first.
            runs = np.flatnonzero(np.concatenate([[True], np.diff(doc << 16 | context[place]) != 0]))
            run = np.repeat(np.arange(len(runs)), np.diff(np.append(runs, len(mine))))
            gone = pair[place] == n_pair
            n_context, n_gone = np.add.reduceat(n_pair, runs)[run], np.add.reduceat(gone, runs, dtype=np.int64)[run]
            _, same = np.unique(doc << 16 | word[place], return_inverse=True)
            n_word = np.bincount(same, weights=n_pair).astype(np.int64)[same]
            left = _bits(pair[place] - n_pair, single[word[place]] - n_word, total[context[place]] - n_context, after[context[place]] - n_gone, every - self.sizes[doc], size)
            loss[own] = left[at]
        sums = np.bincount(self.whose, weights=loss, minlength=len(self.sizes))
        return np.divide(sums, self.sizes, out=np.full(len(sums), np.nan), where=self.sizes > 0)


def _bits(pair: np.ndarray, single: np.ndarray, total: np.ndarray, followers: np.ndarray, every, size: int) -> np.ndarray:
    share = (single + 1) / (every + size)
    known = total + followers
    return -np.log2(np.where(known > 0, (pair + followers * share) / np.maximum(known, 1), share))


def buckets_of(keys: np.ndarray, size: int, buckets: int) -> np.ndarray:
    """A bigram goes by its context, a unigram by its token."""
    context = keys >> np.uint32(16)
    by = np.where(context == size, keys & np.uint32(0xFFFF), context).astype(np.uint64)
    return ((by * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)


def added(tables: pa.Table, size: int) -> pa.Table:
    """The sums of one bucket, for each block the rows of what it sent, with totals and followers of its contexts."""
    sent = [tuple(np.frombuffer(tables.column(c)[k].as_py(), np.uint32) for c in ("keys", "target", "background")) for k in range(tables.num_rows)]
    every, place = np.unique(np.concatenate([s[0] for s in sent]), return_inverse=True)
    sums = [np.bincount(place, weights=np.concatenate([s[c] for s in sent]), minlength=len(every)).astype(np.int64) for c in (1, 2)]
    context, of = np.unique(every >> np.uint32(16), return_inverse=True)
    totals = [np.bincount(of, weights=s).astype(np.int64) for s in sums]
    followers = [np.bincount(of, weights=s > 0).astype(np.int64) for s in sums]
    rows, at = [], 0
    for keys, *_ in sent:
        own = place[at : at + len(keys)]
        at += len(keys)
        mine = np.unique(of[own])
        mine = mine[context[mine] <= size + 1]
        base = context[mine].astype(np.uint32) << np.uint32(16)
        names = np.concatenate([keys, base | np.uint32(TOTAL), base | np.uint32(FOLLOWERS)])
        rows.append((names.tobytes(), *(np.concatenate([s[own], t[mine], f[mine]]).astype(np.uint32).tobytes() for s, t, f in zip(sums, totals, followers, strict=True))))
    keys, target, background = zip(*rows, strict=True)
    n = tables.num_rows
    columns = [tables.column("block"), pa.nulls(n, tables.schema.field("doc_id").type), tables.column("bucket"), *(pa.array(c, pa.binary()) for c in (keys, target, background))]
    return pa.table(columns, names=["block", "doc_id", "bucket", "keys", "target", "background"])


def score(docs: DataFrame, labels: DataFrame, vocab_path: str, *, block: int = BLOCK) -> DataFrame:
    """(doc_id, n_tokens, target_bits, background_bits, score) for each row; ``labels`` holds (doc_id, quality)."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    text = F.coalesce(F.col("text"), F.lit(""))
    blocks = max(1, math.ceil((docs.agg(F.sum(F.length(text))).first()[0] or 0) / block))
    # Copies of an id are dealt by their texts to some places, and its label is sent to each of them; null ids have no label.
    home = lambda salt: F.pmod(F.coalesce(F.xxhash64("doc_id"), F.lit(0)) + salt, F.lit(blocks))
    text_hash = F.xxhash64(text)
    salt = F.when(F.col("doc_id").isNull(), text_hash).otherwise(F.pmod(text_hash, F.lit(SALTS)))
    dealt = docs.select(home(salt).alias("block"), "doc_id", text.alias("text"), F.xxhash64("doc_id", text).alias("hash"))
    good = labels.where("doc_id is not null and quality = 1").select(F.col("doc_id").cast(kind).alias("doc_id")).distinct()
    schema = PACKED.format(kind)
    empty = [F.lit(None).cast(t).alias(c) for c, t in (("bucket", "bigint"), ("keys", "binary"), ("target", "binary"), ("background", "binary"))]
    known = good.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))).select(home(F.col("salt")).alias("block"), "doc_id", *empty).distinct()

    def read(own: pa.Table, notes: pa.Table, words: WordTokens) -> Block:
        good_ids = set(notes.filter(pc.is_null(notes.column("keys"))).column("doc_id").to_pylist())
        target = np.array([i is not None and i in good_ids for i in own.column("doc_id").to_pylist()], dtype=bool)
        return Block.of(own.column("text").to_pylist(), own.column("hash").to_numpy(), target, words)

    def count(own: pa.Table, notes: pa.Table) -> pa.Table:
        words, rows = word_tokens(vocab_path), []
        if own.num_rows:
            keys, target, background = read(own, notes, words).counts(words.size)
            bucket = buckets_of(keys, words.size, blocks)
            order = np.argsort(bucket, kind="stable")
            cuts = np.flatnonzero(np.diff(bucket[order])) + 1
            rows = [(int(bucket[part[0]]), keys[part].tobytes(), target[part].tobytes(), background[part].tobytes()) for part in np.split(order, cuts)]
        number = own.column("block")[0].as_py() if rows else 0
        bucket, *packed = zip(*rows, strict=True) if rows else ([], [], [], [])
        columns = [pa.array([number] * len(rows), pa.int64()), pa.nulls(len(rows), own.schema.field("doc_id").type), pa.array(bucket, pa.int64()), *(pa.array(c, pa.binary()) for c in packed)]
        return pa.table(columns, names=["block", "doc_id", "bucket", "keys", "target", "background"])

    def add(sent: pa.Table) -> pa.Table:
        return added(sent, word_tokens(vocab_path).size)

    def judge(own: pa.Table, notes: pa.Table) -> pa.Table:
        words = word_tokens(vocab_path)
        if not own.num_rows:
            return pa.table([own.column("doc_id"), *(pa.array([], t) for t in (pa.int64(), pa.float64(), pa.float64(), pa.float64()))], names=["doc_id", "n_tokens", "target_bits", "background_bits", "score"])
        mine = read(own, notes, words)
        answers = notes.filter(pc.is_valid(notes.column("keys")))
        columns = [np.frombuffer(b"".join(answers.column(c).to_pylist()), np.uint32) for c in ("keys", "target", "background")]
        order = np.argsort(columns[0], kind="stable")
        keys, target, background = (c[order] for c in columns)
        a, b = mine.losses(keys, target, mine.target, words.size), mine.losses(keys, background, mine.background, words.size)
        floats = [pa.array(x, pa.float64(), from_pandas=True) for x in (a, b, a - b)]
        return pa.table([own.column("doc_id"), pa.array(mine.sizes, pa.int64()), *floats], names=["doc_id", "n_tokens", "target_bits", "background_bits", "score"])

    by_block = dealt.groupBy("block")
    sent = by_block.cogroup(known.groupBy("block")).applyInArrow(count, schema)
    answers = sent.groupBy("bucket").applyInArrow(add, schema)
    return by_block.cogroup(known.unionByName(answers).groupBy("block")).applyInArrow(judge, f"doc_id {kind}, n_tokens bigint, target_bits double, background_bits double, score double")
