"""Token ids of a tokenizers-library vocabulary, many texts at once.

The vocabulary drops white space, so a text's ids are those of its white-space chunks in order.  Texts are laid end to end
as one array of characters; a table of character kinds gives where pre-tokens begin, each distinct pre-token is merged once
by byte-pair ranks, all of them together, and the ids are dealt back.  Nothing is remembered from one call to the next, so
memory follows the ``SPAN`` characters that are worked on together (or one longer text).

Characters whose treatment could depend on more than themselves (not in composed form, combining, lower-cased to several,
beyond the basic plane, or changed between editions of Unicode) send their whole chunk to the library, as do pre-tokens that
are very long.  Special tokens of the vocabulary are taken from the text as the library takes them by default.
"""

from __future__ import annotations

import functools
import json
import os
import re
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Characters of texts that are encoded together, and the longest pre-token that is merged here.
SPAN, LONGEST = 1 << 20, 48
SPACE, LETTER, NUMBER, SIGN, ODD = range(5)


@functools.cache
def character_tables() -> tuple[np.ndarray, np.ndarray]:
    """(kind, lower case) of every character of the basic plane."""
    kinds, lower, old = np.full(1 << 16, ODD, dtype=np.uint8), np.arange(1 << 16, dtype=np.uint16), unicodedata.ucd_3_2_0
    for c in range(1 << 16):
        s = chr(c)
        kind, small = unicodedata.category(s), s.lower()
        if c in (9, 10, 11, 12, 13, 32):
            kinds[c] = SPACE
        elif c in (0x85, 0xA0) or kind[0] in "ZM" or kind in ("Cn", "Cs", "Co") or kind != old.category(s) or unicodedata.combining(s):
            continue
        elif len(small) == 1 and ord(small) < 1 << 16 and unicodedata.is_normalized("NFC", s) and old.category(small) != "Cn" and not 0x1100 <= c < 0x1200:
            kinds[c] = LETTER if kind[0] == "L" else NUMBER if kind[0] == "N" else SIGN
            lower[c] = ord(small)
    return kinds, lower


class Merges:
    """Byte-pair merges of many words at once."""

    def __init__(self, model: dict) -> None:
        vocab: dict[str, int] = model["vocab"]
        ends = model["end_of_word_suffix"]
        own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
        shown = {b: chr(b) for b in own} | {b: chr(256 + k) for k, b in enumerate(b for b in range(256) if b not in set(own))}
        self.first = np.array([vocab[shown[b]] for b in range(256)], dtype=np.int64)
        self.last = np.array([vocab[shown[b] + ends] for b in range(256)], dtype=np.int64)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        keys = np.array([vocab[a] << 20 | vocab[b] for a, b in pairs], dtype=np.int64)
        made = np.array([vocab[a.removesuffix(ends) + b if a.endswith(ends) else a + b] for a, b in pairs], dtype=np.int64)
        # Open addressing with few steps: a million slots for some fifty thousand pairs, the last of them left empty.
        self.bits, self.steps = 20, 0
        self.slots, self.rank, self.made = np.full(1 << self.bits, -1, dtype=np.int64), np.full(1 << self.bits, NEVER, dtype=np.int32), np.zeros(1 << self.bits, dtype=np.int32)
        left, none = np.arange(len(keys)), (1 << self.bits) - 1
        while len(left):
            at = self._place(keys[left], self.steps)
            free = (self.slots[at] < 0) & (at != none)
            _, one = np.unique(at, return_index=True)
            chosen = one[free[one]]
            self.slots[at[chosen]], self.rank[at[chosen]], self.made[at[chosen]] = keys[left[chosen]], left[chosen], made[left[chosen]]
            left = np.delete(left, chosen)
            self.steps += 1

    def _place(self, keys: np.ndarray, step: int) -> np.ndarray:
        mixed = keys.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        return ((mixed >> np.uint64(64 - self.bits)).astype(np.int64) + step) & ((1 << self.bits) - 1)

    def found(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The slot of each pair, or -1."""
        keys = a << 20 | b
        at = self._place(keys, 0)
        there = self.slots[at]
        out = np.where(there == keys, at, -1)
        open_ = np.flatnonzero((there != keys) & ((there >= 0) | (at == len(self.slots) - 1)))
        for step in range(1, self.steps):
            if not len(open_):
                break
            at = self._place(keys[open_], step)
            there = self.slots[at]
            out[open_] = np.where(there == keys[open_], at, -1)
            open_ = open_[(there != keys[open_]) & ((there >= 0) | (at == len(self.slots) - 1))]
        return out

    def ids(self, symbols: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, ends) after all merges of words that lie end to end; ``ends`` holds the position after each word, none empty.

        A merge makes a token whose own merges all rank later, so in every step each word can do all of its lowest-ranked
        merges together; of overlapping ones every second, from the left.  Words with nothing left to merge are put aside.
        """
        words, kept_ids, kept_words = np.arange(len(ends)), [], []
        slot = np.full(len(symbols), -1, dtype=np.int64)
        slot[:-1] = self.found(symbols[:-1], symbols[1:])
        slot[ends - 1] = -1
        rank = self.rank[slot]  # slot -1 is the last one, which stays empty
        sizes = np.diff(ends, prepend=0)
        while True:
            lowest = np.minimum.reduceat(rank, ends - sizes)
            over = lowest == NEVER
            if over.any():
                aside = np.repeat(over, sizes)
                kept_ids.append(symbols[aside])
                kept_words.append(np.repeat(words[over], sizes[over]))
                words, sizes, lowest = words[~over], sizes[~over], lowest[~over]
                if not len(words):
                    break
                symbols, rank, slot = symbols[~aside], rank[~aside], slot[~aside]
                ends = np.cumsum(sizes)
            here = np.flatnonzero(rank == np.repeat(lowest, sizes))
            close = np.flatnonzero(np.diff(here) == 1) + 1
            if len(close):  # equal symbols in a row: a merge right behind a merge has lost its left symbol
                fine = np.ones(len(here), dtype=bool)
                for k in close.tolist():
                    fine[k] = not fine[k - 1]
                here = here[fine]
            symbols[here] = self.made[slot[here]]
            keep = np.ones(len(symbols), dtype=bool)
            keep[here + 1] = False
            symbols, rank, slot = symbols[keep], rank[keep], slot[keep]
            sizes = np.add.reduceat(keep, ends - sizes, dtype=np.int64)
            ends = np.cumsum(sizes)
            here -= np.arange(len(here))  # each merge before has taken one place
            new = np.concatenate([here, here[here > 0] - 1])
            slot[new] = self.found(symbols[new], symbols[np.minimum(new + 1, len(symbols) - 1)])
            slot[ends - 1] = -1
            rank[new], rank[ends - 1] = self.rank[slot[new]], NEVER
        every, whose = np.concatenate(kept_ids), np.concatenate(kept_words)
        order = np.argsort(whose, kind="stable")
        return every[order], np.cumsum(np.bincount(whose, minlength=whose.max() + 1))


NEVER = np.int32((1 << 31) - 1)


class WordTokens:
    def __init__(self, vocab_path: str) -> None:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(vocab_path)
        self.size = self.tokenizer.get_vocab_size()
        self.merges = Merges(json.loads(self.tokenizer.to_str())["model"])
        special = {t.content: i for i, t in self.tokenizer.get_added_tokens_decoder().items()}
        self.special, self.special_at = special, re.compile(f"({'|'.join(map(re.escape, special))})") if special else None

    def library(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, ends): the ids of all texts in one array, and the position after each text's."""
        ids, sizes, at = [], [], 0
        while at < len(texts):
            to, length = at, 0
            while to < len(texts) and (to == at or length + len(texts[to]) <= SPAN):
                length += len(texts[to])
                to += 1
            found, n = self._span(texts[at:to])
            ids.append(found)
            sizes.append(n)
            at = to
        return (np.concatenate(ids), np.cumsum(np.concatenate(sizes))) if ids else (np.zeros(0, np.uint32), np.zeros(0, np.int64))

    def _span(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of ids of each text)."""
        joined = " ".join(texts)
        if self.special_at and self.special_at.search(joined):
            parts = [p for t in texts for p in self.special_at.split(t)]  # plain and special ones in turn, from plain to plain
            plain, n = self._plain([p for p in parts if p not in self.special])
            pieces, at, taken = [], 0, iter(n.tolist())
            sizes = np.array([1 if p in self.special else next(taken) for p in parts])
            for p, k in zip(parts, sizes.tolist(), strict=True):
                pieces.append(np.array([self.special[p]], np.uint32) if p in self.special else plain[at : at + k])
                at += 0 if p in self.special else k
            whose = np.repeat(np.arange(len(texts)), [len(self.special_at.split(t)) for t in texts])
            return np.concatenate(pieces), np.bincount(whose, weights=sizes, minlength=len(texts)).astype(np.int64)
        return self._plain(texts, joined)

    def _plain(self, texts: list[str], joined: str | None = None) -> tuple[np.ndarray, np.ndarray]:
        joined = " ".join(texts) if joined is None else joined
        kinds, lower = character_tables()
        try:
            codes = np.frombuffer(joined.encode("latin-1"), np.uint8)
        except UnicodeEncodeError:
            codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
        kind = kinds[codes] if codes.dtype == np.uint8 else np.where(codes < 1 << 16, kinds[np.minimum(codes, 0xFFFF)], np.uint8(ODD))
        if not len(codes) or not (kind != SPACE).any():
            return np.zeros(0, np.uint32), np.zeros(len(texts), np.int64)
        small = lower[codes].astype(np.uint8) if codes.dtype == np.uint8 else np.where(codes < 1 << 16, lower[np.minimum(codes, 0xFFFF)], codes).astype(np.uint32)
        begins = np.ones(len(codes), dtype=bool)
        begins[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == NUMBER)
        self._contractions(small, kind, begins)
        odd = np.flatnonzero(kind == ODD)
        if len(odd):  # whole chunks, in their own case
            blank = np.flatnonzero(kind == SPACE)
            k = np.unique(np.searchsorted(blank, odd))
            first = np.where(k > 0, blank[np.maximum(k - 1, 0)] + 1, 0) if len(blank) else np.zeros(1, np.int64)
            behind = np.append(blank, len(codes))[k]
            change = np.zeros(len(codes) + 1, dtype=np.int64)
            np.add.at(change, first, 1)
            np.add.at(change, behind, -1)
            whole = np.cumsum(change[:-1]) > 0
            begins[whole] = False
            begins[first] = True
            small = np.where(whole, codes, small)
        starts = np.flatnonzero(begins)
        ends = np.append(starts[1:], len(codes))
        width = small.dtype.itemsize
        slices = pa.Array.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer(np.append(starts, len(codes)).astype(np.int32) * width), pa.py_buffer(np.ascontiguousarray(small))])
        real = kind[starts] != SPACE
        entries = (slices if real.all() else slices.filter(pa.array(real))).dictionary_encode()
        ids, entry_ends = self._entries(entries.dictionary, small.dtype, kinds)
        which = entries.indices.to_numpy()
        sizes = np.diff(entry_ends, prepend=0)
        n = sizes[which]
        upto = np.cumsum(n)
        out = ids[np.repeat(entry_ends[which] - upto, n) + np.arange(upto[-1])]
        # Text k ends, separator included, where the next one begins.
        borders = np.cumsum([len(t) + 1 for t in texts])
        tokens_before = np.searchsorted(starts[real], borders)
        return out.astype(np.uint32), np.diff(np.concatenate([[0], upto])[tokens_before], prepend=0)

    @staticmethod
    def _contractions(small: np.ndarray, kind: np.ndarray, begins: np.ndarray) -> None:
        """An apostrophe that opens a pre-token takes one or two known letters with it; what follows begins anew."""
        quotes = np.flatnonzero((small[:-1] == 39) & begins[:-1])
        if not len(quotes):
            return
        tail = np.append(small, np.zeros(2, small.dtype))
        a, b = tail[quotes + 1], tail[quotes + 2]
        one = np.isin(a, [ord(c) for c in "stmd"])
        two = ((a == ord("r")) | (a == ord("v"))) & (b == ord("e")) | (a == ord("l")) & (b == ord("l"))
        begins[quotes[one | two] + 1] = False
        for some, step in ((quotes[one], 2), (quotes[two], 3)):
            begins[some[some + step < len(begins)] + step] = True
        begins[quotes[two] + 2] = False

    def _entries(self, dictionary: pa.Array, dtype: np.dtype, kinds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, ends) of distinct pre-tokens or odd chunks."""
        offsets = np.frombuffer(dictionary.buffers()[1], np.int32)[: len(dictionary) + 1].astype(np.int64) // dtype.itemsize
        codes = np.frombuffer(dictionary.buffers()[2], dtype)[: offsets[-1]]
        size = np.diff(offsets)
        odd = (kinds[codes] if dtype == np.uint8 else np.where(codes < 1 << 16, kinds[np.minimum(codes, 0xFFFF)], ODD)) == ODD
        by_library = (np.add.reduceat(odd, offsets[:-1], dtype=np.int64) > 0) | (size > LONGEST)
        fast = np.flatnonzero(~by_library)
        counts, parts = np.zeros(len(size), np.int64), []
        if len(fast):
            chosen = codes[np.repeat(~by_library, size)].astype(np.int64)
            n_bytes = 1 + (chosen > 0x7F) + (chosen > 0x7FF)
            raw = _utf8(chosen, n_bytes)
            ends = np.cumsum(np.add.reduceat(n_bytes, np.concatenate([[0], np.cumsum(size[fast])[:-1]])))
            symbols = self.merges.first[raw]
            symbols[ends - 1] = self.merges.last[raw[ends - 1]]
            ids, ends = self.merges.ids(symbols, ends)
            counts[fast] = np.diff(ends, prepend=0)
            parts.append((np.repeat(fast, counts[fast]), ids))
        name = {1: "latin-1", 4: "utf-32-le"}[dtype.itemsize]
        for k in np.flatnonzero(by_library).tolist():
            ids = self.library(codes[offsets[k] : offsets[k + 1]].tobytes().decode(name, "surrogatepass"))
            counts[k] = len(ids)
            parts.append((np.full(len(ids), k), np.array(ids, np.int64)))
        whose, ids = (np.concatenate(c) for c in zip(*parts, strict=True))
        return ids[np.argsort(whose, kind="stable")], np.cumsum(counts)


def _utf8(codes: np.ndarray, n_bytes: np.ndarray) -> np.ndarray:
    """UTF-8 bytes of characters of the basic plane."""
    if (n_bytes == 1).all():
        return codes
    at = np.cumsum(n_bytes) - n_bytes
    out = np.empty(int(n_bytes.sum()), np.int64)
    one, two, three = (n_bytes == k for k in (1, 2, 3))
    out[at[one]] = codes[one]
    out[at[two]], out[at[two] + 1] = 0xC0 | codes[two] >> 6, 0x80 | codes[two] & 63
    out[at[three]], out[at[three] + 1], out[at[three] + 2] = 0xE0 | codes[three] >> 12, 0x80 | codes[three] >> 6 & 63, 0x80 | codes[three] & 63
    return out


def spans(batch: pa.RecordBatch, column: int) -> Iterator[pa.RecordBatch]:
    """The batch in slices whose texts hold about ``SPAN`` bytes together, or one text that is longer."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy().astype(np.int64))
    at = 0
    while at < batch.num_rows:
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + SPAN, "right")))
        yield batch.slice(at, to - at)
        at = to


@functools.lru_cache(maxsize=1)
def word_tokens(vocab_path: str) -> WordTokens:
    """One encoder for each Python worker."""
    return WordTokens(vocab_path)
