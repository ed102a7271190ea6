"""Exact tokenizers-library encoding of text columns, with each distinct piece of text encoded once.

The byte-level pattern never matches across a change from solid text to white space, so a text may be cut there: each cut
piece (white space, then solid text) gets the same ids alone as in place. Texts with characters that could blur such
cuts (white space beyond ASCII, control separators, special-token brackets) are encoded whole instead.
"""

from __future__ import annotations

import numpy as np
import pandas as pd

from .words import SPACE, flatten, hash_spans, spans

#: Distinct pieces that a worker process remembers, at most.
MEMORY = 1_000_000
SLAB = 10_000
SEGMENTS = 8
#: Words on which the model alone is compared with the whole tokenizer before it is used.
SAMPLES = [" the", "The", " Hello", "hello", " internationalisation", "Zyxgrth", " QWERTY", " a", "I", " thndndwh", "don", " ERROR", "camelCase", " snakeLikeWordsOfSomeLength"]
_memory: dict[str, "Encoder"] = {}


def encoder(path: str) -> "Encoder":
    """One encoder a process and tokenizer file."""
    if path not in _memory:
        _memory[path] = Encoder(path)
    return _memory[path]


def _spaced(text: str) -> str:
    """A leading blank as byte-level tokenizers write it."""
    return "\u0120" + text[1:] if text[:1] == " " else text


def _lowered(text: str) -> str:
    return text.strip(" ").lower()


class Encoder:
    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.vocabulary = self.tokenizer.get_vocab_size()
        self.segments: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []  # sorted keys, where in ids, how many
        self.known = 0
        self.ids = np.zeros(0, np.uint32)
        self.direct = next((d for d in (_spaced, _lowered) if self._agrees(d)), None)

    def _agrees(self, prepare) -> bool:
        """Whether the model alone, on words as `prepare` writes them, gives what the whole tokenizer gives."""
        model = self.tokenizer.model
        try:
            return all([k.id for k in model.tokenize(prepare(t))] == self.tokenizer.encode(t, add_special_tokens=False).ids for t in SAMPLES)
        except Exception:  # noqa: BLE001  a model that can't tokenise such words has no short way
            return False

    def _whole(self, texts: list[str]) -> list[list[int]]:
        """The library's ids, a slab at a time."""
        return [e.ids for i in range(0, len(texts), SLAB) for e in self.tokenizer.encode_batch_fast(texts[i : i + SLAB], add_special_tokens=False)]

    def _plain(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of texts. A word of ASCII letters, alone or after a blank, is one unit for the tokenizer's patterns, so its
        ids come from the model directly, at a third of the cost."""
        found: list = [None] * len(texts)
        rest = []
        for i, t in enumerate(texts):
            word = t[1:] if t[:1] == " " else t
            if self.direct is not None and len(word) <= 100 and word.isascii() and word.isalpha():
                found[i] = [k.id for k in self.tokenizer.model.tokenize(self.direct(t))]
            else:
                rest.append(i)
        for i, ids in zip(rest, self._whole([texts[i] for i in rest]), strict=True):
            found[i] = ids
        sizes = np.array([len(x) for x in found], np.int64)
        return np.fromiter((k for x in found for k in x), np.uint32, int(sizes.sum())), sizes

    def encode(self, column) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all rows in order (uint32), and row offsets. Null rows have none."""
        raw, offsets = flatten(column)
        rows = len(offsets) - 1
        odd = np.flatnonzero(_odd(raw, offsets))
        starts, ends, first = spans(raw, offsets)
        sizes = np.diff(offsets)
        # A piece begins where the one before it ends; white space at a row's end is a piece of its own.
        begin = np.empty_like(starts)
        begin[1:] = ends[:-1]
        own = np.diff(first) > 0
        begin[first[:-1][own]] = offsets[:-1][own]
        tail_from = np.where(own, ends[np.maximum(first[1:] - 1, 0)] if len(ends) else 0, offsets[:-1])
        tail = np.flatnonzero((tail_from < offsets[1:]) & (sizes > 0))
        begin, end = np.concatenate([begin, tail_from[tail]]), np.concatenate([ends, offsets[1:][tail]])
        order = np.argsort(begin, kind="stable")
        begin, end = begin[order], end[order]
        piece_row = np.searchsorted(offsets, begin, "right") - 1
        if len(odd):
            keep = ~np.isin(piece_row, odd)
            begin, end, piece_row = begin[keep], end[keep], piece_row[keep]
        code, distinct = pd.factorize(hash_spans(raw, begin, end))
        seen = np.full(len(distinct), -1, np.int64)
        if len(code):
            seen[code[::-1]] = np.arange(len(code))[::-1]
        at, length, pool = self._lookup(distinct, raw, begin[seen], end[seen])
        size = length[code]
        ids = pool[_ranges(at[code], size)]
        counts = np.bincount(piece_row, weights=size, minlength=rows).astype(np.int64)
        if not len(odd):
            return ids, np.concatenate([[0], np.cumsum(counts)])
        whole, whole_sizes = self._plain([raw[offsets[r] : offsets[r + 1]].tobytes().decode("utf-8", "replace") for r in odd])
        cut = np.concatenate([[0], np.cumsum(counts)])
        slow = dict(zip(odd.tolist(), np.split(whole, np.cumsum(whole_sizes)[:-1]), strict=True))
        parts, last = [], 0
        for r in odd.tolist():
            parts += [ids[cut[last] : cut[r]], slow[r]]
            last = r
        parts.append(ids[cut[last] :])
        counts[odd] = whole_sizes
        return np.concatenate(parts), np.concatenate([[0], np.cumsum(counts)])

    def _lookup(self, keys, raw, begin, end):
        """Where in a pool of ids each distinct piece's ids are; unknown pieces are encoded and, up to MEMORY, remembered."""
        at, length, left = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64), np.arange(len(keys))
        for held, start, size in self.segments:
            pos = np.minimum(np.searchsorted(held, keys[left]), len(held) - 1)
            hit = held[pos] == keys[left]
            at[left[hit]], length[left[hit]] = start[pos[hit]], size[pos[hit]]
            left = left[~hit]
        if not len(left):
            return at, length, self.ids
        view = raw.tobytes()
        ids, sizes = self._plain([view[b:e].decode("utf-8", "replace") for b, e in zip(begin[left].tolist(), end[left].tolist(), strict=True)])
        at[left], length[left] = len(self.ids) + np.cumsum(sizes) - sizes, sizes
        pool = np.concatenate([self.ids, ids])
        if self.known + len(left) <= MEMORY:
            order = left[np.argsort(keys[left], kind="stable")]
            self.segments.append((keys[order], at[order].astype(np.uint32), length[order].astype(np.uint32)))
            self.ids, self.known = pool, self.known + len(left)
            if len(self.segments) > SEGMENTS:
                whole = [np.concatenate(c) for c in zip(*self.segments, strict=True)]
                order = np.argsort(whole[0], kind="stable")
                self.segments = [tuple(c[order] for c in whole)]
        return at, length, pool


def _ranges(at: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Indices at[0] .. at[0]+size[0]-1, at[1] .. and so on."""
    total = int(size.sum())
    if not total:
        return np.zeros(0, np.int64)
    end = np.cumsum(size)
    return np.repeat(at - (end - size), size) + np.arange(total)


def _odd(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Rows to encode whole: white space beyond ASCII, control separators, special-token brackets, zero bytes."""
    out = np.zeros(len(offsets) - 1, bool)
    if len(raw) < 2:
        return out
    a, b = raw[:-1], raw[1:]
    hit = ((a == 0xC2) & ((b == 0x85) | (b == 0xA0))) | ((a == 0xE1) & ((b == 0x9A) | (b == 0xA0))) | ((a == 0xE2) & ((b == 0x80) | (b == 0x81))) | ((a == 0xE3) & (b == 0x80)) | ((a == 0x3C) & (b == 0x7C))
    hit = np.append(hit, False) | ((raw < 0x20) & ~SPACE[raw])
    where = np.flatnonzero(hit)
    out[np.searchsorted(offsets, where, "right") - 1] = True
    return out
