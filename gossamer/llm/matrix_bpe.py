"""Byte-level BPE by padded matrices.

Unseen pre-tokens of a batch are bucketed by length into numpy matrices, one row each. In every
round each row merges its leftmost pair of lowest rank; pair ranks come from an open-addressing hash
table, finished rows are taken out. Pre-tokens over ``MATRIX_MOST`` bytes would need too many rounds
of wide rows; they take a heap of pairs over a linked list, with the same merges.

Cases: null text is empty (no ids); texts of any length are cut at pre-token borders only; repeated
rows are encoded once a slice; other columns are not read; an empty table gives no rows.
"""

from __future__ import annotations

import base64
import functools
import heapq
from collections.abc import Iterable, Iterator

import numpy as np
import regex

from . import common

MATRIX_MOST = 256
ROWS_MOST = 16_384
NONE = np.int64(1 << 40)


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class PairTable:
    """(left id, right id) -> rank of the merged token, in an open-addressing table."""

    def __init__(self, ranks: dict[bytes, int]):
        left, right, rank = [], [], []
        for token, r in ranks.items():
            for i in range(1, len(token)):
                a, b = ranks.get(token[:i]), ranks.get(token[i:])
                if a is not None and b is not None:
                    left.append(a)
                    right.append(b)
                    rank.append(r)
        keys = np.asarray(left, np.uint64) << np.uint64(32) | np.asarray(right, np.uint64)
        self.bits = max(4, int(np.ceil(np.log2(max(1, len(keys)) * 4))))
        self.mask = (1 << self.bits) - 1
        self.keys = np.full(1 << self.bits, np.uint64(2**64 - 1))
        self.ranks = np.full(1 << self.bits, NONE)
        self.longest = 0
        todo, place = np.arange(len(keys)), self._home(keys)
        rank_of = np.asarray(rank, np.int64)
        while len(todo):
            free = self.keys[place[todo]] == np.uint64(2**64 - 1)
            takers = todo[free]
            _, first = np.unique(place[takers], return_index=True)
            takers = takers[first]
            self.keys[place[takers]], self.ranks[place[takers]] = keys[takers], rank_of[takers]
            todo = np.setdiff1d(todo, takers, assume_unique=True)
            place[todo] = (place[todo] + 1) & self.mask
            self.longest += 1

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return (keys * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).astype(np.int64)

    def __call__(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Ranks of the pairs; NONE where no token has them or an id is negative (padding)."""
        out = np.full(left.shape, NONE)
        todo = np.flatnonzero((left >= 0) & (right >= 0))
        keys = left[todo].astype(np.uint64) << np.uint64(32) | right[todo].astype(np.uint64)
        place = self._home(keys)
        for _ in range(self.longest + 1):
            if not len(todo):
                break
            seen = self.keys[place]
            hit = seen == keys
            out[todo[hit]] = self.ranks[place[hit]]
            on = ~hit & (seen != np.uint64(2**64 - 1))
            todo, keys, place = todo[on], keys[on], (place[on] + 1) & self.mask
        return out


class MatrixBpe:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pattern = ranks, regex.compile(pattern)
        self.pairs = PairTable(ranks)
        self.byte_ids = np.asarray([ranks.get(bytes([b]), -1) for b in range(256)], np.int64)
        if (self.byte_ids < 0).any():
            raise ValueError("every single byte needs a rank")
        self.tokens = [b""] * (max(ranks.values()) + 1)
        for token, r in ranks.items():
            self.tokens[r] = token
        self.known: dict[str, bytes] = {}

    def _rows(self, many: list[bytes], width: int) -> list[np.ndarray]:
        """Ids of words of at most ``width`` bytes."""
        raw = np.frombuffer(b"".join(w.ljust(width, b"\0") for w in many), np.uint8).reshape(len(many), width)
        sizes = np.asarray([len(w) for w in many])
        ids = np.where(np.arange(width) < sizes[:, None], self.byte_ids[raw], -1)
        ranks = self.pairs(ids[:, :-1].ravel(), ids[:, 1:].ravel()).reshape(len(many), width - 1)
        who, done = np.arange(len(many)), [None] * len(many)
        while len(who):
            at = ranks.argmin(axis=1)  # the first of equal minima is the leftmost
            line = np.arange(len(who))
            best = ranks[line, at]
            over = best == NONE
            if over.any():
                for i in np.flatnonzero(over):
                    row = ids[i]
                    done[who[i]] = row[row >= 0]
                keep = ~over
                who, ids, ranks, at, best = who[keep], ids[keep], ranks[keep], at[keep], best[keep]
                line = np.arange(len(who))
                if not len(who):
                    break
            most = int((ids >= 0).sum(axis=1).max())
            ids, ranks = ids[:, :most], ranks[:, : most - 1]
            ids[line, at] = best
            columns = np.arange(most - 1)
            source = np.minimum(columns + (columns > at[:, None]), most - 1)
            ids = np.take_along_axis(ids, source, axis=1) if most > 2 else ids[:, :1]
            if most > 2:
                pair_columns = np.arange(most - 2)
                ranks = np.take_along_axis(ranks, np.minimum(pair_columns + (pair_columns >= at[:, None]), most - 2), axis=1)
                for shift in (-1, 0):
                    p = at + shift
                    ok = (p >= 0) & (p < most - 2)
                    ranks[line[ok], p[ok]] = self.pairs(ids[line[ok], p[ok]], ids[line[ok], p[ok] + 1])
            else:
                ranks = np.full((len(who), 1), NONE)
        return done

    def _long(self, word: bytes) -> list[int]:
        """The same merges for a long word: the leftmost pair of lowest rank from a heap."""
        get = {}
        ids = [self.ranks[bytes([b])] for b in word]
        text = [bytes([b]) for b in word]
        after, before = list(range(1, len(ids) + 1)), list(range(-1, len(ids) - 1))
        heap: list[tuple[int, int, int, int]] = []

        def push(i: int) -> None:
            j = after[i]
            if j < len(ids):
                r = get.get((ids[i], ids[j]), -2)
                if r == -2:
                    r = get[ids[i], ids[j]] = self.ranks.get(text[i] + text[j], -1)
                if r >= 0:
                    heapq.heappush(heap, (r, i, ids[i], ids[j]))

        for i in range(len(ids) - 1):
            push(i)
        while heap:
            r, i, a, b = heapq.heappop(heap)
            j = after[i] if ids[i] == a else len(ids)
            if j >= len(ids) or ids[j] != b:
                continue
            text[i] += text[j]
            ids[i], ids[j], after[i] = r, -1, after[j]
            if after[i] < len(ids):
                before[after[i]] = i
            push(i)
            if before[i] >= 0:
                push(before[i])
        return [x for x in ids if x >= 0]

    def words(self, words: list[str]) -> list[bytes]:
        """Ids of each pre-token, as little-endian unsigned 32-bit bytes."""
        raw = [w.encode() for w in words]
        out: list[bytes] = [b""] * len(raw)
        buckets: dict[int, list[int]] = {}
        for i, w in enumerate(raw):
            if (r := self.ranks.get(w)) is not None:
                out[i] = r.to_bytes(4, "little")
            elif len(w) > MATRIX_MOST:
                out[i] = np.asarray(self._long(w), "<u4").tobytes()
            elif w:
                buckets.setdefault(max(4, -(-len(w) // 4) * 4), []).append(i)
        for width, members in buckets.items():
            for a in range(0, len(members), ROWS_MOST):
                part = members[a : a + ROWS_MOST]
                for i, ids in zip(part, self._rows([raw[k] for k in part], width), strict=True):
                    out[i] = ids.astype("<u4").tobytes()
        return out

    def chunks(self, chunks: list[str]) -> Iterator[tuple[str, bytes]]:
        """Each chunk with its ids: its pre-tokens one by one, unseen ones together."""
        cut = [self.pattern.findall(common.chunk_text(c)) for c in chunks]
        fresh = list({w for words in cut for w in words if w not in self.known})
        if len(self.known) + len(fresh) > 200_000:
            self.known.clear()
            fresh = list({w for words in cut for w in words})
        self.known.update(zip(fresh, self.words(fresh), strict=True))
        return zip(chunks, [b"".join(map(self.known.__getitem__, words)) for words in cut], strict=True)

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.tokens.__getitem__, np.frombuffer(ids, "<u4").tolist()))


class BpeCodec:
    """Whole texts to ids and back."""

    def __init__(self, path: str, pattern: str):
        self.bpe = MatrixBpe(read_ranks(path), pattern)
        self.cache = common.ChunkCache(self.bpe.chunks)

    def encode(self, many: list[str]) -> Iterator[bytes]:
        for start in range(0, len(many), 1024):
            part = many[start : start + 1024]
            cut = {t: common.word_chunks(t) for t in set(part)}
            self.cache.learn(list(cut.values()))
            done = {t: self.cache.join(chunks) for t, chunks in cut.items()}
            for t in part:
                yield done[t]


@functools.lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> BpeCodec:
    return BpeCodec(path, pattern)


def encode(docs, path: str, pattern: str):
    """``doc_id, ids binary, decoded binary``: ids as little-endian unsigned 32-bit, and the bytes decoded from them."""
    import pyarrow as pa

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = codec(path, pattern)
        for part in common.slices(batches):
            ids = list(bpe.encode(part.column(1).to_pylist()))
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.large_binary()).cast(pa.binary()), pa.array([bpe.bpe.decode(x) for x in ids], pa.binary())], ["doc_id", "ids", "decoded"])

    return common.texts(docs).mapInArrow(run, "doc_id long, ids binary, decoded binary")
