"""Helpers that the training-data operators share: bounded batches, shared tables, token chunks."""

from __future__ import annotations

import functools
import re
import tempfile
import unicodedata
import uuid
from codecs import charmap_decode
from collections.abc import Iterable, Iterator
from operator import itemgetter

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: UTF-8 bytes of text that one slice of an Arrow batch holds at most (one longer text forms a slice alone).
SLICE_BYTES = 8 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(docs: DataFrame, *more: str) -> DataFrame:
    """``(doc_id, text, ...)`` with null text as the empty string; other columns are not read."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), *more)


def slices(batches: Iterable[pa.RecordBatch], column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Zero-copy slices of every batch whose ``column`` holds about ``most`` bytes each.

    Freed memory goes back to the system before each batch: workers that tasks share do not keep their peaks.
    """
    for batch in batches:
        pa.default_memory_pool().release_unused()
        n = batch.num_rows
        if batch.nbytes <= most or n < 2:
            if n:
                yield batch
            continue
        values = batch.column(batch.schema.get_field_index(column))
        sizes = np.asarray(pc.fill_null(pc.binary_length(values), 0).to_numpy(zero_copy_only=False))
        cell = np.cumsum(sizes, dtype=np.int64) // most
        cuts = [0, *(np.flatnonzero(np.diff(cell)) + 1).tolist(), n]
        for a, b in zip(cuts, cuts[1:], strict=False):
            if b > a:
                yield batch.slice(a, b - a)
    pa.default_memory_pool().release_unused()


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or a new one where that is unset (tests)."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        where = "file://" + tempfile.mkdtemp(prefix="gossamer-")
        spark.sparkContext.setCheckpointDir(where)
        where = spark.sparkContext.getCheckpointDir()
    return where.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def settled(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once as Parquet into the shared folder and read back: cuts lineage, survives lost executors."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Hash places of rows; a bounded sample takes the rows with the smallest places.
PLACES = 1 << 30


def place(*key) -> Column:
    return F.pmod(F.xxhash64(*key), F.lit(PLACES))


def likely(most: int, rows: Column) -> Column:
    """A bound on places below which the ``most`` smallest of ``rows`` lie almost surely: about four times as many do.

    It cuts the rows before they are ranked, so that what meets in one task does not grow with the number of tasks.
    """
    return F.ceil(F.least(F.lit(1.0), F.lit(4.0 * most + 100) / rows) * F.lit(PLACES))


# --- text to token ids through cached chunks -------------------------------------------------

_LOOSE_SPACE = re.compile(r" (?=\s|\Z)")
_BEFORE_WORD = re.compile(r" (?=\S)")
#: Stands before the first chunk of a text; no valid text holds it. Chunks without it follow a space.
FIRST = "\ud800"


def word_chunks(text: str) -> list[str]:
    """Cuts before each space that a non-space follows.

    A pre-token of the byte-level pattern can span such a cut only by starting at it, so the chunks
    can be encoded one by one. The spaces cut at are left out; ``FIRST`` marks a first chunk.
    """
    parts = _BEFORE_WORD.split(text) if _LOOSE_SPACE.search(text) else text.split(" ")
    if parts[0]:
        parts[0] = FIRST + parts[0]
        return parts
    return parts[1:]


def chunk_text(chunk: str) -> str:
    return chunk[1:] if chunk[0] == FIRST else " " + chunk


class ChunkCache(dict):
    """chunk -> ids as little-endian unsigned 32-bit bytes; beyond ``most`` chunks it keeps those in use only.

    ``encode`` takes a list of chunks and gives what ``dict.update`` takes.
    """

    def __init__(self, encode, most: int = 400_000):
        super().__init__()
        self.encode, self.most = encode, most

    def learn(self, many: list[list[str]]) -> None:
        used = set().union(*many)
        fresh = used.difference(self)
        if fresh:
            if len(self) + len(fresh) > self.most:
                held = {c: self[c] for c in used.difference(fresh)}
                self.clear()
                self.update(held)
            self.update(self.encode(list(fresh)))

    def join(self, chunks: list[str]) -> bytes:
        return b"".join(itemgetter(*chunks)(self)) if len(chunks) > 1 else self[chunks[0]] if chunks else b""


# --- whole texts with the ids of the tokenizers library ------------------------------------------------

#: A noncharacter before the first chunk of a text in Arrow columns; texts that hold it are encoded whole.
_MARK = "\U0010ffff"
#: RE2 pattern of a space that no non-space follows, and of ``_MARK``; every kind of white space counts.
_ODD = r" ([\s\x0b\x1c-\x1f\x{85}\pZ]|\z)|\x{10ffff}"
#: In bytes that no UTF-8 text has: a space that belongs to the pre-token after it.
_GAP = b"\xff"
_NONE, _LETTER_KIND, _NUMBER, _OTHER, _LINE = range(5)


def _settled_characters() -> str:
    """Characters whose class and case every Unicode version agrees on: Latin letters, signs, common punctuation.

    Left out: unassigned and combining ones, ones that normal form C or lower-casing turns into others or several.
    """
    wide = [*range(0x250), *range(0x2010, 0x2028), 0x20AC]
    return "".join(c for c in map(chr, wide) if unicodedata.category(c) not in ("Cn", "Mn") and unicodedata.normalize("NFC", c) == c and len(c.lower()) == 1 and (ord(c.lower()) < 0x250 or c.lower() == c))


class TextEncoder:
    """Whole texts to ids (little-endian unsigned 32-bit bytes) with the tokenizers library, each chunk of a slice once.

    Texts are cut where no pre-token crosses and Arrow finds the distinct chunks of a slice. All ids come from the library.
    Chunks of settled characters are cut into pre-tokens by Arrow and go to the library's merge model (the same file
    without its normalizer, pre-tokens between spaces), many in a call; the letters that tokens stand for tell where
    each chunk ends. Other chunks go through the library's whole chain. Nothing is kept from one slice to the next.
    The strings of special tokens count as ordinary text.
    """

    def __init__(self, path: str, splits: str, group: int = 4096):
        import json
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        os.environ.setdefault("RAYON_NUM_THREADS", "1")
        import public_tokenizers
        import regex
        from tokenizers import Tokenizer

        self.tokenizer, self.splits, self.group = Tokenizer.from_file(path), splits, group
        with open(path, encoding="utf-8") as f:
            own = json.load(f)
        self.model = Tokenizer.from_str(json.dumps(own | {"normalizer": None, "pre_tokenizer": {"type": "WhitespaceSplit"}, "post_processor": None}))
        for t in (self.tokenizer, self.model):
            t.encode_special_tokens = True
        word = splits == "word"
        self.pattern = regex.compile(public_tokenizers.PATTERN if word else own["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        letters = _byte_letters()
        self.letters = "".join(" " if b == 0x20 else letters[0x20] if b == _GAP[0] else letters[b] for b in range(256))
        known = _settled_characters()
        self.rare = re.compile(f"[^{re.escape(known)}]")
        usual = "".join(f"\\x{{{ord(c):x}}}" for c in known if not c.isspace() and c != "'")
        # no apostrophe, no white space but single line ends: then pre-tokens are runs of letters, numbers and signs
        self.plain = f"^{_MARK}?[{usual}]+(\n[{usual}]+)*$" if word else f"^[{usual}]+$"
        self.kinds = np.full(0x2100, _OTHER, np.uint8)
        for c in known:
            self.kinds[ord(c)] = {"L": _LETTER_KIND, "N": _NUMBER}.get(unicodedata.category(c)[0], _LINE if c == "\n" else _OTHER)
        self.kinds[-1] = _NONE  # of ``_GAP``
        vocabulary = self.model.get_vocab(with_added_tokens=False)
        self.sizes = np.zeros(max(vocabulary.values()) + 1, np.int64)
        for token, i in vocabulary.items():
            self.sizes[i] = len(token if word else token.removesuffix("</w>"))

    def whole(self, text: str) -> bytes:
        return np.asarray(self.tokenizer.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def chained(self, words: list[str]) -> Iterator[bytes]:
        """Ids of each word by the library's whole chain, many words a call."""
        for a in range(0, len(words), self.group):
            part = words[a : a + self.group]
            got = self.tokenizer.encode(part, is_pretokenized=True, add_special_tokens=False)
            raw = np.asarray(got.ids, dtype="<u4").tobytes()
            ends = (4 * np.searchsorted(np.asarray(got.word_ids, dtype=np.int64), np.arange(len(part) + 1))).tolist()
            for x, y in zip(ends, ends[1:], strict=False):
                yield raw[x:y]

    def merged(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all pre-tokens one after another, and the borders between them."""
        cut = pc.binary_join_element_wise(words, pa.scalar(b"", pa.large_binary()), pa.scalar(b" ", pa.large_binary()))
        at, raw = _buffers(cut)
        shown = charmap_decode(raw, "strict", self.letters)[0]
        stops = [*range(0, len(cut), self.group), len(cut)]
        got = self.model.encode_batch_fast([shown[at[a] : at[b]] for a, b in zip(stops, stops[1:], strict=False)], add_special_tokens=False)
        ids = np.concatenate([np.asarray(g.ids, dtype="<u4") for g in got]) if got else np.zeros(0, "<u4")
        reach = at - np.arange(len(at))  # letters up to each border
        laid = np.concatenate([[0], np.cumsum(self.sizes[ids])])
        ends = np.searchsorted(laid, reach)
        if (laid[ends] != reach).any():
            raise ValueError("the vocabulary lacks single bytes")
        return ids, ends

    def plain_cut(self, chunks: pa.Array) -> tuple[pa.Array, np.ndarray]:
        """The pre-tokens of plain chunks in bytes, ``_GAP`` for a space before one, and how many precede each border of chunks."""
        if self.splits == "word":
            kinds = pa.large_binary()
            before = pc.if_else(pc.starts_with(chunks, _MARK), pa.scalar(b"", kinds), pa.scalar(_GAP, kinds))
            chunks = pc.binary_join_element_wise(before, pc.replace_substring(chunks, _MARK, "").cast(kinds), pa.scalar(b"", kinds))
        else:
            chunks = pc.utf8_lower(chunks)
        at, raw = _buffers(chunks)
        kind = self.kinds[np.minimum(np.frombuffer(bytes(raw).decode("utf-8", "replace").encode("utf-32-le"), "<u4"), len(self.kinds) - 1)]
        place = np.flatnonzero(np.frombuffer(raw, np.uint8) & 0xC0 != 0x80)  # where characters begin
        new = np.zeros(len(kind), bool)
        new[1:] = (kind[1:] != kind[:-1]) & (kind[:-1] != _NONE)
        if self.splits != "word":
            new |= kind == _NUMBER
        new[np.searchsorted(place, at[:-1])] = True
        borders = np.append(place[new], len(raw))
        return _binary(borders, raw), np.searchsorted(borders, at)

    def ids_of(self, chunks: pa.Array) -> tuple[pa.Array, np.ndarray]:
        """Ids of distinct chunks as large binary, in an order of its own, and the place of each chunk there."""
        is_plain = pc.match_substring_regex(chunks, self.plain)
        mask = is_plain.to_numpy(zero_copy_only=False)
        near, far, cut, sizes = [], [], [], []
        for c in chunks.filter(pc.invert(is_plain)).to_pylist():
            t = c if self.splits != "word" else " " + c if c[:1] != _MARK else c[1:]
            near.append(t.isascii() or not self.rare.search(t))
            if near[-1]:
                pre = self.pattern.findall(t if self.splits == "word" else t.lower())
                cut += [p.encode().replace(b" ", _GAP) for p in pre]
                sizes.append(len(pre))
            else:
                far.append(t)
        words, borders = self.plain_cut(chunks.filter(is_plain))
        coded = pa.concat_arrays([words, pa.array(cut, pa.large_binary())]).dictionary_encode()
        borders = np.concatenate([borders, len(words) + np.cumsum(sizes, dtype=np.int64)])
        ids, ends = self.merged(coded.dictionary)
        at, laid = _buffers(_binary(4 * ends, ids).take(coded.indices))
        found = _binary(at[borders], laid)
        near, place, n = np.asarray(near, bool), np.empty(len(chunks), np.int64), int(mask.sum())
        rest = np.empty(len(near), np.int64)
        rest[near], rest[~near] = n + np.arange(len(sizes)), n + len(sizes) + np.arange(len(far))
        place[mask], place[~mask] = np.arange(n), rest
        return pa.concat_arrays([found, pa.array(self.chained(far), pa.large_binary(), size=len(far))]) if far else found, place

    def joined(self, lists: pa.ListArray) -> Iterator[bytes]:
        """Ids of each list of chunks: distinct chunks are encoded, Arrow lays their ids out in order."""
        coded, bounds = lists.flatten().dictionary_encode(), np.cumsum([0, *lists.value_lengths().to_numpy(zero_copy_only=False).tolist()])
        if not len(coded):
            yield from (b"" for _ in range(len(lists)))
            return
        ids, place = self.ids_of(coded.dictionary)
        laid = ids.take(pa.array(place[coded.indices.to_numpy()]))
        at, data = _buffers(laid)
        at = at[bounds].tolist()
        for x, y in zip(at, at[1:], strict=False):
            yield bytes(data[x:y])

    def batch(self, column: pa.Array | list[str]) -> Iterator[bytes]:
        """Ids of each text of a column without nulls."""
        column = pa.array(column, pa.large_string()) if isinstance(column, list) else column.cast(pa.large_string())
        if self.splits != "word":
            yield from self.joined(pc.ascii_split_whitespace(column))
            return
        odd = pc.match_substring_regex(column, _ODD)
        usual = self.joined(pc.split_pattern(pc.binary_join_element_wise(pa.scalar(_MARK, pa.large_string()), column, pa.scalar("", pa.large_string())).filter(pc.invert(odd)), " "))
        strange = column.filter(odd).to_pylist()
        cut = [[_MARK + c[1:] if c[0] == FIRST else c for c in word_chunks(t)] for t in strange if _MARK not in t]
        rest = self.joined(pa.array(cut, pa.list_(pa.large_string())))
        strange = iter(strange)
        for k in odd.to_pylist():
            if not k:
                yield next(usual)
            else:
                yield self.whole(t) if _MARK in (t := next(strange)) else next(rest)


def _buffers(values: pa.Array) -> tuple[np.ndarray, memoryview]:
    """Borders, from 0, and bytes of a large binary or string array without nulls."""
    if not len(values):
        return np.zeros(1, np.int64), memoryview(b"")
    at = np.frombuffer(values.buffers()[1], np.int64)[values.offset : values.offset + len(values) + 1]
    return at - at[0], memoryview(values.buffers()[2] or b"")[at[0] : at[-1]]


def _binary(borders: np.ndarray, data) -> pa.Array:
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(borders) - 1, [None, pa.py_buffer(np.ascontiguousarray(borders, np.int64)), pa.py_buffer(data)])


def _byte_letters() -> dict[int, str]:
    """Byte -> the printable character that stands for it in byte-level vocabularies."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    return {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(sorted(set(range(256)) - set(shown)))}


@functools.lru_cache(maxsize=4)
def text_encoder(path: str, splits: str) -> TextEncoder:
    """One encoder for all tasks that a Python worker runs."""
    return TextEncoder(path, splits)
