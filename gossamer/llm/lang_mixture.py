"""Language identification by multilingual mixtures.

Every language has a distribution over hashed byte n-grams, learnt from labelled documents. A document's
n-grams come from a mixture of languages; expectation-maximisation estimates the proportions, and the set of
languages is chosen by likelihood less a penalty for each language added: from the best single one on, the language
that gains most is added as long as its gain passes the penalty. For a mixture with distribution Q the gain of mixing in l
is at most N (mean(P_l / Q) - 1), by concavity, so EM runs for every language whose bound passes the penalty, and no other.

``kept`` has one more component beside the languages, even over all n-grams: a text of which it explains more than
``UNKNOWN`` is in none of the learnt languages and is rejected.

Learning uses at most ``fit_docs`` documents a language, those with the smallest hash of doc_id: a documented
bound for fitting a classifier on labelled rows. Prediction reads the text alone.

Cases: null texts and texts without a letter are ``und`` with score 0; if nothing could be learnt, every
text is ``und``; equal likelihoods go to the language first in order; texts of any length are read whole;
repeated rows stay; an empty table gives no rows; null doc_ids never take part in learning; more than
``MOST_LANGUAGES`` different labels are an error, none is left out.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

BUCKETS = 1 << 15
SIZES = (2, 3, 4)
FIT_DOCS, FIT_TASKS, MOST_LANGUAGES = 1000, 8, 512
SMOOTHING = 0.5
PENALTY = 6.0  #: times log(n-grams), for each language after the first
ROUNDS, SETTLED = 30, 1e-4
REST = "\0rest"
UNKNOWN = 0.8  #: share of ``REST`` above which a text is in no learnt language
_LETTER = re.compile(r"[^\W\d_]")


def has_letter(text: str) -> bool:
    m = _LETTER.search(text)
    return m is not None and (m[0].isalpha() or any(c.isalpha() for c in text))


def grams(text: str) -> np.ndarray:
    """Hashes of the n-grams of the lower-cased text, white space and digits folded."""
    raw = np.frombuffer(f" {text.lower()} ".encode("utf-8", "surrogatepass"), np.uint8)
    raw = _FOLD[raw].astype(np.uint32)
    out = []
    for n in SIZES:
        if len(raw) >= n:
            h = raw[: len(raw) - n + 1].copy()
            for k in range(1, n):
                h *= np.uint32(0x01000193)
                h ^= raw[k : len(raw) - n + 1 + k]
            h *= np.uint32(0x9E3779B1)
            out.append(h >> np.uint32(17))
    return np.concatenate(out) if out else np.zeros(0, np.uint32)


_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[:33] = 32
_FOLD[48:58] = 48


@dataclass
class Model:
    languages: list[str]
    log_p: np.ndarray  # buckets x languages

    def __post_init__(self) -> None:
        self.p = np.exp(self.log_p.astype(np.float64))
        self.ratio = [(self.p / self.p[:, [b]]).astype(np.float32) for b in range(len(self.languages))] if len(self.languages) <= 32 else None

    def mixture(self, text: str) -> tuple[dict[str, float], float]:
        """The chosen languages with their proportions, and the log-likelihood."""
        h = grams(text)
        n = len(h)
        single = self.log_p[h].sum(axis=0, dtype=np.float64)
        best = int(single.argmax())
        chosen, share, value = [best], np.ones(1), float(single[best])
        penalty = PENALTY * np.log(max(n, 2))
        counts = unique = None
        while len(chosen) < len(self.languages):
            if len(chosen) == 1:
                ratio = self.ratio[best][h] if self.ratio is not None else self.p[h] / self.p[h][:, [best]]
                bound = ratio.mean(axis=0, dtype=np.float64)
            else:
                mixed = self.p[unique][:, chosen] @ share
                bound = counts @ (self.p[unique] / mixed[:, None]) / n
            bound = n * (bound - 1)
            bound[chosen] = -np.inf
            likely = np.flatnonzero(bound > penalty)
            if not len(likely):
                break
            if unique is None:
                unique, counts = np.unique(h, return_counts=True)
            gained, more = value + penalty, None
            for add in likely[np.argsort(-bound[likely], kind="stable")].tolist():
                if value + bound[add] <= gained:  # no later one can gain more
                    break
                trial, own = self._em(unique, counts, n, [*chosen, add])
                if own > gained:
                    gained, more = own, (add, trial)
            if more is None:
                break
            chosen, share, value = [*chosen, more[0]], more[1], gained
        return {self.languages[k]: float(s) for k, s in zip(chosen, share, strict=True)}, value

    def with_rest(self) -> Model:
        """The same with a component for other languages, even over all n-grams, named ``REST``."""
        return Model([*self.languages, REST], np.concatenate([self.log_p, np.full((len(self.log_p), 1), -np.log(len(self.log_p)), np.float32)], axis=1))

    def _em(self, unique: np.ndarray, counts: np.ndarray, n: int, chosen: list[int]) -> tuple[np.ndarray, float]:
        p, share = self.p[unique][:, chosen], np.full(len(chosen), 1 / len(chosen))
        for _ in range(ROUNDS):
            mixed = p @ share
            new = share * ((counts / mixed) @ p) / n
            moved = np.abs(new - share).max()
            share = new
            if moved < SETTLED:
                break
        return share, float(counts @ np.log(p @ share))

    def predict(self, text: str | None) -> tuple[str, float]:
        if text is None or not self.languages or not has_letter(text):
            return "und", 0.0
        shares, _ = self.mixture(text)
        top = max(shares, key=lambda k: (shares[k], -self.languages.index(k)))
        return top, min(1.0, max(0.0, shares[top]))


def held_out(doc_id: Column) -> Column:
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(5)) == 0


def learn(docs: DataFrame, fit_docs: int = FIT_DOCS) -> Model:
    """n-gram counts of at most ``fit_docs`` labelled documents a language outside the held-out fifth."""
    labelled = docs.where("lang is not null and doc_id is not null and text is not null").where(~held_out(F.col("doc_id")))
    counted = labelled.groupBy("lang").agg(F.count("*").alias("rows")).limit(MOST_LANGUAGES + 1).collect()
    if len(counted) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    sizes = docs.sparkSession.createDataFrame([tuple(r) for r in counted], "lang string, rows long")
    placed = labelled.select("doc_id", "lang", common.place("doc_id").alias("h")).join(F.broadcast(sizes), "lang").where(F.col("h") < common.likely(fit_docs, F.col("rows")))
    ranked = placed.withColumn("n", F.row_number().over(Window.partitionBy("lang").orderBy("h", "doc_id"))).where(F.col("n") <= fit_docs)
    # fit_docs * MOST_LANGUAGES ids at most
    sample = labelled.select("doc_id", "lang", "text").join(F.broadcast(ranked.select("doc_id")), "doc_id", "left_semi").repartition(FIT_TASKS)

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[str, np.ndarray] = {}
        for part in common.slices(batches):
            for lang, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                if has_letter(text):
                    totals[lang] = totals.get(lang, 0) + np.bincount(grams(text), minlength=BUCKETS)
        yield pa.RecordBatch.from_arrays([pa.array(list(totals), pa.string()), pa.array([v.astype("<i8").tobytes() for v in totals.values()], pa.binary())], ["lang", "counts"])

    totals: dict[str, np.ndarray] = {}
    for row in sample.select("lang", "text").mapInArrow(count, "lang string, counts binary").toLocalIterator():
        totals[row.lang] = totals.get(row.lang, 0) + np.frombuffer(row.counts, "<i8")
    languages = sorted(totals)
    if not languages:
        return Model([], np.zeros((BUCKETS, 0), np.float32))
    counts = np.stack([totals[k] for k in languages], axis=1) + SMOOTHING
    return Model(languages, np.log(counts / counts.sum(axis=0)).astype(np.float32))


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """``doc_id, lang_pred, score, mixture`` for every document; reads doc_id and text only."""
    sent = docs.sparkSession.sparkContext.broadcast((model.languages, model.log_p))  # BUCKETS x languages floats

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Model(*sent.value)
        for part in common.slices(batches):
            known: dict[str | None, tuple[str, float]] = {}
            many = part.column(1).to_pylist()
            for t in many:
                if t not in known:
                    known[t] = own.predict(t)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array([known[t][0] for t in many], pa.string()), pa.array([known[t][1] for t in many], pa.float64())], ["doc_id", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, lang_pred string, score double")


def identified(docs: DataFrame, fit_docs: int = FIT_DOCS) -> DataFrame:
    found = predict(docs, learn(docs, fit_docs))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def kept(docs: DataFrame, fit_docs: int = FIT_DOCS, languages: frozenset[str] | None = None, least: float = 0.0) -> DataFrame:
    """The documents whose text is in a learnt language, with all their columns; the others are rejected.

    Rejected are texts without a letter, texts of which ``REST`` explains more than ``UNKNOWN``, and, if asked for, those
    whose main language is not in ``languages`` or has a share below ``least`` of what languages explain. If no
    language could be learnt, null texts and texts without a letter are rejected and nothing else.
    """
    model = learn(docs, fit_docs)
    schema = docs.schema
    sent = docs.sparkSession.sparkContext.broadcast((model.languages, model.log_p))
    at = docs.columns.index("text")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Model(*sent.value).with_rest()
        known = len(own.languages) > 1

        def stays(text: str | None) -> bool:
            if text is None or not has_letter(text):
                return False
            if not known:
                return True
            shares, _ = own.mixture(text)
            rest = shares.pop(REST, 0.0)
            if rest > UNKNOWN or not shares:
                return False
            lang, share = max(shares.items(), key=lambda x: (x[1], -own.languages.index(x[0])))
            return share >= least * (1 - rest) and (languages is None or lang in languages)

        for part in common.slices(batches):
            many = part.column(at).to_pylist()
            decided = {t: stays(t) for t in set(many)}
            yield part.filter(pa.array([decided[t] for t in many], pa.bool_()))

    return docs.mapInArrow(run, schema)
