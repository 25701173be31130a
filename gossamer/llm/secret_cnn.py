"""Secret scanning: fixed patterns, and a character convolutional network over every candidate.

Findings of the three base patterns always stay. Candidates are their values and every other long run of key-like
characters, value after a wider list of key words, and password in a URL. Each is read by a small network in numpy:
characters of the candidate and of its surroundings are embedded with a mark of which are inside, convolved, max-pooled over
the candidate and over its context, and scored; a candidate longer than a window is read by overlapping windows, and its
largest score counts. Base findings carry their probability; other candidates are findings where theirs reaches the threshold.

Training examples are labelled findings of a bounded sample of documents: values of base findings are secrets; other candidates
(but those of a known secret format) and words are not; findings built here from known formats, and look-alikes, are placed into
contexts of the sample. Documents, and the examples built into them, are split in three: one part trains, one calibrates the scores
(Platt), one sets the threshold: the largest that keeps ``RECALL`` of its secrets.

Cases: null and empty texts have no findings; texts of any length are scanned whole; overlapping findings of
different kinds all stay, network findings only outside base ones; repeated rows stay; with no documents the
network learns from the built findings alone; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from itertools import accumulate, chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

KINDS = ("assign", "access", "hex", "learnt")
FIT_DOCS = 2000  #: documents that training reads at most, those with the smallest hash of doc_id
FIT_EACH = 8  #: findings, and other candidates, that training takes of a document at most, drawn from its whole text
LONG = 192  #: characters of a candidate in a training example, a place drawn at random in longer ones
INSIDE, AROUND = 48, 24
WINDOW = INSIDE + 2 * AROUND
RECALL = 0.95

#: The base patterns. Runs are maximal, so a least length drops the same ones as a later test.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{12,}")
HEX = re.compile(r"[0-9a-f]{32,}")
#: Wider candidates for the network.
RUN = re.compile(r"[A-Za-z0-9+/_.=-]{12,}")
NAMED = re.compile(r"""(?:pwd|passphrase|credential|auth|bearer|access_?key|private_?key|client_?id|signature)["']?\x20*[:=]?\x20*["']?([A-Za-z0-9+/_.=~!@#$%^&*-]{8,})""", re.IGNORECASE | re.ASCII)
URL_PASSWORD = re.compile(r"[a-z][a-z0-9+]{1,15}://[^\s:/@]{1,64}:([^\s/@]{4,128})@")
_DIGIT, _ALPHA = re.compile(r"[0-9]"), re.compile(r"[A-Za-z]")
_WORD = re.compile(r"[^\W_]{4,14}", re.ASCII)
#: Formats of known secrets: such candidates are no examples of other text.
KNOWN = re.compile(r"gh[pousr]_|xox[abp]-|sk_live_|AIza|eyJ|AKIA")


def base_findings(text: str) -> list[tuple[int, int, int]]:
    """Start, number of the kind, end."""
    found = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 8]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text)]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def value_of(text: str, start: int, kind: int, end: int) -> tuple[int, int]:
    """The part of a base finding that the network reads: of an assignment the value."""
    return (ASSIGN.match(text, start).start(2), end) if kind == 0 else (start, end)


def candidates(text: str, taken: list[tuple[int, int, int]]) -> list[tuple[int, int]]:
    """Spans that base findings do not touch, in order and without overlap."""
    spans = [m.span() for m in RUN.finditer(text) if _DIGIT.search(m[0])]
    spans += [m.span(1) for m in NAMED.finditer(text) if _DIGIT.search(m[1])]
    if "://" in text:
        spans += [m.span(1) for m in URL_PASSWORD.finditer(text)]
    out: list[tuple[int, int]] = []
    starts, ends = [x for x, _, _ in taken], [0, *accumulate((y for _, _, y in taken), max)]
    for a, b in sorted(spans):
        if a >= ends[bisect_left(starts, b)] and (not out or a >= out[-1][1]):
            out.append((a, b))
    return out


# --- the network ----------------------------------------------------------------------------------------

_CLASSES = 100


def _codes(chars: str) -> np.ndarray:
    c = np.frombuffer(chars.encode("utf-32-le", "surrogatepass"), np.uint32)
    return np.where(c < 32, 1, np.where(c < 127, c - 30, 97)).astype(np.uint8)  # 0: nothing there


def windows(text: str, a: int, b: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Character classes of context, candidate and context, and which are inside; long candidates in overlapping pieces."""
    for x in [a] if b - a <= INSIDE else chain(range(a, b - INSIDE, INSIDE // 2), [b - INSIDE]):
        y = min(b, x + INSIDE)
        low = max(0, x - AROUND)
        codes, mark = np.zeros(WINDOW, np.uint8), np.zeros(WINDOW, bool)
        shown, at = _codes(text[low : y + AROUND]), AROUND - (x - low)
        codes[at : at + len(shown)] = shown
        mark[max(0, a - x + AROUND) : min(WINDOW, b - x + AROUND)] = True
        yield codes, mark


def stacked(spans: list[tuple[str, int, int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Windows of many candidates, and the number of each window's candidate."""
    found = [(i, w) for i, (text, a, b) in enumerate(spans) for w in windows(text, a, b)]
    if not found:
        return np.zeros((0, WINDOW), np.uint8), np.zeros((0, WINDOW), bool), np.zeros(0, np.int64)
    return np.stack([w[0] for _, w in found]), np.stack([w[1] for _, w in found]), np.asarray([i for i, _ in found])


@dataclass
class Net:
    """Embedding, one convolution, max-pooling inside and outside, one dense layer."""

    embed: np.ndarray
    filters: np.ndarray  # width * (depth + 1) x filters
    bias: np.ndarray
    dense: np.ndarray
    out: float
    slope: float = 1.0
    shift: float = 0.0
    threshold: float = 0.5
    held_out: dict = field(default_factory=dict)  # recall and precision on the part that sets the threshold

    WIDTH = 5

    @staticmethod
    def fresh(rng: np.random.Generator, depth: int = 10, filters: int = 24) -> Net:
        wide = Net.WIDTH * (depth + 1)
        return Net(rng.normal(0, 0.3, (_CLASSES, depth)).astype(np.float32), rng.normal(0, wide**-0.5, (wide, filters)).astype(np.float32), np.zeros(filters, np.float32), rng.normal(0, 0.1, 2 * filters).astype(np.float32), 0.0)

    def forward(self, codes: np.ndarray, mark: np.ndarray):
        x = np.concatenate([self.embed[codes], mark[..., None].astype(np.float32)], axis=2)
        n, length, depth = x.shape
        patches = np.lib.stride_tricks.sliding_window_view(x, self.WIDTH, axis=1).transpose(0, 1, 3, 2).reshape(n, length - self.WIDTH + 1, -1)
        hidden = np.maximum(patches @ self.filters + self.bias, 0)
        middle = mark[:, self.WIDTH // 2 : length - self.WIDTH // 2, None]
        pooled, at = [], []
        for own in (middle, ~middle):
            masked = np.where(own, hidden, 0)
            k = masked.argmax(axis=1)
            at.append(k)
            pooled.append(np.take_along_axis(masked, k[:, None, :], axis=1)[:, 0])
        features = np.concatenate(pooled, axis=1)
        return features @ self.dense + self.out, (x, patches, pooled, at, features)

    def logits(self, codes: np.ndarray, mark: np.ndarray) -> np.ndarray:
        return np.concatenate([self.forward(codes[a : a + 512], mark[a : a + 512])[0] for a in range(0, len(codes), 512)]) if len(codes) else np.zeros(0)

    def scores(self, spans: list[tuple[str, int, int]]) -> np.ndarray:
        """The largest logit of each candidate ``(text, start, end)``; a bounded number of windows at a time."""
        best, held = np.full(len(spans), -np.inf), []

        def flush() -> None:
            if held:
                who, codes, mark = zip(*held, strict=True)
                np.maximum.at(best, np.asarray(who), self.logits(np.stack(codes), np.stack(mark)))
                held.clear()

        for i, span in enumerate(spans):
            for codes, mark in windows(*span):
                held.append((i, codes, mark))
                if len(held) >= 512:
                    flush()
        flush()
        return best

    def probability(self, z: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * z + self.shift, -30, 30)))

    def train(self, codes: np.ndarray, mark: np.ndarray, y: np.ndarray, rng: np.random.Generator, epochs: int = 12, rate: float = 0.004, batch: int = 128) -> None:
        names = ("embed", "filters", "bias", "dense")
        m1 = {k: np.zeros_like(getattr(self, k)) for k in names} | {"out": 0.0}
        m2 = {k: np.zeros_like(getattr(self, k)) for k in names} | {"out": 0.0}
        step = 0
        for _ in range(epochs):
            order = rng.permutation(len(y))
            for a in range(0, len(y), batch):
                own = order[a : a + batch]
                z, (x, patches, pooled, at, features) = self.forward(codes[own], mark[own])
                dz = ((1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[own]) / len(own)).astype(np.float32)
                grads = {"dense": features.T @ dz, "out": float(dz.sum())}
                back = dz[:, None] * self.dense
                n_filters = len(self.bias)
                g_filters, g_bias, g_embed = np.zeros_like(self.filters), np.zeros_like(self.bias), np.zeros_like(self.embed)
                row, f = np.arange(len(own))[:, None], np.arange(n_filters)[None, :]
                for half in (0, 1):
                    d = back[:, half * n_filters : (half + 1) * n_filters] * (pooled[half] > 0)
                    picked = patches[row, at[half]]  # examples x filters x patch
                    g_filters += np.einsum("nf,nfp->pf", d, picked)
                    g_bias += d.sum(axis=0)
                    to_patch = (d[:, :, None] * self.filters.T[None]).reshape(len(own), n_filters, self.WIDTH, -1)[..., :-1]
                    chars = codes[own][row[:, :, None], at[half][:, :, None] + np.arange(self.WIDTH)]
                    np.add.at(g_embed, chars.ravel(), to_patch.reshape(-1, to_patch.shape[-1]))
                grads |= {"filters": g_filters, "bias": g_bias, "embed": g_embed}
                step += 1
                for k, g in grads.items():
                    m1[k] = 0.9 * m1[k] + 0.1 * g
                    m2[k] = 0.999 * m2[k] + 0.001 * g * g
                    move = rate * (m1[k] / (1 - 0.9**step)) / (np.sqrt(m2[k] / (1 - 0.999**step)) + 1e-8)
                    setattr(self, k, getattr(self, k) - (float(move) if k == "out" else move.astype(np.float32)))

    def calibrate(self, z: np.ndarray, y: np.ndarray) -> None:
        """Platt scaling by Newton steps."""
        a, b = 1.0, 0.0
        target = np.where(y > 0, (y.sum() + 1) / (y.sum() + 2), 1 / ((1 - y).sum() + 2))
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(a * z + b, -30, 30)))
            w = np.maximum(p * (1 - p), 1e-9)
            g = np.asarray([((p - target) * z).sum() + 1e-3 * (a - 1), (p - target).sum()])
            h = np.asarray([[(w * z * z).sum() + 1e-3, (w * z).sum()], [(w * z).sum(), w.sum() + 1e-6]])
            move = np.linalg.solve(h, g)
            a, b = a - move[0], b - move[1]
            if np.abs(move).max() < 1e-6:
                break
        self.slope, self.shift = float(a), float(b)

    def constrain(self, z: np.ndarray, y: np.ndarray, recall: float) -> None:
        """The largest threshold at which ``recall`` of the secrets are found."""
        sure = np.sort(self.probability(z[y > 0]))
        if len(sure):
            self.threshold = float(sure[int(np.floor((1 - recall) * len(sure)))])


# --- labelled findings ----------------------------------------------------------------------------------

_UPPER, _LOWER, _DIGITS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz", "0123456789"


def _draw(rng: np.random.Generator, alphabet: str, n: int) -> str:
    return "".join(alphabet[k] for k in rng.integers(0, len(alphabet), n))


def _built_secret(rng: np.random.Generator) -> tuple[str, str, str]:
    """What stands before, a value in a known format, what stands after."""
    mixed = _UPPER + _LOWER + _DIGITS
    size = int(rng.integers(20, 60))
    kinds = [
        ("", "ghp_" + _draw(rng, mixed, 36), ""), ("", "xoxb-" + _draw(rng, _DIGITS, 12) + "-" + _draw(rng, mixed, 24), ""), ("key ", "sk_live_" + _draw(rng, mixed, 24), ""), ("", "AIza" + _draw(rng, mixed + "-_", 35), ""),
        ("Authorization: Bearer ", "eyJ" + _draw(rng, mixed + "-_", size), ""), ('pwd="', _draw(rng, mixed + "!@#$%", int(rng.integers(10, 20))), '"'), ("auth: ", _draw(rng, mixed + "+/", size) + "=", ""), ("postgres://user:", _draw(rng, mixed, int(rng.integers(10, 24))), "@db.example.com/main"),
        ("private_key = ", _draw(rng, mixed + "+/", size), ""), ("", _draw(rng, mixed + "+/", 40), ""), ("credential=", _draw(rng, mixed, size), ""),
    ]
    return kinds[int(rng.integers(len(kinds)))]


def _built_other(rng: np.random.Generator, words: list[str]) -> tuple[str, str, str]:
    """Look-alikes that are no secrets."""
    pick = lambda: words[int(rng.integers(len(words)))]
    year, n = int(rng.integers(1990, 2030)), int(rng.integers(1, 9999))
    kinds = [
        ("https://www.example.com/", f"{pick()}-{pick()}-{pick()}-{pick()}-{n}", " "), ("", f"{pick()}_{pick()}_{pick()}_{pick()}{n}", " "), ("file ", f"{pick()}-{year}-{n:04d}-{pick()}-{pick()}", ".txt"), ("", f"{pick()}{pick()}{pick()}{pick()}{n % 100}", " "),
        ("auth: ", f"see-section-{n}", " "), ("", f"{year}-{n % 12 + 1:02d}-{n % 28 + 1:02d}T{n % 24:02d}-00-00Z-{pick()}", " "), ("", "=" * 20 + str(n) + "x" + "=" * 10, ""), ("isbn ", f"978-{n:04d}-{n * 7 % 9999:04d}-{n % 9}-{pick()}-{pick()}", " "), ("pwd: ", f"example{n % 10}", " "), ("", "-".join(pick() for _ in range(5)) + str(n % 10), ""),
    ]
    return kinds[int(rng.integers(len(kinds)))]


#: kind, part (of ``PARTS``), text, start, end of the example in it
Example = tuple[str, int, str, int, int]
PARTS = 5  #: of documents: three train, one calibrates, one sets the threshold


def shown(text: str, seed: int) -> list[Example]:
    """Examples of a document, drawn from its whole text: findings, other candidates, a word and a place for built ones."""
    key = xxhash.xxh64_intdigest(text.encode("utf-8", "surrogatepass"), seed)
    rng, part = np.random.default_rng(key), key % PARTS
    found, out = base_findings(text), []

    def add(kind: str, a: int, b: int) -> None:
        if b - a > LONG:
            a += int(rng.integers(0, b - a - LONG + 1))
            b = a + LONG
        low = max(0, a - AROUND)
        out.append((kind, part, text[low : b + AROUND], a - low, b - low))

    spans = {"secret": [value_of(text, *f) for f in found], "other": [(a, b) for a, b in candidates(text, found) if not KNOWN.match(text, a)]}
    for kind, own in spans.items():
        for k in sorted(rng.choice(len(own), min(FIT_EACH, len(own)), replace=False).tolist()) if own else ():
            add(kind, *own[k])
    if text:
        m = _WORD.search(text, int(rng.integers(len(text))))
        if m and not any(x < m.end() and m.start() < y for x, _, y in found):
            add("word", *m.span())
        place = text.find(" ", int(rng.integers(len(text)))) + 1
        add("place", place, place)
    return out


def built(sample: list[Example], rng: np.random.Generator, many: int) -> list[Example]:
    """Secrets of known formats and look-alikes, put into places of the sample; each in the part of its place."""
    words = ["alpha", "report", "second", "table", "green", "window", "market", "number", *[t[a:b] for kind, _, t, a, b in sample if kind == "word"]]
    places = [x for x in sample if x[0] == "place"] or [("place", k, "the value is here and then more", 13, 13) for k in range(PARTS)]
    out: list[Example] = []
    for k in range(many):
        _, part, context, cut, _ = places[int(rng.integers(len(places)))]
        kind = ("secret", "other")[k % 2]
        before, value, after = _built_secret(rng) if kind == "secret" else _built_other(rng, words)
        at = cut + len(before)
        out.append((kind, part, context[:cut] + before + value + after + " " + context[cut:], at, at + len(value)))
    return out


def fit(docs: DataFrame, fit_docs: int = FIT_DOCS, seed: int = 7) -> Net:
    """Trains on at most ``fit_docs`` different rows; the sample is the same for the same rows, whatever their order."""
    usable = docs.where("doc_id is not null and text is not null").select("doc_id", "text", F.xxhash64("text").alias("tie"))
    placed = usable.select("doc_id", "tie", common.place("doc_id").alias("h")).where(F.col("h") < common.likely(fit_docs, F.lit(max(1, docs.count()))))
    ids = placed.distinct().orderBy("h", "doc_id", "tie").limit(fit_docs).select("doc_id", "tie")
    rows = usable.join(F.broadcast(ids), ["doc_id", "tie"], "left_semi")

    def show(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches):
            found = [x for t in set(part.column(0).to_pylist()) for x in shown(t, seed)]
            kinds = (pa.string(), pa.int32(), pa.string(), pa.int32(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*found, strict=True) if found else [[]] * 5, kinds, strict=True)], ["kind", "part", "text", "a", "b"])

    got = rows.select("text").mapInArrow(show, "kind string, part int, text string, a int, b int").distinct()
    return trained([tuple(r) for r in got.toLocalIterator()], seed)  # 2 * FIT_EACH + 2 short rows a document at most


def trained(sample: list[Example], seed: int = 7, many: int = 3000) -> Net:
    """A net from examples; rows of any order give the same one."""
    rng, sample = np.random.default_rng(seed), sorted(sample)
    every = [x for x in sample if x[0] != "place"] + built(sample, rng, many)
    codes, mark, who = stacked([x[2:] for x in every])
    y, part = np.asarray([x[0] == "secret" for x in every], np.float32), np.asarray([x[1] for x in every])
    net, own = Net.fresh(rng), part[who] < PARTS - 2
    net.train(codes[own], mark[own], y[who][own], rng)
    z = net.scores([x[2:] for x in every])
    net.calibrate(z[part == PARTS - 2], y[part == PARTS - 2])
    last = part == PARTS - 1
    net.constrain(z[last], y[last], RECALL)
    sure = net.probability(z[last]) >= net.threshold
    net.held_out = {"secrets": int(y[last].sum()), "others": int((1 - y[last]).sum()), "recall": float(sure[y[last] > 0].mean()) if y[last].any() else 1.0, "precision": float(y[last][sure].mean()) if sure.any() else 1.0}
    return net


#: start, kind, end, probability
Finding = tuple[int, int, int, float]


def scored(texts: list[str], net: Net) -> list[tuple[list[Finding], int]]:
    """Of each text all findings by start, then kind, and how many candidates the network read."""
    base = [base_findings(t) for t in texts]
    other = [candidates(t, f) for t, f in zip(texts, base, strict=True)]
    spans = [(t, *value_of(t, *f)) for t, own in zip(texts, base, strict=True) for f in own] + [(t, a, b) for t, own in zip(texts, other, strict=True) for a, b in own]
    sure = iter(net.probability(net.scores(spans)).tolist())
    out = [[(*f, next(sure)) for f in own] for own in base]
    for found, own in zip(out, other, strict=True):
        found += [(a, 3, b, p) for a, b in own if (p := next(sure)) >= net.threshold]
        found.sort()
    return [(found, len(b) + len(o)) for found, b, o in zip(out, base, other, strict=True)]


def findings(text: str, net: Net) -> list[Finding]:
    return scored([text], net)[0][0]


def redacted(text: str, found: list[Finding]) -> str:
    """Findings replaced by a mark of their kind; overlapping ones by one."""
    out, at, k = [], 0, 0
    while k < len(found):
        a, kind, b, _ = found[k]
        while k + 1 < len(found) and found[k + 1][0] < b:
            k += 1
            b = max(b, found[k][2])
        out += [text[at:a], f"<{KINDS[kind]}>"]
        at, k = b, k + 1
    return "".join([*out, text[at:]])


def scanned(docs: DataFrame, net: Net | None = None) -> DataFrame:
    """``doc_id, spans array<struct<kind, start, end, probability>>, n_candidates`` of every document."""
    sent = docs.sparkSession.sparkContext.broadcast(net or fit(docs))  # about 20 kB
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("probability", pa.float64())]))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches):
            many = part.column(1).to_pylist()
            different = list(dict.fromkeys(many))
            known = {t: ([{"kind": KINDS[k], "start": a, "end": b, "probability": p} for a, k, b, p in found], n) for t, (found, n) in zip(different, scored(different, sent.value), strict=True)}
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array([known[t][0] for t in many], kind), pa.array([known[t][1] for t in many], pa.int64())], ["doc_id", "spans", "n_candidates"])

    return common.texts(docs).mapInArrow(run, "doc_id long, spans array<struct<kind: string, start: long, end: long, probability: double>>, n_candidates long")


def digests(found: DataFrame) -> DataFrame:
    """Counts and digests of ``scanned`` rows, in SQL."""
    said = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    base = F.filter("spans", lambda s: s["kind"] != "learnt")
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    sure = F.transform("spans", lambda s: F.round(s["probability"], 4)).alias("probabilities")
    return found.select("doc_id", *[count(k) for k in KINDS[:3]], F.sha2(said(base), 256).alias("base_sha256"), said(F.col("spans")).alias("spans"), count("learnt"), "n_candidates", sure)


def without_secrets(docs: DataFrame, net: Net | None = None) -> DataFrame:
    """Every document with its columns; findings in ``text`` are replaced, ``n_chars`` follows if there is one."""
    sent = docs.sparkSession.sparkContext.broadcast(net or fit(docs))
    schema, at = docs.schema, docs.columns.index("text")
    long_at = docs.columns.index("n_chars") if "n_chars" in docs.columns else None

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches):
            many = part.column(at).to_pylist()
            texts = [redacted(t, f) if f else t for t, (f, _) in zip(many, scored([t or "" for t in many], sent.value), strict=True)]
            columns = list(part.columns)
            columns[at] = pa.array(texts, part.schema.field(at).type)
            if long_at is not None:
                columns[long_at] = pa.array([n if t is None else len(t) for t, n in zip(texts, columns[long_at].to_pylist(), strict=True)], part.schema.field(long_at).type)
            yield pa.RecordBatch.from_arrays(columns, schema=part.schema)

    return docs.mapInArrow(run, schema)
