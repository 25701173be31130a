"""Each operator against brute force, on the small tables and on awkward rows."""

import base64
import hashlib
import html
import re
import unicodedata
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from gossamer.llm import adaptive_scan, chat_template, common, golay_simhash, lang_mixture, matrix_bpe, matroska, queries, secret_cnn, sos_packing, sstable, text_density

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, start long, fp long, spans string, media string"
ODD = ["", None, " ", "  a   b \n\n c  ", "x\x1cy z", " 's it's\t\n  q", "Σας ΟΔΟΣ é́ é", "<|endoftext|> </turn> ###", "日本語 テキスト", "a" * 4000, "word " * 30_000, "12 34", "\U0001f600" * 90, "password: secret=abcdefgh1 token=secret: abcdefghij", "AKIA" + "A" * 12 + " AKIA" + "A" * 11, "0123456789abcdef" * 2 + "g", "paſſword=abcdefgh1"]


def rows_of(texts, first=0):
    return [(first + i, t, ("en", None, "de")[i % 3], "s", 1, 5, 6, "x", "m") for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def odd(spark):
    rows = rows_of(ODD)
    return spark.createDataFrame([*rows, rows[3], rows[3], (None, "null id here", "en", None, None, None, None, None, None)], SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def documents(spark, small):
    return common.table(spark, small, "documents").collect()


def pandas(df, *by):
    return df.toPandas().sort_values(list(by)).reset_index(drop=True)


def crc(ids):
    return zlib.crc32(np.asarray(ids, "<u4").tobytes())


def library(name):
    t = Tokenizer.from_file(P.path(name))
    t.encode_special_tokens = True
    return t


# --- 1: shards -----------------------------------------------------------------------------------------


def test_shards_hold_every_document_in_order(spark, small, documents):
    t = library("word_bpe_49k.json")
    got = pandas(queries.op1_sstable_shards(spark, small), "doc_id")
    start = 0
    for r, d in zip(got.itertuples(), sorted(documents, key=lambda d: d.doc_id), strict=True):
        ids = [*t.encode(d.text or "", add_special_tokens=False).ids, 1]
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (d.doc_id, start, len(ids), crc(ids))
        start += len(ids)


def test_shards_of_odd_rows_and_lookup(spark, odd, none):
    t = library("word_bpe_49k.json")
    manifest = sstable.write_shards(odd, P.path("word_bpe_49k.json"), sstable.shard_folder(spark), splits="space")
    read = sstable.read_shards(manifest, 3).collect()
    assert len(read) == odd.count()
    truth = {d.doc_id: [*t.encode(d.text or "", add_special_tokens=False).ids, 1] for d in odd.collect()}
    assert all(np.frombuffer(r.ids, "<u4").tolist() == truth[r.doc_id] for r in read)
    ends = sorted((r.start, r.n_tokens) for r in read)
    assert all(a + n == b for (a, n), (b, _) in zip(ends, ends[1:], strict=False)) and ends[0][0] == 0
    wanted = spark.createDataFrame([(3,), (9,), (999,), (None,), (-5,)], "doc_id long")
    found = sorted((r.doc_id, np.frombuffer(r.ids, "<u4").tolist()) for r in sstable.lookup(manifest, wanted).collect())
    assert found == [(3, truth[3])] * 3 + [(9, truth[9])]
    empty = sstable.write_shards(none, P.path("word_bpe_49k.json"), sstable.shard_folder(spark))
    assert empty.count() == 0 and sstable.read_shards(empty, 2).count() == 0


def test_shards_roll_at_their_size_and_guard_wide_ids(spark, odd, tmp_path):
    path = P.path("word_bpe_49k.json")
    one, many = (sstable.write_shards(odd, path, sstable.shard_folder(spark), most=m) for m in (sstable.SHARD_BYTES, 1))
    assert many.count() > one.count() and many.agg({"n_docs": "sum"}).first()[0] == odd.count()
    order = [(r.start, r.doc_id, bytes(r.ids)) for r in sstable.read_shards(many, 3).collect()]
    assert sorted(order) == sorted((r.start, r.doc_id, bytes(r.ids)) for r in sstable.read_shards(one, 3).collect())
    wanted = spark.createDataFrame([(3,), (9,)], "doc_id long")
    assert sorted(r.doc_id for r in sstable.lookup(many, wanted).collect()) == [3, 3, 3, 9]
    with (tmp_path / "w").open("wb") as f, pytest.raises(ValueError):
        sstable.ShardWriter(f, 2).add(sstable.key_of(1), np.asarray([70_000], "<u4").tobytes())


def test_shard_file_search(tmp_path):
    keys = sorted(np.random.default_rng(1).choice(10**12, 3000, replace=False).tolist()) + [2**62]
    with (tmp_path / "a").open("wb") as f:
        w = sstable.ShardWriter(f, 4)
        for k in keys:
            w.add(sstable.key_of(k), np.arange(k % 97, dtype="<u4").tobytes())
        w.close()
    reader = sstable.ShardReader((tmp_path / "a").open("rb"))
    assert len(reader.index) > 3 and [sstable.id_of(k) for k, _, _ in reader.scan()] == keys
    for k in keys[::37]:
        assert len(reader.get(sstable.key_of(k))[0]) == 4 * (k % 97)
    misses = sum(reader.may_hold(sstable.key_of(k + 1)) for k in keys if k + 1 not in keys)
    assert misses < 0.05 * len(keys) and not reader.get(sstable.key_of(keys[5] + 1))
    assert sstable.key_of(-3) < sstable.key_of(-2) < sstable.key_of(7) and sstable.key_of(None) < sstable.key_of(-(2**63))


# --- 2: main text -----------------------------------------------------------------------------------------


def article_of(page):
    inside = page[page.index("<article>") + 9 : page.index("</article>")]
    blocks = re.sub(r"<[^>]+>", "", re.sub(r"<(?:/?p|/?h1|br)>", "\n", inside)).split("\n")
    return " ".join(b for b in (re.sub(r"\s+", " ", html.unescape(x)).strip() for x in blocks) if b)


def test_main_text_of_every_page(spark, medium):
    pages = {r.page_id: r for r in common.table(spark, medium, "pages").collect()}
    for r in queries.op2_text_density(spark, medium).collect():
        assert r.text == article_of(pages[r.page_id].html) and r.n_chars == len(r.text) and r.url == pages[r.page_id].url


PAGE = """<html><head><title>t</title><style>p{}</style></head><body class="no-sidebar"><header><h1>Site</h1><nav>home</nav></header><div id="cookie-notice">We use cookies, accept them all now please.</div>
<div class="wrap"><div class="sidebar"><ul><li><a href=x>aaa bbb</a><li><a>ccc</a></ul></div><div class="content"><h2>Title  here</h2><p>Long text one with many words, and more
words here to be dense<p>Second with an <a href="q>r">inline</a> link &amp; more&hellip;</p><table><tr><td>cell a<td>cell b</table></div>
<div class="comments"><p>I am a reader comment that is quite long and dense so that it might be taken.</p></div></div><form>Mail<input></form><script>var a = "</p>";</script><footer>foot</footer></body></html>"""


def test_main_text_without_chrome():
    assert text_density.extract(PAGE) == "Title here Long text one with many words, and more words here to be dense Second with an inline link & more… cell a cell b"


@pytest.mark.parametrize("page, text", [(None, ""), ("", ""), ("<p>only", "only"), ("plain & text", "plain & text"), ("<script>x", ""), ("<div>" * 20_000 + "deep", "deep"), ("<p>a</b></i>b</p>", "ab"), ("<", "<"), ("<!-- x", "")])
def test_main_text_of_broken_pages(page, text):
    assert text_density.extract(page) == text


PROSE = ["".join(f"<p>{' '.join(f'{half}{k}{j} are some words' for j in range(12))}.</p>" for k in range(3)) for half in "ab"]
LINKS = "<div>" + "".join(f"<a href=/{k}>linked page {k}</a> " for k in range(8)) + "</div>"


@pytest.mark.parametrize("left, right", [("<div>", "</div>"), ("<section>", "</section>"), ("<article>", "</article>"), ("<div><div>", "</div></div>"), ("", "")])
def test_main_text_without_one_wrapper(left, right):
    whole = " ".join(re.sub("<[^>]+>", " ", "".join(PROSE)).split())
    assert text_density.extract(f"<html><body>{LINKS}{left}{PROSE[0]}{right}{left}{PROSE[1]}{right}</body></html>") == whole


def test_density_decides_without_names_of_articles(spark, small):
    pages = [r.html for r in common.table(spark, small, "pages").collect()]
    named = re.compile(r"(</?)(?:article|main)\b")
    assert all(text_density.extract(named.sub(r"\1div", p)) == article_of(p) for p in pages)


def test_main_text_right_below_the_body():
    assert text_density.extract("<body><h1>T</h1><p>A</p><p>B with a <b>bold phrase</b></p></body>") == "T A B with a bold phrase"
    assert text_density.extract(f"<body>{LINKS}<div>{PROSE[0]}</div><div>Copyright</div></body>") == text_density.extract(PROSE[0])


def test_main_text_table_cases(spark):
    rows = [(1, "u", PAGE, 1), (2, None, None, 2), (None, "v", "<p>x", 3), (1, "u", PAGE, 1)]
    got = text_density.main_text(spark.createDataFrame(rows, "page_id long, url string, html string, n_chars int")).collect()
    assert len(got) == 4 and [g.n_chars for g in got if g.page_id == 2] == [0]
    assert text_density.main_text(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


# --- 3: secrets --------------------------------------------------------------------------------------------


def base_of(text):
    found = [(m.start(), 0, m.end()) for m in re.finditer(r"""(?ai)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text) if len(m[2]) >= 8]
    found += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 16]
    found += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 32]
    return sorted(found)


@pytest.fixture(scope="module")
def net():
    texts = [f"the report {k} of the market was here " * 5 + f'token = "{hashlib.sha1(bytes([k])).hexdigest()}" and {k}x{k * 7919 % 10**12:012d} more words' for k in range(60)]
    return secret_cnn.trained([x for t in texts for x in secret_cnn.shown(t, 7)])


def test_base_findings_of_documents(spark, medium):
    docs = {r.doc_id: r.text or "" for r in common.table(spark, medium, "documents").collect()}
    rows = queries.op3_secret_cnn(spark, medium).collect()
    assert len(rows) == len(docs)
    for r in rows:
        base = base_of(docs[r.doc_id])
        said = ",".join(f"{secret_cnn.KINDS[k]}:{a}:{b}" for a, k, b in base)
        assert r.base_sha256 == hashlib.sha256(said.encode()).hexdigest()
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(k == n for _, k, _ in base) for n in range(3))
        assert set(filter(None, said.split(","))) <= set(r.spans.split(","))


def test_network_finds_built_secrets_and_spares_words(net):
    sample = [x for k in range(40) for x in secret_cnn.shown(f"some other context {k} with plain words in it for the test", 3)]
    cases = secret_cnn.built(sample, np.random.default_rng(5), 800) + [x for x in sample if x[0] == "word"]
    sure = net.probability(net.scores([x[2:] for x in cases])) >= net.threshold
    y = np.asarray([x[0] == "secret" for x in cases])
    assert sure[y].mean() >= 0.9 and sure[~y].mean() <= 0.03
    assert net.held_out["recall"] >= secret_cnn.RECALL and net.held_out["precision"] >= 0.9 and net.held_out["others"] > 100
    text = "see ghp_" + "a1B2c3D4e5F6g7H8i9J0k1L2m3N4o5P6q7R8" + " there"
    assert [text[a:b] for a, k, b, _ in secret_cnn.findings(text, net) if k == 3] == ["ghp_a1B2c3D4e5F6g7H8i9J0k1L2m3N4o5P6q7R8"]
    assert secret_cnn.findings("a plain report about the market and nothing else", net) == []


def test_network_reads_every_candidate_of_the_documents(spark, medium):
    docs = {r.doc_id: r.text or "" for r in common.table(spark, medium, "documents").collect()}
    rows = queries.op3_secret_cnn(spark, medium).collect()
    for r in rows:
        base = secret_cnn.base_findings(docs[r.doc_id])
        assert r.n_candidates == len(base) + len(secret_cnn.candidates(docs[r.doc_id], base))
        assert len(r.probabilities) == r.n_assign + r.n_access + r.n_hex + r.n_learnt
    found = [p for r in rows for p in r.probabilities]
    assert sum(r.n_candidates for r in rows) > 2 * len(found) > 0 and np.mean(np.asarray(found) > 0.5) > 0.9
    assert sum(r.n_learnt for r in rows) <= 0.02 * sum(r.n_candidates for r in rows)  # all secrets of these tables are base findings


def test_network_equals_plain_loops(net):
    spans = [("see abc-1234-def-5678 there", 4, 21), ("x" * 30 + "7" * 130 + " y", 0, 160), ("12ab34cd56ef", 0, 12)]
    for (text, a, b), got in zip(spans, net.scores(spans), strict=True):
        best, seen = -np.inf, set()
        for codes, mark in secret_cnn.windows(text, a, b):
            half, pooled = net.WIDTH // 2, [np.zeros(len(net.bias)), np.zeros(len(net.bias))]
            for t in range(len(codes) - net.WIDTH + 1):
                patch = np.concatenate([np.append(net.embed[codes[t + i]], float(mark[t + i])) for i in range(net.WIDTH)])
                own = pooled[0 if mark[t + half] else 1]
                np.maximum(own, np.maximum(patch @ net.filters + net.bias, 0), out=own)
            best = max(best, np.concatenate(pooled) @ net.dense + net.out)
        assert abs(best - got) < 1e-4
    for size in (5, 48, 49, 100, 1000):
        text = "".join(chr(48 + k % 10) for k in range(size))
        for x in [0, size // 2, size - 1]:  # each place is inside some window
            hidden = "#" * x + text[x] + "#" * (size - x - 1)
            one = secret_cnn._codes(text[x])[0]
            assert any((codes[mark] == one).any() for codes, mark in secret_cnn.windows(hidden, 0, size))


def test_candidates_keep_clear_of_findings():
    for text in ("auth: abcdef12345 token=abcdefgh1 zz9zz9zz9zz9 AKIA" + "A1" * 8 + " 123456789012", "ftp://u:pass1word@h token: secret=aaaa1111bbbb cccc2222dddd", "0123456789abcdef" * 3 + "xyz" + "9" * 20):
        base = secret_cnn.base_findings(text)
        got = secret_cnn.candidates(text, base)
        assert got == sorted(got) and all(b <= c for (_, b), (c, _) in zip(got, got[1:], strict=False))
        assert not any(x < b and a < y for a, b in got for x, _, y in base)
    assert [t[a:b] for t in ["card 9807915762804490 here", "mail 12345678901 x"] for a, b in secret_cnn.candidates(t, [])] == ["9807915762804490"]


def test_secret_cases(spark, odd, none, net):
    got = {(r.doc_id): r for r in secret_cnn.scanned(odd, net).collect()}
    for d in odd.collect():
        assert [(s.start, secret_cnn.KINDS.index(s.kind), s.end) for s in got[d.doc_id].spans if s.kind != "learnt"] == base_of(d.text or "")
    assert secret_cnn.scanned(none, net).count() == 0 and 0 < secret_cnn.fit(none).threshold <= 1
    clean = secret_cnn.without_secrets(odd, net)
    assert clean.columns == odd.columns and clean.count() == odd.count()
    assert not [1 for r in clean.collect() if r.text and base_of(r.text)]
    assert secret_cnn.redacted("abcdef", [(0, 0, 3, 1.0), (2, 2, 5, 1.0)]) == "<assign>f"
    repeated = odd.unionByName(odd).unionByName(odd.selectExpr("7L AS doc_id", "concat(text, ' more') AS text", *odd.columns[2:]))
    a, b = (secret_cnn.fit(x, 12) for x in (repeated, repeated.repartition(5)))
    assert (a.embed == b.embed).all() and a.threshold == b.threshold


# --- 4: neighbours -------------------------------------------------------------------------------------------


def brute_neighbours(vectors, asks, k=20):
    ids, x = np.asarray([v for v, _ in vectors]), np.asarray([e for _, e in vectors], np.float64)
    out = {}
    for q in asks:
        s = x @ x[np.flatnonzero(ids == q)[0]]
        order = [i for i in np.lexsort((ids, -np.round(s, 12))) if ids[i] != q][:k]
        out[q] = [(int(ids[i]), float(s[i])) for i in order]
    return out


def test_neighbours_recall_and_scores(spark, medium):
    vectors = [(r.vec_id, r.embedding) for r in common.table(spark, medium, "embeddings").collect()]
    truth = brute_neighbours(vectors, [v for v, _ in vectors if v % 20 == 0])
    rows = queries.op4_adaptive_scan(spark, medium).collect()
    by = {}
    for r in rows:
        by.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    x = dict(vectors)
    assert set(by) == set(truth)
    hits = 0
    for q, found in by.items():
        found.sort()
        assert [f[0] for f in found] == list(range(1, 21))
        assert all(abs(s - float(np.dot(np.asarray(x[q], float), np.asarray(x[v], float)))) < 1e-12 for _, v, s in found)
        assert [(-s, v) for _, v, s in found] == sorted((-s, v) for _, v, s in found)
        hits += len({v for _, v, _ in found} & {v for v, _ in truth[q]})
    assert hits >= 0.95 * 20 * len(truth)


def test_neighbours_large_index_and_norms(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(30_000, 24)) * rng.uniform(0.2, 3, (30_000, 1))
    x[5000:9000] = x[5000]
    vectors = [(i, [float(np.float32(v)) for v in row]) for i, row in enumerate(x)]
    df = spark.createDataFrame([(i, e) for i, e in vectors], "vec_id long, embedding array<float>")
    asks = [0, 500, 5000, 5500, 29_000]
    got = adaptive_scan.search(df, df.vec_id.isin(asks)).collect()
    truth = brute_neighbours(vectors, asks)
    mine = {q: [r.vec_id for r in sorted(got, key=lambda r: r["rank"]) if r.query_id == q] for q in asks}
    assert mine[5500][:3] == [v for v, _ in truth[5500]][:3]
    assert sum(len(set(mine[q]) & {v for v, _ in truth[q]}) for q in asks) >= 0.9 * 100


def test_neighbours_cases(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.0]), (20, [1.0, 0.0]), (3, [0.5, 0.5]), (4, None), (5, [0.0, 0.0]), (6, [nan, 1.0]), (7, [inf, 1.0]), (8, [None, 1.0]), (9, [1.0]), (40, [0.0, 0.0]), (None, [1.0, 1.0]), (3, [0.5, 0.5]), (10, [])]
    df = spark.createDataFrame([(*r, 1, "k") for r in rows], "vec_id long, embedding array<float>, rank int, key string")
    got = sorted(map(tuple, adaptive_scan.search(df, df.vec_id % 20 == 0).collect()))
    assert got == [(0, 1, 20, 1.0), (0, 2, 3, 0.5), (20, 1, 0, 1.0), (20, 2, 3, 0.5)]
    assert adaptive_scan.search(df.where("vec_id < -5"), df.vec_id % 20 == 0).count() == 0
    other = df.unionByName(spark.createDataFrame([(60, [2.0], 1, "k"), (80, [1.0, 2.0, 3.0], 1, "k")], df.schema))
    assert sorted(map(tuple, adaptive_scan.search(other, other.vec_id % 20 == 0).collect())) == [*got, (60, 1, 9, 2.0)]  # each length by itself
    assert adaptive_scan.search(df.where("vec_id = 0"), df.vec_id % 20 == 0).count() == 0


def test_abandoned_candidates_are_far():
    rng = np.random.default_rng(0)
    x, q = rng.normal(size=(4000, 64)).astype(np.float32), rng.normal(size=64).astype(np.float32)
    far = ((x - q) ** 2).sum(axis=1)
    limit = float(np.sort(far)[20])
    alive = adaptive_scan.scan([x[:, a : a + 16] for a in range(0, 64, 16)], q, limit)
    assert len(set(np.argsort(far)[:20]) & set(alive)) >= 19 and (far[alive] <= limit * 1.001).all()


def test_repeated_rows_do_not_hide_other_ids(spark):
    same = [1.0, 2.0, 3.0, 4.0]
    df = spark.createDataFrame([(1, same)] * 25 + [(i, same) for i in range(2, 6)] + [(9, [9.0, 0.0, 0.0, 1.0])], "vec_id long, embedding array<double>")
    assert {r.vec_id for r in adaptive_scan.search(df, df.vec_id == 9).collect()} == {1, 2, 3, 4, 5}


# --- 5: media -------------------------------------------------------------------------------------------------


def test_media_round_trip(spark, odd, none):
    texts = {d.doc_id: d.text or "" for d in odd.collect()}
    stored = {r.doc_id: bytes(r.media) for r in matroska.store(odd).collect()}
    for r in matroska.features(matroska.store(odd)).collect():
        raw = texts[r.doc_id].encode()
        payload = raw + b" " * (max(192, -(-len(raw) // 192) * 192) - len(raw))
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]))
        assert (r.media_bytes, r.media_sha256) == (len(stored[r.doc_id]), hashlib.sha256(stored[r.doc_id]).hexdigest())
    packets = matroska.packet_table(matroska.store(odd)).where("doc_id = 10").orderBy("packet").collect()
    assert b"".join(stored[10][p.offset : p.offset + p["size"]] for p in packets).decode().strip() == texts[10].strip()
    assert [p.timestamp_ns for p in packets] == [24_000_000 * i for i in range(len(packets))]
    assert matroska.features(matroska.store(none)).count() == 0


@given(st.lists(st.binary(max_size=700), min_size=1, max_size=20), st.sampled_from([1, 3]))
@settings(max_examples=60, deadline=None)
def test_lacing(frames, mode):
    packed = matroska.lace(frames, mode)
    sizes, at = matroska.lace_sizes(packed, 0, len(packed), mode)
    assert sizes == list(map(len, frames)) and packed[at:] == b"".join(frames)


def test_media_of_other_shapes():
    block = lambda n, k: matroska.element(matroska.SIMPLE_BLOCK, bytes([0x80 | n, 0, k, 0x80]) + bytes([n]) * 3)
    cluster = matroska.number(matroska.TIMESTAMP, 5) + block(1, 0) + block(2, 7)
    unknown = b"\x1f\x43\xb6\x75\xff" + cluster
    head = matroska.element(matroska.EBML, matroska.element(matroska.DOC_TYPE, b"webm"))
    movie = matroska.parse(head + b"\x18\x53\x80\x67\x01" + b"\xff" * 7 + unknown + unknown + matroska.element(matroska.CUES, b""))
    assert [(p.track, p.timestamp, p.size) for p in movie.packets] == [(1, 5, 3), (2, 12, 3)] * 2 and movie.doc_type == "webm"
    for bad in (b"", b"\x00abc", head + b"\x18\x53\x80\x67\x84ab", matroska.mux(b"x" * 192)[:-3]):
        with pytest.raises(ValueError):
            matroska.parse(bad)


# --- 6: packing ------------------------------------------------------------------------------------------------


def check_packing(rows, texts, end_id=0, capacity=2048):
    t, by, used = library("byte_bpe_50k.json"), {}, {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
        used.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for doc_id, text in texts.items():
        ids, own = [*t.encode(text, add_special_tokens=False).ids, end_id], sorted(by[doc_id], key=lambda r: r.piece)
        assert [r.piece for r in own] == list(range(len(own))) and all(r.length == capacity for r in own[1:])
        assert [r.start for r in own] == [sum(x.length for x in own[:i]) for i in range(len(own))] and sum(r.length for r in own) == len(ids)
        assert all(r.ids_crc32 == crc(ids[r.start : r.start + r.length]) for r in own)
    for places in used.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= capacity
    return len(used), -(-sum(r.length for r in rows) // capacity)


def test_packing_of_documents(spark, medium):
    rows = queries.op6_sum_of_squares(spark, medium).collect()
    n, least = check_packing(rows, {d.doc_id: d.text or "" for d in common.table(spark, medium, "documents").collect()})
    assert n <= 1.01 * least + 1


def test_packing_cases(spark, odd, none):
    rows = sos_packing.packed(odd.where("doc_id is not null").dropDuplicates(["doc_id"]), P.path("byte_bpe_50k.json")).collect()
    check_packing(rows, {d.doc_id: d.text or "" for d in odd.where("doc_id is not null").collect()})
    assert sos_packing.packed(odd, P.path("byte_bpe_50k.json")).select("doc_id").distinct().count() == len(ODD) + 1
    assert sos_packing.packed(none, P.path("byte_bpe_50k.json")).count() == 0


@pytest.mark.parametrize("eager", [False, True])
def test_the_rule_is_sum_of_squares(eager):
    rng, s = np.random.default_rng(2), sos_packing.SumOfSquares(20, eager)
    gaps: list[int] = []
    for size in rng.integers(1, 21, 400).tolist():
        value = lambda g: sum(g.count(v) ** 2 for v in set(g) if v)
        fits = [i for i, g in enumerate(gaps) if g >= size]
        trials = {i: value([g - size if k == i else g for k, g in enumerate(gaps)]) for i in fits}
        opened = value([*gaps, 20 - size])
        sequence, offset = s.place(size)
        if fits and not (eager and opened < min(trials.values())):
            assert trials[sequence] == min(trials.values()) and offset == 20 - gaps[sequence]
            gaps[sequence] -= size
        else:
            assert sequence == len(gaps) and offset == 0
            gaps.append(20 - size)
    with pytest.raises(ValueError):
        s.place(21)


# --- 7: language -------------------------------------------------------------------------------------------------


def test_language_accuracy_on_held_out(spark, medium):
    docs = {r.doc_id: r for r in common.table(spark, medium, "documents").collect()}
    rows = queries.op7_lang_mixture(spark, medium).collect()
    assert len(rows) == len(docs) and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    out = [r for r in rows if r.held_out]
    assert np.mean([r.lang_pred == docs[r.doc_id].lang for r in out]) >= 0.95 and all(0 <= r.score <= 1 for r in rows)


def plain_mixture(model, text):
    """Every language tried with plain EM on every n-gram, the one that gains most added while it pays."""
    h = [int(x) for x in lang_mixture.grams(text)]
    p = [[float(model.p[x, k]) for k in range(len(model.languages))] for x in h]
    value_of = lambda chosen, share: sum(np.log(sum(row[k] * s for k, s in zip(chosen, share))) for row in p)
    chosen = [max(range(len(model.languages)), key=lambda k: (round(value_of([k], [1.0]), 9), -k))]
    share, value = [1.0], value_of(chosen, [1.0])
    pays = lang_mixture.PENALTY * np.log(max(len(h), 2))
    while True:
        tried = []
        for k in range(len(model.languages)):
            if k not in chosen:
                own, s = [*chosen, k], [1 / (len(chosen) + 1)] * (len(chosen) + 1)
                for _ in range(lang_mixture.ROUNDS):
                    mixed = [sum(row[j] * v for j, v in zip(own, s)) for row in p]
                    new = [v * sum(row[j] / m for row, m in zip(p, mixed)) / len(p) for j, v in zip(own, s)]
                    moved = max(abs(a - b) for a, b in zip(new, s))
                    s = new
                    if moved < lang_mixture.SETTLED:
                        break
                tried.append((value_of(own, s), own, s))
        best = max(tried, key=lambda x: x[0], default=None)
        if best is None or best[0] - value <= pays:
            return {model.languages[k]: v for k, v in zip(chosen, share)}, value
        value, chosen, share = best


def test_mixtures_equal_plain_em(monkeypatch):
    monkeypatch.setattr(lang_mixture, "PENALTY", 0.3)
    rng, sizes = np.random.default_rng(3), []
    for _ in range(60):
        words = ["".join(rng.choice(list("abcd"), 4)) for _ in range(12)]
        counts = np.zeros((lang_mixture.BUCKETS, 5)) + 0.01
        for k in range(5):
            counts[:, k] += np.bincount(lang_mixture.grams(" ".join(rng.choice(words, 40))), minlength=lang_mixture.BUCKETS)
        model = lang_mixture.Model(list("vwxyz"), np.log(counts / counts.sum(axis=0)).astype(np.float32))
        text = " ".join(rng.choice(words, 25))
        (got, value), (want, plain) = model.mixture(text), plain_mixture(model, text)
        assert got.keys() == want.keys() and abs(value - plain) < 1e-3 and all(abs(got[k] - want[k]) < 1e-3 for k in got)
        sizes.append(len(got))
    assert max(sizes) > 2 and min(sizes) < 3


def test_language_ties_and_too_many_labels(spark, monkeypatch):
    own = [i for i in range(60) if zlib.crc32(str(i).encode()) % 5]
    rows = [(i, "one and the same text", ("zz", "aa")[k % 2], "s", 1, None, None, None, None) for k, i in enumerate(own[:20])]
    docs = spark.createDataFrame(rows, SCHEMA)
    assert {r.lang_pred for r in lang_mixture.identified(docs).collect()} == {"aa"}  # the first in order
    monkeypatch.setattr(lang_mixture, "MOST_LANGUAGES", 1)
    with pytest.raises(ValueError):
        lang_mixture.learn(docs)


def test_language_mixture_and_cases(spark, medium, odd, none):
    docs = common.table(spark, medium, "documents")
    model = lang_mixture.learn(docs)
    text = {r.lang: r.text for r in docs.where("n_chars > 1500").dropDuplicates(["lang"]).collect()}
    shares, _ = model.mixture(text["en"][:1000] + text["fr"][:1000])
    assert set(shares) == {"en", "fr"} and abs(shares["en"] - 0.5) < 0.12
    assert len(model.mixture(text["de"])[0]) == 1
    got = {r.doc_id: r for r in lang_mixture.identified(odd).collect()}
    for d in odd.collect():
        assert (got[d.doc_id].lang_pred == "und") == (not any(c.isalpha() for c in d.text or ""))
    assert lang_mixture.identified(none).count() == 0 and lang_mixture.kept(odd).columns == odd.columns
    unlabelled = lang_mixture.identified(odd.withColumn("lang", odd.lang.substr(9, 1)).where("lang is null")).collect()
    assert {r.lang_pred for r in unlabelled} == {"und"}


# --- 8: BPE ------------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def reference_bpe():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_multi_50k.tiktoken"), "rb"))}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_of_documents(spark, small, documents, reference_bpe):
    got = {r.doc_id: r for r in queries.op8_matrix_bpe(spark, small).collect()}
    for d in documents:
        ids = reference_bpe.encode_ordinary(d.text or "")
        r = got[d.doc_id]
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(np.asarray(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((d.text or "").encode()).hexdigest())


def test_bpe_cases(spark, odd, none, reference_bpe):
    path = P.path("byte_bpe_multi_50k.tiktoken")
    for r, d in zip(sorted(matrix_bpe.encode(odd.where("doc_id >= 0"), path, P.PATTERN).collect()), sorted(odd.where("doc_id >= 0").select("doc_id", "text").collect(), key=lambda d: d.doc_id), strict=True):
        assert np.frombuffer(r.ids, "<u4").tolist() == reference_bpe.encode_ordinary(d.text or "") and bytes(r.decoded).decode() == (d.text or "")
    assert matrix_bpe.encode(none, path, P.PATTERN).count() == 0


@given(st.text(max_size=300))
@settings(max_examples=150, deadline=None)
def test_bpe_of_any_text(text):
    path = P.path("byte_bpe_multi_50k.tiktoken")
    codec = matrix_bpe.codec(path, P.PATTERN)
    (ids,) = codec.encode([text])
    global _REFERENCE
    try:
        reference = _REFERENCE
    except NameError:
        reference = _REFERENCE = tiktoken.Encoding("own2", pat_str=P.PATTERN, mergeable_ranks=codec.bpe.ranks, special_tokens={})
    assert np.frombuffer(ids, "<u4").tolist() == reference.encode_ordinary(text) and codec.bpe.decode(ids) == text.encode()


@given(st.text(max_size=120))
@settings(max_examples=120, deadline=None)
def test_cached_chunks_equal_the_library(text):
    for name, splits in (("word_bpe_49k.json", "space"), ("byte_bpe_50k.json", "word")):
        encoder = common.text_encoder(P.path(name), splits)
        (ids,) = encoder.batch([text])
        assert ids == encoder.whole(text), unicodedata.name(text[:1], "")


@given(st.lists(st.text("aeZéßÿŁƀɏ1²½ ,.-_'’“€…\n\tsdlvⅣ日", max_size=60), min_size=1, max_size=6))
@settings(max_examples=300, deadline=None)
def test_slices_of_settled_characters_equal_the_library(texts):
    for name, splits in (("word_bpe_49k.json", "space"), ("byte_bpe_50k.json", "word")):
        encoder = common.text_encoder(P.path(name), splits)
        assert list(encoder.batch(texts)) == [encoder.whole(t) for t in texts]


# --- 9: near duplicates -----------------------------------------------------------------------------------------------


def fingerprint_of(text):
    words = re.findall("[^\x20\x09-\x0d]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), seed=42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(prints):
    root = {i: i for i, _ in prints}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, (i, f) in enumerate(prints):
        for j, g in prints[:k]:
            if (f ^ g).bit_count() <= 3 and (a := find(i)) != (b := find(j)):
                root[max(a, b)] = min(a, b)
    return {i: find(i) for i, _ in prints}


def test_near_duplicates_of_documents(spark, medium):
    docs = common.table(spark, medium, "documents").collect()
    prints = [(d.doc_id, fingerprint_of(d.text or "")) for d in docs]
    truth = brute_components(prints)
    got = {r.doc_id: r for r in queries.op9_golay_simhash(spark, medium).collect()}
    assert {i: int(r.fingerprint, 16) for i, r in got.items()} == dict(prints)
    assert {i: r.component_id for i, r in got.items()} == truth


def test_near_duplicate_cases(spark, odd, none):
    got = {r.doc_id: r.component_id for r in golay_simhash.near_duplicates(odd).collect()}
    named = [(d.doc_id, fingerprint_of(d.text or "")) for d in odd.where("doc_id is not null").dropDuplicates(["doc_id"]).collect()]
    assert {k: v for k, v in got.items() if k is not None} == brute_components(sorted(named)) and golay_simhash.near_duplicates(odd).count() == odd.count()
    assert golay_simhash.near_duplicates(none).count() == 0


def test_golay_keys_meet_within_three_bits(spark):
    rng = np.random.default_rng(7)
    fps = rng.integers(0, 2**63, 4000).astype(np.uint64) * np.uint64(2)
    other = fps.copy()
    for _ in range(3):
        other ^= np.uint64(1) << rng.integers(0, 64, len(fps)).astype(np.uint64)
    keys = [{}, {}]
    for side, f in zip(keys, (fps, other), strict=True):
        for i, k in zip(*map(np.ndarray.tolist, golay_simhash.keys_of(f)), strict=True):
            side.setdefault(i, set()).add(k)
    assert all(keys[0][i] & keys[1][i] for i in range(len(fps)))


def test_crowded_keys_and_long_chains(spark, monkeypatch):
    monkeypatch.setattr(golay_simhash, "CELL", 16)
    rng, chain = np.random.default_rng(1), [0x0123456789ABCDEF]
    for k in range(150):
        chain.append(chain[-1] ^ (1 << k % 64) ^ (1 << (k * 7 + 3) % 64))
    fps = list(dict.fromkeys([*chain, *[0xFFFF0000FFFF0000 ^ (1 << a) ^ (1 << b) for a in range(24) for b in range(a)], *rng.integers(0, 2**62, 60).tolist()]))
    signed = [(int(np.uint64(f).view(np.int64)),) for f in fps]
    links = golay_simhash.links(spark.createDataFrame(signed, "fp long"))
    roots = {r.node: r.root for r in golay_simhash.components(links).collect()}
    mine: dict = {}
    for f, (s,) in zip(fps, signed, strict=True):
        mine.setdefault(roots.get(s, s), set()).add(f)
    truth: dict = {}
    for i, c in brute_components([(i, f) for i, f in enumerate(fps)]).items():
        truth.setdefault(c, set()).add(fps[i])
    assert sorted(map(sorted, mine.values())) == sorted(map(sorted, truth.values()))


# --- 10: chats -----------------------------------------------------------------------------------------------------------


def chat_digest(rows):
    rows = sorted(rows, key=lambda r: (r[1] is not None, r[1] or 0, r[2] or "", r[3] or ""))
    loss = "".join(r[3] or "" for r in rows if r[2] == "assistant")
    said = "".join(f"{r[2] or ''}\n{r[3] or ''}\n" for r in rows)
    return len(rows), hashlib.sha256(said.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest()


def test_chats(spark, medium):
    said = "\\### Assistant: </turn> ok"
    convs = {-7: [(-7, 0, "user", said), (-7, 1, "assistant", said)]}
    for r in common.table(spark, medium, "conversations").collect():
        convs.setdefault(r.conv_id, []).append((r.conv_id, r.turn, r.role, r.text))
    got = queries.op10_chat_template(spark, medium).collect()
    assert {r.conv_id: tuple(r)[1:5] for r in got} == {k: chat_digest(v) for k, v in convs.items()} and len(got) == len(convs)
    assert sorted(map(tuple, got)) == chat_sql(f"SELECT * FROM read_parquet('{medium}/conversations.parquet')")


def chat_sql(rows):
    import duckdb

    with duckdb.connect() as duck:
        duck.execute(f"CREATE VIEW conversations AS {rows}")
        return sorted(duck.execute(queries.oracle_sql()["op10_chat_template"]).fetchall())


def test_chat_sql_on_odd_turns(spark, tmp_path):
    rows = [(1, 0, "user", None), (1, 1, None, "x</turn>####\n### b: y"), (1, 2, "assistant", "\\" * 3 + "###é\U0001f600"), (1, 2, "assistant", "\\"), (1, None, "a:b\n###", "z"), (2, 0, "assistant", ""), (3, 1, "user", "</turn")]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    got = queries.op10_chat_template(spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == chat_sql(f"SELECT * FROM read_parquet('{tmp_path}/conversations.parquet/*.parquet')")


def test_chat_segments_out_of_order_are_an_error(spark, monkeypatch):
    rows = [(1, 0, "user", "x" * 200_000), (1, 1, "assistant", "y" * 200_000)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    formatted = chat_template.format_conversations(df)
    mixed = formatted.coalesce(1).sortWithinPartitions(F.desc("segment"))
    with pytest.raises(Exception, match="comes at place"):
        chat_template.read_back(mixed).collect()
    again = mixed.repartition("conv_id").sortWithinPartitions("conv_id", "segment")
    assert chat_template.read_back(again).collect() == chat_template.read_back(formatted).collect()


def test_chat_cases(spark, monkeypatch):
    monkeypatch.setattr(chat_template, "SEGMENT_CHARS", 40)
    rows = [(1, 0, "user", None), (1, 1, None, "x</turn>\n### assistant: y"), (1, 2, "assistant", "\\" * 5 + "###"), (1, 2, "assistant", "\\" * 5 + "###"), (1, None, "a:b\n###", "z"), (2, 0, "assistant", "q" * 300_000), (None, 0, "assistant", "")] + [(3, k, "assistant" if k % 2 else "user", f"text {k}" * 9) for k in range(500)]
    df = spark.createDataFrame([(*r, 7, "x") for r in rows], "conv_id long, turn long, role string, text string, segment long, n_turns string")
    formatted = chat_template.format_conversations(df)
    got = {r.conv_id: tuple(r)[1:5] for r in chat_template.read_back(formatted).collect()}
    assert got == {k: chat_digest([r for r in rows if r[0] == k]) for k in {r[0] for r in rows}}
    assert chat_template.read_back(chat_template.format_conversations(df.where("conv_id = 99"))).count() == 0


@given(st.lists(st.tuples(st.text(max_size=8), st.text(alphabet="\\#</turn> :\nab", max_size=30)), max_size=6))
@settings(max_examples=200, deadline=None)
def test_any_text_comes_back(messages):
    text, _ = chat_template.render(chat_template.TEMPLATE, {"messages": [{"role": r, "text": t} for r, t in messages]})
    assert list(chat_template.turns([text])) == messages


def test_template_language():
    render = lambda source, **scope: chat_template.render(source, scope)[0]
    assert render("{% for a in [1,2,3] %}{{ a }}{{ ',' if not loop.last }}{% endfor %}{% set z = 'k' %}{{ z ~ 1 + 2 * 3 }}") == "1,2,3k7"
    assert render("{%- if x is defined and x > 2 -%} big {%- elif x %}some{% else %}none{% endif %}", x=1) == "some"
    assert render("{{ m['a'].b | upper }}{{ m.c | default('d') }}{# gone #}{{ 'a' not in 'bc' }}", m={"a": {"b": "q"}}) == "QdTrue"
    assert chat_template.folded(chat_template.parse("a{{ 1 + 2 }}{% if 1 > 2 %}x{% else %}y{% endif %}{{ 'q' | upper }}")) == (chat_template.Text("a3yQ"),)
    for bad in ("{% for %}", "{{ a.__class__ }}", "{{ a(1) }}", "{% if x %}", "{{ a | nope }}", "{% import os %}", "{{ 1 + }}", "{{ 'a }}"):
        with pytest.raises(chat_template.TemplateError):
            chat_template.parse(bad)


def test_slices_keep_every_row(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(common, "SLICE_BYTES", 100)
    batch = pa.RecordBatch.from_pydict({"doc_id": list(range(50)), "text": [None if i % 7 == 0 else "x" * (i * 5) for i in range(50)]})
    parts = list(common.slices([batch, batch.slice(0, 0)], most=100))
    assert len(parts) > 20 and [i for p in parts for i in p.column(0).to_pylist()] == list(range(50))
