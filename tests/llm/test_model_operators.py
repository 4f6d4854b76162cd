"""Quality, language model, near-duplicates, media, pages, archive records."""

import base64
import hashlib
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from sparseloom.llm import flac, html_extract, lm_scoring, quality, simhash, warc
from sparseloom.llm.common import table
from sparseloom.llm.components import components
from sparseloom.llm.queries import ORACLES, QUERIES

SF01 = "/root/testdata/sf0.01"

# ------------------------------------------------------------------ quality


def test_quality_is_learned_and_held_out(spark):
    rows = QUERIES["op7_quality_classifier"](spark, SF01).join(table(spark, SF01, "labels"), "doc_id").collect()
    for r in rows:
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) and 0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.3)
    held = [r for r in rows if r["held_out"]]
    assert np.mean([r["predicted"] == r["quality"] for r in held]) > 0.9


def test_quality_learns_from_a_bounded_sample(spark):
    docs, labels = table(spark, SF01, "documents"), table(spark, SF01, "labels")
    few = quality.train(docs.union(docs), labels, max_labelled=120)
    again = quality.train(docs, labels, max_labelled=120)
    assert np.allclose(few.weights, again.weights) and few.weights.any()
    rows = quality.score(docs, few).join(labels, "doc_id").collect()
    assert np.mean([(r["score"] >= 0.3) == (r["quality"] == 1) for r in rows]) > 0.85


def test_quality_on_odd_rows(spark, odd_docs, no_docs):
    labels = spark.createDataFrame([(1, 1, 0), (4, 0, 0), (5, 1, None), (9, 0, 0), (None, 1, 0), (3, None, 0), (99, 1, 0), (8, 1, 0), (8, 0, 0)], "doc_id long, quality int, toxic int")
    rows = quality.classify(odd_docs, labels).collect()
    assert len(rows) == 13 and all(0 <= r["score"] <= 1 for r in rows)
    assert quality.classify(no_docs, labels).count() == 0
    assert {r["score"] for r in quality.classify(odd_docs, labels.limit(0)).collect()} == {0.5}
    assert len(quality.features("")) == len(quality.features("a b\nc"))


# ------------------------------------------------------------------ language model


def test_base_scores_and_gain(spark):
    docs = {r["doc_id"]: r["text"] or "" for r in table(spark, SF01, "documents").collect()}
    cut = lambda t: [*re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), t.encode())), None]
    counts: Counter = Counter()
    for i, t in docs.items():
        if zlib.crc32(str(i).encode()) % 7 != 2:
            counts.update(cut(t))
    n, v = sum(counts.values()), len(counts)
    # few hot tokens, so that the join of rare ones is put to use
    got = lm_scoring.score_documents(table(spark, SF01, "documents"), hot=2000, own_classes=200).collect()
    assert len(got) == len(docs)
    for r in got:
        words = cut(docs[r["doc_id"]])
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(words), sum(counts[w] > 0 for w in words), n)
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 7 == 2)
        assert abs(r["base_score"] - sum(np.log10((counts[w] + 1) / (n + v + 1)) for w in words)) < 1e-6 * len(words)
    held = [r for r in got if r["held_out"]]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)


def slow_log10(learner, far, near, target):
    """One token's log10-probability by a plain softmax over all outputs."""
    f, c, out, bias = (p.astype(float) for p in learner.params)
    weights = (f[far] + c[near]) @ out.T + bias[:, 0]
    top = weights.max()
    return (weights[target] - top - np.log(np.exp(weights - top).sum())) / np.log(10)


def test_model_is_normalised():
    rng = np.random.default_rng(0)
    c = rng.integers(0, 6, (3000, 3))
    c[:, 2] = (c[:, 1] + rng.integers(0, 2, 3000)) % 6
    learner = lm_scoring.Learner(np.bincount(c[:, 2], minlength=6), 6, 8)
    for _ in range(20):
        learner.learn(*c.T, rng)
    m = learner.normalised(block=4)
    for f, g in ((0, 0), (6, 6), (3, 5)):
        p = m.log10(np.full(6, f), np.full(6, g), np.arange(6))
        assert abs((10.0**p).sum() - 1) < 1e-4 and np.allclose(p, [slow_log10(learner, f, g, t) for t in range(6)], atol=1e-4)
    follows = m.log10(np.full(6, 2), np.full(6, 3), np.arange(6))
    assert set(follows.argsort()[-2:]) == {3, 4}


def test_scores_equal_brute_force(spark):
    """Every step of the score once more in plain Python: folds, counts, spelling classes, softmax over all outputs."""
    docs = table(spark, SF01, "documents").limit(60)
    rows = lm_scoring.texts(docs)
    counted = lm_scoring.count_training_tokens(rows)
    vocab = lm_scoring.vocabulary(counted, 120, 30)
    learner = lm_scoring.Learner(vocab.output_tokens(), vocab.n_contexts, 6)
    model = learner.normalised()
    n = {r["token"]: r["n"] for r in counted.collect()}
    rare = {w: k for w, k in n.items() if w not in vocab.hot}
    assert len(vocab.hot) <= 120 and min(n[w] for w in vocab.hot) > max(rare.values())
    by_class: dict = {}
    for w, k in rare.items():
        total, distinct = by_class.get(lm_scoring.shared_class(w), (0, 0))
        by_class[lm_scoring.shared_class(w)] = total + k, distinct + 1
    got = {r["doc_id"]: r["score"] for r in lm_scoring.score(rows, counted, vocab, model).collect()}
    for r in docs.collect():
        words = [*re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), r["text"].encode())), b" "]
        far = near = vocab.n_contexts
        want = 0.0
        for w in words[:400]:
            kind = lm_scoring.shared_class(w)
            output = vocab.hot.get(w, len(vocab.hot) + kind)
            want += slow_log10(learner, far, near, output)
            if w not in vocab.hot:
                total, distinct = by_class.get(kind, (0, 0))
                want += np.log10((n.get(w, 0) + 1) / (total + distinct + 1))
            far, near = near, output if output < vocab.own else vocab.own + kind
        if len(words) <= 400:
            assert abs(got[r["doc_id"]] - want) < 1e-4 * len(words)


def test_every_training_token_is_learnt_from(spark):
    docs = lm_scoring.texts(table(spark, SF01, "documents"))
    vocab = lm_scoring.vocabulary(lm_scoring.count_training_tokens(docs), 2000, 200)
    coded = lm_scoring.encode_training(docs, vocab).collect()
    held = Counter(x for r in coded for x in np.frombuffer(r["outputs"], np.int32).tolist())
    assert sum(r["n"] for r in coded) == vocab.total
    assert [held[k] for k in range(len(vocab.contexts))] == vocab.output_tokens().tolist()
    one, many = (lm_scoring.train(x, vocab, shard_tokens=100_000) for x in (docs.repartition(3), docs.repartition(7)))
    assert all((getattr(one, k) == getattr(many, k)).all() for k in ("far", "near", "out", "bias", "norm"))
    text = np.concatenate([np.frombuffer(r["outputs"], np.int32) for r in coded])
    starts = np.cumsum([0, *(r["n"] for r in coded)])[:-1]
    noise = np.log10((vocab.output_tokens() + 1) / (vocab.output_tokens() + 1).sum())
    assert one.log10(*lm_scoring.contexts_of(text, starts, vocab.contexts, vocab.n_contexts), text).mean() > noise[text].mean() + 0.1
    assert lm_scoring.grown_classes(10**10) > lm_scoring.grown_classes(10**8) > lm_scoring.grown_classes(10**6) == 700


def test_lm_on_odd_rows(odd_docs, no_docs):
    rows = lm_scoring.score_documents(odd_docs).collect()
    assert len(rows) == 13 and all(np.isfinite(r["score"]) and np.isfinite(r["base_score"]) for r in rows)
    assert {r["n_tokens"] for r in rows if r["doc_id"] in (2, 3, 7, 10)} == {1}
    assert lm_scoring.score_documents(no_docs).count() == 0


# ------------------------------------------------------------------ near-duplicates


def slow_fingerprint(text, k=4):
    words = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    if not words:
        return 0
    shingles = [b" ".join(words[i : i + k]) for i in range(max(1, len(words) - k + 1))]
    counts = [0] * 64
    for s in shingles:
        h = xxhash.xxh64_intdigest(s, seed=42)
        for b in range(64):
            counts[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * counts[b] > len(shingles))


def brute_groups(fps, ids, radius=4):
    root = list(range(len(fps)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= radius:
                root[max(find(i), find(j))] = min(find(i), find(j))
    least: dict = {}
    for i, d in enumerate(ids):
        least[find(i)] = min(least.get(find(i), d), d)
    return [least[find(i)] for i in range(len(fps))]


def test_simhash_query(spark, sf):
    docs = sorted((r["doc_id"], r["text"]) for r in table(spark, sf, "documents").collect())
    fps = [slow_fingerprint(t) for _, t in docs]
    want = {d: (f"{f:016x}", g) for (d, _), f, g in zip(docs, fps, brute_groups(fps, [d for d, _ in docs]))}
    assert {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in QUERIES["op8_simhash_near_dedup"](spark, sf).collect()} == want


@pytest.mark.parametrize("cell_rows", [4096, 16])
def test_links_keep_reachability_in_crowded_cells(spark, cell_rows):
    rng = np.random.default_rng(3)
    fps = {int(rng.integers(0, 2**63))}
    seeds = [int(x) for x in rng.integers(0, 2**63, 4)]
    for s in seeds:
        for _ in range(60):  # chains and clouds around few centres: crowded cells
            s ^= sum(1 << int(b) for b in rng.choice(63, rng.integers(1, 4), replace=False))
            fps.add(s)
    fps = sorted(fps)
    links = simhash.link_fingerprints(spark.createDataFrame([(x,) for x in fps], "fp long"), cell_rows=cell_rows)
    root = {r["vertex"]: r["root"] for r in components(links).collect()}
    assert [root.get(x, x) for x in fps] == brute_groups(fps, fps)


@pytest.mark.parametrize("radius, linked", [(1, False), (2, True), (5, True)])
def test_radius_holds_for_lone_pairs(spark, radius, linked):
    fps = spark.createDataFrame([(12345,), (12345 ^ 3,)], "fp long")
    assert simhash.link_fingerprints(fps, radius=radius, blocks=radius + 2, n_pivots=3).count() == linked


def test_components(spark):
    pairs = [(i, i + 1) for i in range(40)] + [(100, i) for i in range(101, 160)] + [(7, 7), (None, 3), (5, None), (200, 201), (201, 200)]
    got = {r["vertex"]: r["root"] for r in components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, **{i: 100 for i in range(100, 160)}, 200: 200, 201: 200}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_simhash_on_odd_rows(odd_docs, no_docs):
    rows = simhash.near_duplicates(odd_docs).collect()
    assert len(rows) == 13
    by = {r["doc_id"]: r["component_id"] for r in rows if r["doc_id"] is not None}
    assert by[1] == by[5] == by[11] == 1 and by[2] == by[3] == by[7] == by[10] == 2
    assert {r["component_id"] for r in rows if r["doc_id"] is None} == {1, 2}
    assert simhash.near_duplicates(no_docs).count() == 0
    kept = simhash.deduplicate(odd_docs)
    assert kept.columns == odd_docs.columns
    assert sorted(r["doc_id"] for r in kept.collect() if r["doc_id"] is not None) == [1, 2, 4, 8, 9]


# ------------------------------------------------------------------ media


@settings(max_examples=40, deadline=None)
@given(st.lists(st.binary(min_size=1, max_size=900), min_size=1, max_size=4))
def test_flac_round_trip(payloads):
    for p, x in zip(payloads, flac.decode(flac.encode(payloads))):
        assert (x + 128).astype(np.uint8).tobytes() == p


def bits(*fields):
    return "".join(f"{v & ((1 << w) - 1):0{w}b}" for v, w in fields)


def hand_made(body: str, samples: list[int]) -> bytes:
    """A one-frame stream around subframe bits."""
    head = bytes([0xFF, 0xF8, 0x70, 0x02, 0x00]) + (len(samples) - 1).to_bytes(2, "big")
    c8 = 0
    for b in head:
        c8 = int(flac._CRC8[c8 ^ b])
    raw = int(body.ljust(-(-len(body) // 8) * 8, "0"), 2).to_bytes(-(-len(body) // 8), "big")
    frame = head + bytes([c8]) + raw
    c16 = 0
    for b in frame:
        c16 = ((c16 << 8) ^ int(flac._CRC16[(c16 >> 8) ^ b])) & 0xFFFF
    frame += c16.to_bytes(2, "big")
    return flac._stream_head(bytes(v + 128 for v in samples), [frame], 256) + frame


def test_flac_partitions_escapes_and_predictors():
    samples = [3, 5, 4, 4, 9, -2, 0, 1, 1, 1, 2, 3, 5, 8, 13, 21]
    residual = [b - a for a, b in zip(samples, samples[1:])]

    def rice(v, k):
        f = 2 * v if v >= 0 else -2 * v - 1
        return "0" * (f >> k) + "1" + (f"{f & ((1 << k) - 1):0{k}b}" if k else "")

    # fixed order 1, two partitions: Rice with k=2, then an escape with 6-bit values; five-bit parameters
    body = bits((9 << 1, 8), (samples[0], 8), (1, 2), (1, 4), (2, 5)) + "".join(rice(v, 2) for v in residual[:7]) + bits((31, 5), (6, 5)) + bits(*[(v, 6) for v in residual[7:]])
    assert flac.decode([hand_made(body, samples)])[0].tolist() == samples
    # linear predictor of order 2, weights 3 and -1 at shift 1
    pred = [(3 * samples[i - 1] - samples[i - 2]) >> 1 for i in range(2, 16)]
    body = bits((33 << 1, 8), (samples[0], 8), (samples[1], 8), (4, 4), (1, 5), (3, 5), (-1, 5), (0, 2), (0, 4), (3, 4)) + "".join(rice(s - p, 3) for s, p in zip(samples[2:], pred))
    assert flac.decode([hand_made(body, samples)])[0].tolist() == samples


def test_flac_damage_and_seeking():
    data = bytes((128 + 90 * np.sin(np.arange(5000) / 7)).astype(np.uint8))
    stream, = flac.encode([data])
    assert len(stream) < len(data)
    for a, n in ((0, 10), (255, 2), (4990, 10), (1000, 3000)):
        assert flac.seek(stream, a, n) == data[a : a + n]
    for at in (len(stream) - 1, len(stream) - 300, len(stream) // 2):
        broken = bytearray(stream)
        broken[at] ^= 4
        with pytest.raises(flac.FlacError):
            flac.decode([bytes(broken)])
    with pytest.raises(flac.FlacError):
        flac.decode([b"RIFF" + stream[4:]])
    assert zlib.crc32(flac.seek(stream, 4936, 64)) == zlib.crc32(data[-64:])


def test_media_query_and_odd_rows(spark, sf, odd_docs, no_docs):
    got = {r["doc_id"]: r for r in QUERIES["op5_flac_media"](spark, sf).collect()}
    for r in table(spark, sf, "documents").collect():
        raw = (r["text"] or "").encode()
        p = raw.ljust(max(64, -(-len(raw) // 64) * 64), b"\0")
        g = got[r["doc_id"]]
        assert (g["n_bytes"], g["payload_bytes"], g["payload_sha256"], g["tail_crc32"]) == (len(raw), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
    media = flac.encode_media(odd_docs)
    rows = flac.read_media(media).collect()
    assert len(rows) == 13 and {r["payload_bytes"] for r in rows if r["doc_id"] in (2, 3, 10)} == {64}
    assert len({(r["media_sha256"], r["feature"]) for r in rows if r["doc_id"] in (1, 5)}) == 1
    assert flac.read_media(flac.encode_media(no_docs)).count() == 0
    blocks = flac.pcm_blocks(media).where("doc_id = 4").orderBy("block").collect()
    pcm = b"".join(r["pcm"] for r in blocks)
    assert [r["first_sample"] for r in blocks] == list(range(0, len(pcm), 256)) and bytes(b ^ 128 for b in pcm).rstrip(b"\0").startswith(b"lorem")


# ------------------------------------------------------------------ pages

PAGE = """<html><head><title>T</title><script>var a="<p>no</p>";</script></head><body><header class="top"><a href=/>Home</a><h2>Site</h2></header><nav><ul><li>menu</ul></nav>
<div id="content"><h1>Big &amp; title</h1><p>First long paragraph with <b>bold</b> text and
 many words in it, content really.<p>Short.</p><p>Another long paragraph with text &#233; and many words in it, content really.</p></div>
<div class="sidebar"><p>Side matter that goes on and on and on for many words</p></div><div class="cookie-notice">We use cookies</div><form><p>Fill in this form please</p></form>
<section id="comments"><article class="comment"><p>I am a reader and I think that this is nice</p></article></section><footer>foot</footer></body></html>"""
BODY = "Big & title First long paragraph with bold text and many words in it, content really. Short. Another long paragraph with text é and many words in it, content really."


def test_main_text():
    assert html_extract.main_text(PAGE) == BODY
    marked = PAGE.replace('<div id="content">', "<main><article><header>").replace("</h1>", "</h1></header>").replace("</p></div>\n<div class=\"sidebar\">", "</p></article></main>\n<div class=\"sidebar\">")
    assert html_extract.main_text(marked) == BODY
    assert html_extract.main_text("") == html_extract.main_text("<html><body></body></html>") == html_extract.main_text("<nav>x</nav>") == ""
    assert html_extract.main_text("only &lt;text&gt;\n\n here") == "only <text> here"
    assert html_extract.main_text("<p>" + "long words here " * 20000) == ("long words here " * 20000).strip()


def test_page_query(spark, sf):
    rows = QUERIES["op2_html_extraction"](spark, sf).collect()
    pages = {r["page_id"]: r["html"] for r in table(spark, sf, "pages").collect()}
    assert len(rows) == len(pages)
    for r in rows:
        inner = re.search(r"<article>(.*)</article>", pages[r["page_id"]], re.S)[1]
        parts = [re.sub(r"\s+", " ", __import__("html").unescape(re.sub("<[^>]*>", "", b))).strip() for b in re.split(r"</?(?:h1|p|br)[^>]*>", inner)]
        assert r["text"] == " ".join(p for p in parts if p) and r["n_chars"] == len(r["text"])
    odd = spark.createDataFrame([(1, None, None), (None, "u", "<p>x</p>"), (2, "u", ""), (2, "u", "")], "page_id long, url string, html string").withColumn("text", F.lit(1))
    assert sorted((str(r["page_id"]), r["text"]) for r in html_extract.extract_pages(odd).collect()) == [("1", ""), ("2", ""), ("2", ""), ("None", "x")]
    assert html_extract.extract_pages(odd.limit(0)).count() == 0


# ------------------------------------------------------------------ archive records


def records(spark, rows):
    return spark.createDataFrame(rows, ", ".join(f"{c} {t}" for c, t in warc.COLUMNS.items()))


def response(i, url, ts, etag=None, modified=None, digest=None, status=200, headers=None):
    return (i, "response", url, ts, status, etag, modified, digest, headers or {"ETag": etag or "", "Content-Type": "text/html", "Content-Length": "3"}, f"p{i}")


def visit(i, url, ts, etag=None, modified=None, digest=None, headers=None):
    return (i, "revisit", url, ts, 304, etag, modified, digest, headers or {}, None)


def test_revisit_rules(spark):
    rows = [
        response(1, "http://www.A.com/x?b=2&a=1&utm_source=z#f", 10, '"1"'), response(2, "https://a.com/x?a=1&b=2", 20, '"2"'), response(3, "http://a.com/x/?a=1&b=2", 30, status=500),
        response(4, "http://a.com:80/x?b=2&a=1", 40, '"4"'), response(6, "http://b.com", 5, None, "Mon", "d"), response(5, "http://b.com/", 5, None, "Tue", "d"),
        visit(10, "http://m.a.com/x?a=1&b=2", 25, 'W/"2"', headers={"Date": "now", "Set-Cookie": "no", "Content-Length": "0"}), visit(11, "http://a.com/x?a=1&b=2", 40, '"2"'),
        visit(12, "http://a.com/x?a=1&b=2", 41, '"1"'), visit(13, "http://a.com/x?a=1&b=2", 10, '"1"'), visit(14, "http://b.com", 9, None, "Mon"), visit(15, "http://b.com", 9, None, None, "e"),
        visit(16, "http://b.com", 9), visit(17, None, 9), visit(18, "http://b.com", None), visit(19, "", 1), visit(16, "http://b.com", 9),
    ]
    for slices in (1, 3, 64):
        found = warc.resolve_revisits(records(spark, rows), slices).collect()
        got = {r["record_id"]: (r["base_id"], r["outcome"]) for r in found}
        assert len(found) == 11
        assert got == {10: (2, "resolved"), 11: (2, "resolved"), 12: (4, "mismatch"), 13: (None, "missing"), 14: (6, "resolved"), 15: (6, "mismatch"), 16: (6, "unvalidated"), 17: (None, "missing"), 18: (None, "missing"), 19: (None, "missing")}
    r = next(r for r in found if r["record_id"] == 10)
    assert r["payload"] == "p2" and r["headers"] == {"etag": '"2"', "content-type": "text/html", "content-length": "3", "date": "now"}
    assert warc.resolve_revisits(records(spark, rows).limit(0)).count() == 0


def test_revisit_query_and_files(spark, sf, tmp_path):
    got = sorted(map(str, (tuple(r) for r in QUERIES["op4_warc_revisits"](spark, sf).collect())))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW pages AS SELECT * FROM '{sf}/pages.parquet'")
    assert got == sorted(map(str, con.execute(ORACLES["op4_warc_revisits"]).fetchall()))
    rows = [r.asDict() for r in warc.crawl_of(table(spark, sf, "pages")).orderBy("record_id").limit(40).collect()]
    (tmp_path / "a.warc.gz").write_bytes(warc.to_warc(rows))
    back = {r["record_id"]: r for r in warc.read_warc(spark, str(tmp_path)).collect()}
    assert len(back) == 40 and all(back[r["record_id"]]["payload"] == (r["payload"] or "") and back[r["record_id"]]["etag"] == r["etag"] for r in rows)
    assert base64.b64decode("")[:0] == b""
