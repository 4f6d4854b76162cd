"""Token counts, packing, decontamination, secrets: against libraries and brute force, and on odd rows."""

import base64
import bz2
import gzip
import hashlib
import re
import urllib.parse
import zlib

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from sparseloom.llm import decontamination, packing, secret_scan, token_counts
from sparseloom.llm.common import table
from sparseloom.llm.queries import QUERIES

WORDY = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
BYTES = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
ODD = ["", "  ", "a  b\n\n c\t\td 's it's'll  \n", "x<|endoftext|>y <|startoftext|> z", "ΑΣ ΟΔΟΣ İstanbul é x y", "日本語 🙂🙂 \x1c\x1dz", "ab" * 5000, "½² 12 ´ª", "don't WE'LL ''s"]
ALPHABET = st.text(alphabet=st.sampled_from(list("abcAB'é ß\n\t,.1|<>#Σ日")), max_size=40)


@settings(max_examples=150, deadline=None)
@given(ALPHABET)
def test_ids_and_counts_equal_the_library(text):
    words, merges = packing._word_ids("word_bpe_49k.json"), token_counts.merges_of("byte_bpe_50k.json")
    assert words.encode(text) == np.asarray(WORDY.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
    assert merges.count(text) == len(BYTES.encode(text, add_special_tokens=False).ids)


@pytest.mark.parametrize("text", ODD)
def test_odd_texts(text):
    test_ids_and_counts_equal_the_library.hypothesis.inner_test(text)


def test_token_counts_query(spark, sf):
    got = {r["doc_id"]: r for r in QUERIES["op10_token_counts"](spark, sf).collect()}
    for r in table(spark, sf, "documents").collect():
        n = len(BYTES.encode(r["text"] or "", add_special_tokens=False).ids)
        assert (got[r["doc_id"]]["n_tokens"], got[r["doc_id"]]["over_limit"], got[r["doc_id"]]["n_bytes"]) == (n, n > 512, len((r["text"] or "").encode()))


def test_token_counts_on_odd_rows(odd_docs, no_docs):
    rows = token_counts.count_tokens(odd_docs).collect()
    assert len(rows) == 13 and token_counts.count_tokens(no_docs).count() == 0
    by = {r["doc_id"]: r["n_tokens"] for r in rows}
    assert by[2] == by[3] == by[10] == 0 and by[4] > 10000


def checked_packing(rows, most=2048):
    """Every sequence gapless from 0 and within bounds; gives the number of sequences."""
    spans: dict = {}
    for r in rows:
        spans.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in spans.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= most
    return len(spans)


def test_packing_query_against_the_library(spark, sf):
    rows = QUERIES["op1_best_fit_packing"](spark, sf).collect()
    n = checked_packing(rows)
    by: dict = {}
    for r in rows:
        by.setdefault(r["doc_id"], {})[r["piece"]] = r
    total = 0
    for d in table(spark, sf, "documents").collect():
        ids = WORDY.encode(d["text"] or "", add_special_tokens=False).ids + [0]
        total += len(ids)
        for k in range(-(-len(ids) // 2048)):
            part = ids[k * 2048 : (k + 1) * 2048]
            r = by[d["doc_id"]].pop(k)
            assert (r["start"], r["length"], r["ids_crc32"]) == (k * 2048, len(part), zlib.crc32(np.asarray(part, "<u4").tobytes()))
    assert not any(by.values())
    assert n <= -(-total // 2048) + 2


def first_fit(lengths, most):
    """Plain best fit decreasing over single pieces."""
    room: list[int] = []
    for x in sorted(lengths, reverse=True):
        fit = min((r for r in room if r >= x), default=None)
        if fit is None:
            room.append(most - x)
        else:
            room[room.index(fit)] = fit - x
    return len(room)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.integers(1, 20), max_size=80))
def test_plan_equals_best_fit_over_pieces(lengths):
    histogram = {x: lengths.count(x) for x in set(lengths)}
    plan = packing.plan_packing(histogram, 20)
    assert plan.sequences == first_fit(lengths, 20)
    rows = []
    for x, n in histogram.items():
        sequence, offset = plan.slots(np.full(n, x, np.int64), np.arange(n, dtype=np.int64))
        rows += [{"sequence_id": int(s), "offset": int(o), "length": x} for s, o in zip(sequence, offset)]
    assert checked_packing(rows, 20) == plan.sequences


def test_packing_on_odd_rows(odd_docs, no_docs):
    packed = packing.pack_documents(odd_docs)
    rows = packed.collect()
    checked_packing(rows)
    assert sum(r["doc_id"] == 5 for r in rows) == 2 and sum(r["doc_id"] is None for r in rows) == 2
    assert all(r["ids"] == b"\0\0\0\0" for r in rows if r["doc_id"] in (2, 3, 7, 10))
    whole = packing.sequences(packed).collect()
    assert sum(r["n_tokens"] for r in whole) == sum(r["length"] for r in rows) and all(len(r["ids"]) == 4 * r["n_tokens"] for r in whole)
    assert packing.pack_documents(no_docs).count() == 0


# ------------------------------------------------------------------ decontamination


def brute_windows(text, items, window=10):
    word = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    words_of = lambda t: word.findall((t or "").encode().lower())
    words, hit, found = words_of(text), set(), set()
    for item, body in items:
        w = words_of(body)
        for window_ in {tuple(w[i : i + window]) for i in range(max(1, len(w) - window + 1))} if w else ():
            for i in range(len(words) - len(window_) + 1):
                if tuple(words[i : i + len(window_)]) == window_:
                    hit.update(range(i, i + len(window_)))
                    found.add(str(item))
    return len(words), len(hit), sorted(found)


def test_decontamination_query(spark, sf):
    items = [tuple(r) for r in table(spark, sf, "benchmark").select("item_id", "text").collect()]
    got = {r["doc_id"]: r for r in QUERIES["op9_benchmark_decontamination"](spark, sf).collect()}
    hits = 0
    for r in table(spark, sf, "documents").collect():
        n, hit, found = brute_windows(r["text"], items)
        g = got[r["doc_id"]]
        digest = hashlib.sha256(",".join(found).encode()).hexdigest()
        assert (g["n_words"], g["n_hit"], g["n_items"], g["items_sha256"], g["contaminated"]) == (n, hit, len(found), digest, hit > 0)
        hits += hit > 0
    assert hits


def test_decontamination_spans_blocks_and_odd_rows(spark, odd_docs, no_docs):
    bench = spark.createDataFrame(
        [(1, "Quick BROWN fox, jumps over the lazy dog and then it"), (2, "Zürich straße"), (2, "Zürich straße"), (3, None), (None, "near the river bank"), (4, ""), (5, "river bank")],
        "item_id long, text string",
    )
    docs = spark.createDataFrame([(1, "é The quick brown -- fox jumps over the LAZY dog, and then it rests. ZÜRICH Zürich straße river bank!")], "doc_id long, text string")
    for limit in (10**6, 20):  # one automaton, and one per block
        r = decontamination.find_contamination(docs, bench, max_states=limit).first()
        text = docs.first()["text"]
        assert r["items"] == ["1", "2", "5"] and r["n_hit"] == 15 - 0 - 0 + 0
        assert [text[s["from"] : s["to"]] for s in r["spans"]] == ["quick brown -- fox jumps over the LAZY dog, and then it", "Zürich straße river bank"]
    rows = decontamination.find_contamination(odd_docs, bench).collect()
    assert len(rows) == 13 and {r["doc_id"] for r in rows if r["n_hit"]} == {1, 5, 11, None}
    assert decontamination.find_contamination(no_docs, bench).count() == 0
    assert decontamination.find_contamination(odd_docs, bench.limit(0)).agg(F.sum("n_hit")).first()[0] == 0
    assert {r["doc_id"] for r in decontamination.keep_clean(odd_docs, bench).collect()} == {2, 3, 4, 7, 8, 9, 10, None}


# ------------------------------------------------------------------ secrets

SECRET = 'password = "hunter2hunter22"'


def brute_spans(x):
    out = [(m.start(), "assign", m.end()) for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", x, re.I | re.A) if len(m[2]) >= 12]
    out += [(m.start(), "access", m.end()) for m in re.finditer("AKIA[A-Z0-9]+", x) if len(m[0]) >= 18]
    out += [(m.start(), "hex", m.end()) for m in re.finditer("[0-9a-f]+", x) if len(m[0]) >= 16]
    return sorted(out, key=lambda s: (s[0], ["assign", "access", "hex"].index(s[1])))


def test_secret_query(spark, sf):
    got = {r["doc_id"]: r for r in QUERIES["op6_secret_scans"](spark, sf).collect()}
    seen = 0
    for r in table(spark, sf, "documents").collect():
        want = [f"{k}:{a}:{b}" for a, k, b in brute_spans(r["text"] or "")]
        g = got[r["doc_id"]]
        assert g["base_sha256"] == hashlib.sha256(",".join(want).encode()).hexdigest() and set(want) <= set(g["spans"].split(",")) | {""}
        assert (g["n_assign"], g["n_access"], g["n_hex"]) == tuple(sum(w.startswith(k) for w in want) for k in ("assign", "access", "hex"))
        seen += len(want)
    assert seen


def wrap(text, how):
    return {
        "url": lambda: urllib.parse.quote(text, safe=""), "unicode": lambda: "".join(f"\\u{ord(c):04x}" for c in text), "base64": lambda: base64.b64encode(text.encode()).decode(),
        "urlsafe": lambda: base64.urlsafe_b64encode(text.encode()).decode(), "gzip": lambda: base64.b64encode(gzip.compress(text.encode())).decode(),
        "zlib": lambda: base64.b64encode(zlib.compress(text.encode())).decode(), "lines": lambda: base64.encodebytes((text * 4).encode()).decode(),
    }[how]()


@pytest.mark.parametrize("how", ["url", "unicode", "base64", "urlsafe", "gzip", "zlib", "lines", ("base64", "gzip"), ("url", "base64"), ("url", "url"), ("gzip", "unicode", "base64")])
def test_nested_layers(how):
    body = SECRET
    for h in (how,) if isinstance(how, str) else how:
        body = wrap(body, h)
    text = f"été {body} fin"
    if how == "lines":
        text = f"été\n{body}\nfin"
    base, spans, layers = secret_scan.scan(text)
    assert base == [] and spans and layers > 1
    lo, hi = min(a for a, _, _ in spans), max(b for _, _, b in spans)
    assert 3 <= lo and hi <= len(text) - 3
    assert all(kind == "assign" for _, kind, _ in spans)


def test_exact_mapping_cycles_and_redaction():
    text = f"a {wrap('é', 'url')} {wrap(SECRET, 'url')} b"
    (a, kind, b), = secret_scan.scan(text)[1]
    assert urllib.parse.unquote(text[a:b]) == SECRET[:-1]
    assert secret_scan.scan("%2525252525" * 50)[2] < 60
    assert secret_scan.redact("x token=abcdefghijklmnop y", secret_scan.scan("x token=abcdefghijklmnop y")[1]) == "x [SECRET] y"
    assert secret_scan.redact("", []) == ""


@pytest.mark.parametrize("how", ["url", "unicode", "base64", "gzip", ("gzip", "base64")])
def test_every_place_of_a_repeated_encoded_secret_is_found(how):
    run = SECRET
    for h in [how] if isinstance(how, str) else how:
        run = wrap(run, h)
    text = f"{run}\nsome words\n{run}\nother words\n{run}\n"
    redacted = secret_scan.redact(text, secret_scan.scan(text)[1])
    assert len({a for a, _, _ in secret_scan.scan(text)[1]}) == 3
    assert redacted.count(secret_scan.REDACTED) == 3 and not secret_scan.scan(redacted)[1]


@pytest.mark.parametrize("pack", [gzip.compress, zlib.compress, bz2.compress])
def test_compressed_data_is_scanned_to_its_end(pack):
    filler = b"plain words, and more of them\n" * 2_400_000  # beyond 64 MB
    for data in (pack(filler + SECRET.encode()), pack(b"first member\n") + pack(SECRET.encode()), pack(b"a member\n") + gzip.compress(SECRET.encode())):
        run = base64.b64encode(data).decode()
        assert secret_scan.scan(f"<{run}>")[1] == [(1, "assign", 1 + len(run.rstrip("=")))]


def test_pieces_of_inflated_data_do_not_cut_what_a_pattern_holds():
    rng = np.random.default_rng(5)
    words = [SECRET, base64.encodebytes(SECRET.encode() * 9).decode(), wrap(SECRET, "url"), "0123456789abcdef" * 3, "word", "\n", " ", "é, ", "; ", "AKIA" + "Z" * 20, "ab" * 40 + "\n"]
    text = "".join(words[k] for k in rng.integers(0, len(words), 60_000))
    pieces = list(secret_scan._text_pieces(text.encode()[i : i + 70_001] for i in range(0, len(text.encode()), 70_001)))
    assert "".join(pieces) == text and len(pieces) > 3
    assert sum(len(secret_scan.base_spans(p)) for p in pieces) == len(secret_scan.base_spans(text))
    below = lambda x: {b.text[i:j] for b in [secret_scan.Layer(x), *secret_scan.decoded_layers(secret_scan.Layer(x))] for i, _, j in secret_scan.base_spans(b.text)}
    assert set().union(*map(below, pieces)) == below(text)


def test_secrets_on_odd_rows(odd_docs, no_docs):
    rows = secret_scan.find_secrets(odd_docs).collect()
    assert len(rows) == 13 and not any(r["spans"] for r in rows)
    assert secret_scan.find_secrets(no_docs).count() == 0
    kept = secret_scan.redact_documents(odd_docs)
    assert kept.columns == odd_docs.columns and sorted(map(str, kept.collect())) == sorted(map(str, odd_docs.collect()))
