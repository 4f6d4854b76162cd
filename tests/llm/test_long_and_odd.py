"""Very long texts in bounded memory, nestings against a naive decoder, ablations, and rows that share ids."""

import base64
import bz2
import gzip
import html as entities
import os
import random
import re
import subprocess
import sys
import urllib.parse

import numpy as np
import pytest

from sparseloom.llm import decontamination, html_extract, secret_scan, simhash, warc
from sparseloom.llm.common import look_up, table

SF01 = "/root/testdata/sf0.01"
ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def grown_mb(code: str) -> float:
    """MB that a process of its own grows by, beyond its inputs, while it runs the code after the line `START`."""
    before, after = code.split("START")
    script = (
        f"import sys; sys.path.insert(0, {ROOT!r})\nimport resource\npeak = lambda: resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1e3\n{before}\n"
        f"at = peak()\n{after}\nprint('grown', peak() - at)\n"
    )
    found = subprocess.run([sys.executable, "-c", script], capture_output=True, text=True, timeout=300)
    assert found.returncode == 0, found.stderr
    return float(found.stdout.split("grown")[-1])


# ------------------------------------------------------------------ secrets

SECRET = "password = hunter2hunter2xyz9"
WRAPS = {
    "url": lambda t: "".join(f"%{b:02X}" for b in t.encode()), "unicode": lambda t: "".join(f"\\u{ord(c):04x}" for c in t),
    "base64": lambda t: base64.b64encode(t.encode()).decode(), "gzip": lambda t: base64.b64encode(gzip.compress(t.encode(), mtime=0)).decode(),
    "bzip2": lambda t: base64.b64encode(bz2.compress(t.encode())).decode(),
}


def naive_layers(text, depth=0):
    """All decoded texts, by plain recursion over whole lines and runs."""
    yield text
    if depth == 6:
        return
    below = set()
    for line in text.split("\n"):
        below.add(urllib.parse.unquote(line))
        below.add(re.sub(r"\\u([0-9a-f]{4})", lambda m: chr(int(m[1], 16)), line))
    for run in re.findall(r"[A-Za-z0-9+/]{16,}={0,2}", text):
        try:
            raw = base64.b64decode(run.rstrip("=") + "=" * (-len(run.rstrip("=")) % 4))
        except ValueError:
            continue
        for unpack in (bytes, gzip.decompress, bz2.decompress):
            try:
                below.add(unpack(raw).decode())
            except (OSError, ValueError, EOFError):
                pass
    for x in below - {text}:
        yield from naive_layers(x, depth + 1)


@pytest.mark.parametrize("seed", range(40))
def test_random_nestings_with_repeats(seed):
    rng = random.Random(seed)
    parts, secrets = [], []
    for k in range(rng.randint(1, 6)):
        hows = [rng.choice(list(WRAPS)) for _ in range(rng.randint(1, 3))]
        body = SECRET if rng.random() < 0.7 else f"token: {'abcdefghijklmnop'[: rng.randint(12, 16)]}"
        for how in hows:
            body = WRAPS[how](body)
        for _ in range(rng.randint(1, 3)):  # the same encoded secret at several places
            parts += [rng.choice(["plain words, ", "été — ", "line\n", "a; "]), body, rng.choice(["\n", " and so on.\n", ", tail\n"])]
            secrets.append(body)
    text = "".join(parts)
    base, spans, _ = secret_scan.scan(text)
    assert set(base) <= set(spans)
    at = 0
    for body in secrets:  # every place has a span that lies inside it
        a = text.index(body, at)
        at = a + len(body)
        assert any(a <= lo and hi <= at for lo, _, hi in spans)
    redacted = secret_scan.redact(text, spans)
    assert not any(p in layer for layer in naive_layers(redacted) for p in (SECRET, "abcdefghijkl"))
    at = 0
    for part in parts:  # and what is no secret stays, in order
        if part not in secrets:
            at = redacted.index(part, at) + len(part)


@pytest.mark.parametrize("how", ["url", "unicode", "base64"])
def test_spans_are_exact_in_one_layer(how):
    text = f"é{WRAPS[how]('日本 ' + SECRET + ', é')} b"
    (a, _, b), = secret_scan.scan(text)[1]
    inner = {"url": urllib.parse.unquote, "unicode": lambda x: re.sub(r"\\u([0-9a-f]{4})", lambda m: chr(int(m[1], 16)), x)}
    if how in inner:
        assert inner[how](text[a:b]) == SECRET
    else:  # whole quanta of four characters around the secret
        assert SECRET.encode()[2:-2] in base64.b64decode(text[a - (a - 1) % 4 : b + -(b - 1) % 4] + "==")


@pytest.mark.parametrize(
    "make",
    [
        "base64.b64encode(gzip.compress(b'words, and more of them\\n' * 2_800_000 + S)).decode()",  # 64 MB below 90 kB
        "'word, ' * 6_000_000 + '%20' + S.decode().replace('=', '%3D')",  # one line of 36 MB with two escapes
        "'%41%2C' * 2_000_000 + '%20' + S.decode()",  # one long escape
        "base64.b64encode(b'some words, and more\\n' * 400_000 + S).decode()",  # 11 MB in one run
    ],
)
def test_long_layers_in_bounded_memory(make):
    code = f"""
import base64, gzip
from sparseloom.llm import secret_scan
S = b'password = hunter2hunter2xyz9'
text = {make}
START
assert secret_scan.scan(text)[1]
"""
    assert grown_mb(code) < 500


# ------------------------------------------------------------------ media


def test_long_media_in_bounded_memory():
    code = """
from sparseloom.llm import flac
data = (b"some words, and more of them " * 900_000)[: 24 << 20]
START
stream, = flac.encode([data])
back, = flac.decode([stream])
assert (back + 128).astype("u1").tobytes() == data
flac.features_of(back)
"""
    assert grown_mb(code) < 600


def test_features_do_not_depend_on_pieces():
    from sparseloom.llm import flac

    x = np.random.default_rng(3).integers(-128, 128, 1000).astype(np.int16)
    assert len({flac.features_of(x, most) for most in (1, 7, 999, 1000, 5000)}) == 1
    wide = x.astype(int)
    assert flac.features_of(x) == f"peak={abs(wide).max()};energy={(wide * wide).sum()};crossings={((wide[1:] < 0) != (wide[:-1] < 0)).sum()};steps={abs(np.diff(wide)).sum()}"


# ------------------------------------------------------------------ decontamination


def test_automaton_is_bounded_by_states(spark):
    rng = random.Random(1)
    vocabulary = [f"w{k}" for k in range(300)]
    items = [(str(k), " ".join(rng.choices(vocabulary, k=rng.randint(3, 60)))) for k in range(60)]
    frame = spark.createDataFrame([(int(i), t) for i, t in items], "item_id long, text string")
    named = decontamination._items(frame, "item_id", "text")
    blocks = list(decontamination._cut(named, 10, 2000))
    assert len(blocks) > 5 and all(decontamination.WindowAutomaton(b).states <= 2000 for b in blocks)
    bodies = [" ".join(rng.choices(vocabulary, k=30)) + " " + items[k % 60][1] + " " + items[k % 7][1][:40] for k in range(40)]
    docs = spark.createDataFrame(list(enumerate(bodies)), "doc_id long, text string")
    shape = lambda df: sorted((r["doc_id"], r["n_words"], r["n_hit"], tuple(r["items"]), str(r["spans"])) for r in df.collect())
    whole = shape(decontamination.find_contamination(docs, frame))
    assert whole == shape(decontamination.find_contamination(docs, frame, max_states=2000)) and all(n for _, _, n, _, _ in whole)
    one_stage = decontamination.find_contamination(docs, frame, max_states=2000)._jdf.queryExecution().executedPlan().toString()
    assert one_stage.count("MapInArrow") == 1
    assert decontamination.keep_clean(docs, frame, max_states=2000).count() == 0


# ------------------------------------------------------------------ pages


def article_of(html):
    inner = re.search(r"<article>(.*)</article>", html, re.S)[1]
    parts = [re.sub(r"\s+", " ", entities.unescape(re.sub("<[^>]*>", "", b))).strip() for b in re.split(r"</?(?:h1|p|br)[^>]*>", inner)]
    return " ".join(p for p in parts if p)


def misses(pages, change):
    return sum(html_extract.main_text(change(h)) != article_of(h) for h in pages)


def test_ratios_choose_the_region(spark, monkeypatch):
    pages = [r["html"] for r in table(spark, SF01, "pages").collect()]
    unmarked = lambda h: re.sub(r"<(/?)article>", r"<\1div>", h)
    wrapped = lambda h: unmarked(h).replace("<body>", '<body><form><div class="content-sidebar-wrap">').replace("</body>", "</div></form></body>")
    # no names at all, and more links than text: only the ratio tells the article from the rest
    bare = lambda h: re.sub(r"<ul>(.*?)</ul>", lambda m: f"<ul>{m[1] * 25}</ul>", re.sub(r"<(/?)(nav|footer|article)>", r"<\1div>", h))
    assert misses(pages, unmarked) == misses(pages, wrapped) == 0
    assert misses(pages, bare) < 0.05 * len(pages)
    monkeypatch.setattr(html_extract, "text_to_tag", lambda blocks: np.ones(len(blocks)))
    assert misses(pages, bare) > 0.5 * len(pages)


def test_names_are_priors():
    body = "<h1>Head</h1>" + "".join(f"<p>Paragraph {k} with a good many words of content in it.</p>" for k in range(4)) + "<p>End.</p>"
    want = "Head " + " ".join(f"Paragraph {k} with a good many words of content in it." for k in range(4)) + " End."
    for page in (
        f'<div class="content-sidebar-wrap"><main>{body}</main><div class="sidebar"><p>Side matter, side matter.</p></div></div>',
        f'<form id="aspnet"><nav>menu</nav><div class="with-sidebar">{body}</div></form>',
        f'<main><header><p class="breadcrumbs">a b</p></header><article>{body}</article><div class="related"><p>More of the same, and of other things.</p></div></main>',
        f'<article>{body}</article><section class="comments"><article><p>{"I think so too. " * 60}</p></article></section>',
        f'<article>{body}</article><div class="ad">{"Buy now, buy now. " * 200}</div>',
    ):
        assert html_extract.main_text(f"<html><body>{page}</body></html>") == want
    assert html_extract.main_text('<body><div class="ad">Buy now, buy more.</div><article></article></body>') == ""


# ------------------------------------------------------------------ rows that share ids


def test_deduplicate_decides_row_by_row(spark):
    long_a, long_b = " ".join(f"alpha{k}" for k in range(50)), " ".join(f"beta{k}" for k in range(50))
    rows = [(5, long_a, 1), (5, long_b, 2), (7, long_b, 3), (9, long_a, 4), (9, long_a, 5), (None, long_a, 6), (5, long_b, 7), (11, "unlike anything else", 8)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, _id int")
    kept = simhash.deduplicate(docs)
    assert kept.columns == ["doc_id", "text", "_id"]
    assert sorted((str(r["doc_id"]), r["text"][:5]) for r in kept.collect()) == [("11", "unlik"), ("5", "alpha"), ("5", "beta0"), ("None", "alpha")]


def test_every_pair_is_put_to_the_pivots(monkeypatch):
    rng = np.random.default_rng(5)
    fps = rng.integers(0, 2**63, 300, dtype=np.uint64)
    fps = np.concatenate([fps, fps[:100] ^ np.uint64(0b101)])
    rows = simhash.pivot_table(fps, simhash.references())
    found = {(min(a, b), max(a, b)) for i, j in simhash.linked_pairs(fps, rows) for a, b in zip(i.tolist(), j.tolist())}
    want = {(i, j) for i in range(400) for j in range(i + 1, 400) if int(fps[i] ^ fps[j]).bit_count() <= 4}
    assert found == want and len(found) >= 100
    wrong = rows.copy()
    wrong[300:, -1] += 40  # a wrong last coordinate: the pairs go, so that coordinate was asked for
    assert not list(simhash.linked_pairs(fps, wrong))


def test_look_up_answers_frequent_keys(spark):
    rows = spark.range(20_000).selectExpr("CASE WHEN id % 3 = 0 THEN 1 ELSE id END AS k", "id")
    answers = rows.groupBy("k").count().selectExpr("k", "count AS n", "k * 2 AS a")
    got = look_up(rows, "k", answers, "n", 20_000)
    assert got.columns == ["k", "id", "a"] and got.count() == 20_000 and got.where("a <> 2 * k").count() == 0


def test_revisits_of_rows_without_ids_and_with_clashing_columns(spark):
    columns = ", ".join(f"{c} {t}" for c, t in warc.COLUMNS.items())
    full = lambda i, url, ts, tag, body: (i, "response", url, ts, 200, tag, None, None, {"ETag": tag}, body, 0, "k", None)
    visit = lambda i, url, ts, tag: (i, "revisit", url, ts, 304, tag, None, None, {"Date": "d"}, None, 0, "k", None)
    rows = [
        full(None, "a.com/x", 1, "1", "x1"), full(2, "a.com/y", 1, "2", "y1"), full(2, "a.com/x", 3, "3", "x3"),
        visit(None, "a.com/x", 2, "1"), visit(9, "a.com/x", 4, "3"), visit(9, "a.com/y", 4, "2"), visit(9, "a.com/y", 4, "2"), visit(None, None, 5, "1"),
    ]
    frame = spark.createDataFrame(rows, f"{columns}, slice int, key string, base string")
    for slices in (1, 4, 1024):
        got = sorted((str(r["record_id"]), str(r["key"]), r["outcome"], str(r["payload"])) for r in warc.resolve_revisits(frame, slices).collect())
        assert got == [
            ("9", "a.com/x", "resolved", "x3"), ("9", "a.com/y", "resolved", "y1"), ("9", "a.com/y", "resolved", "y1"),
            ("None", "None", "missing", "None"), ("None", "a.com/x", "resolved", "x1"),
        ]
