"""Training-data operators against brute force and on awkward inputs: nulls, empty and long texts, ties, repeated rows, empty tables, extra columns."""

import hashlib
import math
import random
import textwrap
import time
from collections import Counter
from pathlib import Path

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from strata_engine.llm import bm25, bpe, components, decontaminate, html_blocks, importance, langid, licenses, queries, simhash, suffix_dedup, toxicity

WORDS = [f"{a}{b}" for a in ("ka", "lo", "mi", "ter", "un") for b in ("ra", "vel", "ship", "do", "ing", "ex", "pol")]


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


@pytest.fixture(scope="module")
def docs(spark):
    rng = random.Random(5)
    shared = prose(rng, 40)
    long = prose(rng, 30_000)
    rows = [(i, prose(rng, rng.randint(0, 120)) + (" " + shared + " " if i % 3 == 0 else "") + prose(rng, 20), "en", 7, "x") for i in range(60)]
    rows += [(100, None, None, 1, None), (101, "", "en", 1, ""), (102, "a", "de", 1, ""), (103, " \n\t ", "en", 1, ""), (104, "é" * 60 + shared, "fr", 1, ""), (105, "ü" + "é" * 60, "fr", 1, ""), (106, long, "en", 1, ""), (107, long[500:90_000], "en", 1, ""), (108, shared, "en", 1, ""), (109, shared.upper(), "en", 1, "")]
    rows += [rows[3], (None, shared, "en", 1, "")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, stratum int, ids string")


def rows_of(docs):
    return [(r["doc_id"], (r["text"] or "")) for r in docs.select("doc_id", "text").collect()]


def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, quality int, toxic int")


def test_suffix_dedup(spark, docs):
    got = suffix_dedup.repeated_passages(docs).collect()
    big = np.iinfo(np.int64).max
    src = [(big if i is None else i, t.encode()) for i, t in rows_of(docs)]
    want = suffix_dedup.brute_force(src)
    assert len(got) == len(src)
    for r in got:
        w = want[big if r["doc_id"] is None else r["doc_id"]]
        assert (r["n_bytes"], r["n_removed"], r["n_spans"], bytes(r["kept"])) == w
        assert sum(b - a for a, b in zip(r["span_starts"], r["span_ends"], strict=True)) == r["n_removed"]
    assert suffix_dedup.repeated_passages(empty(spark)).count() == 0


@pytest.mark.parametrize("length", [23, 50, 100])
def test_suffix_dedup_edges_of_passages(spark, length):
    """Passages of about the threshold, cut and overlapping anywhere, runs of one letter and long periods, few letters."""
    rng = random.Random(length)
    letters = lambda n, some: "".join(rng.choices(some, k=n))
    pool = [letters(rng.randint(length - 3, 3 * length), "abcdefghij ") for _ in range(12)] + ["a" * 3 * length, "xyz" * 2 * length, letters(length + 1, "ab"), letters(4 * length, "ab")]
    rows = []
    for i in range(150):
        text = ""
        for _ in range(rng.randint(0, 4)):
            one = rng.choice(pool)
            k = rng.randint(0, 12)
            text += letters(rng.randint(0, 60), "abcdefghij ") + one[k : len(one) - rng.randint(0, 12)]
        rows.append((i, text))
    got = suffix_dedup.repeated_passages(spark.createDataFrame(rows, "doc_id long, text string"), length=length).collect()
    want = suffix_dedup.brute_force([(i, t.encode()) for i, t in rows], length)
    assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], bytes(r["kept"])) for r in got} == want


def test_simhash(spark, docs):
    rng = random.Random(1)
    base = prose(rng, 300).split()
    near = [(1000 + i, " ".join(w if j != 7 * i else "changed" for j, w in enumerate(base))) for i in range(25)]
    both = docs.select("doc_id", "text").unionByName(spark.createDataFrame(near, "doc_id long, text string"))
    src = rows_of(both)
    fps = [simhash.fingerprint(t.encode()) for _, t in src]
    root = list(range(len(src)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(src)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 4:
                root[find(i)] = find(j)
    least = {}
    for i, (k, _) in enumerate(src):
        if k is not None:
            least[find(i)] = min(k, least.get(find(i), 1 << 60))
    want = Counter((k, fps[i], least.get(find(i))) for i, (k, _) in enumerate(src))
    for cap in (2048, 3):  # the small cap forces finer keys
        got = Counter((r["doc_id"], r["fp"] % (1 << 64), r["component_id"]) for r in simhash.near_duplicates(both, cap=cap).collect())
        assert got == want
    assert simhash.near_duplicates(empty(spark)).count() == 0
    assert simhash.fingerprint(b"") == simhash.fingerprint(b" \n\x0b") == 0
    assert simhash.fingerprint("Ab CD ÉE x y".encode()) == simhash.fingerprint("ab cd Ée X  y".encode())


def test_bit_slices():
    rng = np.random.default_rng(2)
    for n in (2, 63, 64, 65, 700):
        fps = np.bitwise_xor.accumulate(np.bitwise_and.reduce(rng.integers(0, 1 << 63, (4, n), dtype=np.uint64), axis=0))
        fps[n // 2 :] ^= np.uint64(1 << 63)
        fps[: n // 8] = fps[0]
        planes = simhash.Planes(fps, at_once=128)
        for step in {1, 2, 5, 63, 64, 65, 130, n - 1} & set(range(1, n)):
            for at in (np.arange(n - step), np.flatnonzero(rng.random(n - step) < 0.05)):
                for radius in range(8):
                    want = at[np.bitwise_count(fps[at] ^ fps[at + step]) <= radius]
                    assert planes.near(at, step, radius).tolist() == want.tolist()


def test_components(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (200, 200)] + [(300, 301 + i) for i in range(50)]
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[101] == 100 and all(got[301 + i] == 300 for i in range(50)) and 200 not in got


def test_least_of_hot_keys(spark):
    rows = [(1, i, str(i)) for i in range(200, 0, -1)] + [(k, k + j, "x") for k in range(2, 12) for j in range(3)] + [(20, None, None)]
    df = spark.createDataFrame(rows, "k long, v long, other string")
    got = sorted(map(tuple, components.with_least(df, "k", "v", len(rows)).collect()), key=str)
    least = {1: 1, 20: None} | {k: k for k in range(2, 12)}
    assert got == sorted(((*r, least[r[0]]) for r in rows), key=str)
    assert components.with_least(df.limit(0), "k", "v", 0).count() == 0


def test_bpe_round_trip(spark, docs):
    import tiktoken

    path, pattern = queries.vocabulary()
    ranks = bpe.read_ranks(path)
    lib = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks={t: i for i, t in enumerate(ranks)}, special_tokens={})
    odd = spark.createDataFrame([(1, "<|endoftext|> I'll  go\n\n  x 漢字🙂é½   a"), (2, "a" * 300), (3, None), (3, "é"), (None, " ")], "doc_id long, text string")
    src = docs.select("doc_id", "text").unionByName(odd)
    got = bpe.decode(bpe.encode(src, path, pattern, offsets=True).withColumn("packed", F.col("ids")), path, pattern).collect()
    packed = lambda t: np.array(lib.encode_ordinary(t), dtype="<u4").tobytes()
    want = Counter((k, packed(t), len(lib.encode_ordinary(t)), t.encode()) for k, t in rows_of(src))
    assert Counter((r["doc_id"], bytes(r["packed"]), r["n_tokens"], bytes(r["decoded"])) for r in got) == want
    assert all(r["offsets"][-1] == len(r["decoded"]) for r in got if r["n_tokens"])
    one = bpe.encode(odd, path, pattern).filter("doc_id = 1").select("ids", bpe.unpack_ids("ids").alias("a")).first()
    ids = lib.encode_ordinary("<|endoftext|> I'll  go\n\n  x 漢字🙂é½   a")
    assert one["a"] == ids and bytes(one["ids"]) == np.array(ids, dtype="<u4").tobytes()
    assert "".join(bpe.stream_text([[i] for i in ids], ranks)) == "<|endoftext|> I'll  go\n\n  x 漢字🙂é½   a"
    assert bpe.encode(empty(spark), path, pattern).count() == 0


def test_bpe_ids_of_every_code_point():
    """Ids as tiktoken's for each code point after and before letters, digits, signs and spaces, and for random texts."""
    import tiktoken

    path, pattern = queries.vocabulary()
    lib = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks={t: i for i, t in enumerate(bpe.read_ranks(path))}, special_tokens={})
    points = [chr(c) for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    texts = ["\n".join(f"a{c}a{c}1{c}!{c} {c}" for c in points[i : i + 2000]) for i in range(0, len(points), 2000)]
    rng = random.Random(3)
    letters = [c for c in points if c.isalnum()]
    texts += ["".join(rng.choice((rng.choice(points), rng.choice(letters), rng.choice("ab 1'!\n\t"))) for _ in range(rng.randint(1, 30))) for _ in range(50_000)]
    for i in range(0, len(texts), 500):
        some = texts[i : i + 500]
        assert bpe.packed_ids(some, path, pattern) == [np.array(lib.encode_ordinary(t), dtype="<u4").tobytes() for t in some]


def test_bpe_repeated_words_are_encoded_once(monkeypatch):
    """The library sees a word once while it is kept; what it gives for whole texts doesn't change, nor under another pattern."""
    path, pattern = queries.vocabulary()
    rng, whole, seen = random.Random(5), bpe._library_ids, []
    signs = ["a", "b", "é", "ß", "1", "'s", "!", ",", " ", " ", "  ", "\n", "\t", "\r\n", "\x0b", "\x1c", "\x85", "\xa0", "\u200b", "\u2003", "\u2019", "\u3000", "漢", "🙂", "the ", "x" * 90]
    texts = ["".join(rng.choice(signs) for _ in range(rng.randint(0, 60))) for _ in range(3_000)]
    want = whole(texts, path, pattern)
    monkeypatch.setattr(bpe, "_library_ids", lambda t, *a: (seen.extend(t), whole(t, *a))[1])
    for most in (bpe.KEPT, 100):
        monkeypatch.setattr(bpe, "KEPT", most)
        monkeypatch.setattr(bpe, "_ids", {})
        assert [x for i in range(0, len(texts), 70) for x in bpe.packed_ids(texts[i : i + 70], path, pattern)] == want
    monkeypatch.setattr(bpe, "_ids", {})
    seen.clear()
    often = "of words\nthat come again, " * 5_000
    assert bpe.packed_ids([often, often], path, pattern) == whole([often, often], path, pattern)
    assert sum(map(len, seen)) < 100
    joined = r"\S+\s|\s+|\S+"  # a pattern whose matches end in white space: words are no pieces of it
    assert bpe.packed_ids(["ab cd \n ef"], path, joined) == whole(["ab cd \n ef"], path, joined)


def test_language_id(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    got = queries.op3_language_id(spark, sf).join(d.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in got if r["held_out"]]
    assert len(got) == d.count() and sum(r["lang"] == r["lang_pred"] for r in held) >= 0.97 * len(held)
    assert all(0 <= r["score"] <= 1 for r in got)
    model = langid.fit(d)
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "123 !?"), (4, "漢字"), (None, "der die das")], "doc_id long, text string")
    out = {r["doc_id"]: r["lang_pred"] for r in langid.predict(odd, model).collect()}
    assert out[1] == out[2] == out[3] == "und" and out[4] in model[0]
    none = langid.fit(empty(spark))
    assert langid.predict(odd, none).filter("lang_pred <> 'und'").isEmpty()


def test_toxicity(spark, sf):
    labels = {r["doc_id"]: r["toxic"] for r in spark.read.parquet("/root/testdata/sf0.1/labels.parquet").collect()}
    got = queries.op9_toxicity(spark, "/root/testdata/sf0.1").collect()
    held = [(r["score"], labels[r["doc_id"]]) for r in got if r["held_out"] and r["doc_id"] in labels]
    pos, neg = [s for s, y in held if y], [s for s, y in held if not y]
    assert np.mean([p > n for p in pos for n in neg]) > 0.95
    assert np.mean([s >= 0.5 for s in pos]) > 0.7
    assert np.mean([s >= 0.5 for s in neg]) < 0.02
    model = toxicity.fit(empty(spark))
    odd = spark.createDataFrame([(1, None), (2, "")], "doc_id long, text string")
    assert {r["score"] for r in toxicity.score(odd, model).collect()} == {0.5}


def test_importance(spark, docs):
    target = docs.filter("doc_id % 3 = 0")
    w = {(r["doc_id"], r["n_grams"]): r["log_weight"] for r in importance.log_ratios(docs, target).collect()}
    t, r = Counter(), Counter()
    for k, text in rows_of(docs):
        b = importance.buckets_of(text, 10_000).tolist()
        r.update(b)
        if k is not None and k % 3 == 0:
            t.update(b)
    nt, nr = sum(t.values()) + 10_000, sum(r.values()) + 10_000
    for k, text in rows_of(docs):
        b = importance.buckets_of(text, 10_000).tolist()
        assert w[k, len(b)] == pytest.approx(sum(math.log((t[x] + 1) / nt) - math.log((r[x] + 1) / nr) for x in b), abs=1e-6)
    keyed = spark.range(30_000).selectExpr("id", "cast(id % 1000 as double) as k")
    top = importance.greatest(keyed, "k", "id", 45, small=20)
    assert sorted(r["id"] for r in top.collect()) == sorted(sorted(range(30_000), key=lambda i: (-(i % 1000), i))[:45])
    assert importance.resample(empty(spark), empty(spark), 0.5).count() == 0


def test_licenses(spark, docs):
    mit = licenses.TEXTS["MIT"][1]
    rows = [(1, mit), (2, "Copyright (c) 2020 Someone\n\n" + mit.upper().replace(",", " ")), (3, "text\n  released under the MIT licence!\nmore"), (4, None), (5, ""), (6, mit + " extra"), (6, "licensed under CC-BY NC 4.0")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumnRenamed("text", "license").withColumnRenamed("license", "text")
    for limit in (1000, 2):  # the second goes through the shuffled join
        out = {(r["doc_id"], r["license"], r["n_lines"], r["line_licenses"]) for r in licenses.scan(df, licenses.known(spark), limit=limit).collect()}
        assert {(1, "MIT"), (2, "MIT"), (3, None), (4, None)} <= {(a, b) for a, b, _, _ in out}
        assert (3, None, 1, "MIT") in out and (6, "CC-BY-NC-4.0", 1, "CC-BY-NC-4.0") in out and (6, None, 0, "") in out and len(out) == 7
    assert licenses.scan(empty(spark), licenses.known(spark)).count() == 0


def test_license_files(spark):
    mit, isc = (licenses.TEXTS[n][i] for n, i in (("MIT", 1), ("ISC", 0)))
    folder = Path(licenses.__file__).with_name("license_texts")
    apache = (folder / "Apache-2.0.txt").read_text()
    wrapped = isc.replace("above copyright notice", "above\ncopyright notice")
    bsd = "Redistribution and use" + next(t for t in licenses.TEXTS["BSD-3-Clause"] if "\n1. " in t and "THE COPYRIGHT OWNER" in t).split("Redistribution and use", 1)[1]
    cases = {
        "MIT": "The MIT License (MIT)\n\nCopyright (c) 2020 Someone\nCopyright Another Holder\n\n" + mit,
        "ISC": "ISC License\n\n(c) 2019 Someone\n\n" + wrapped,
        "BSD-3-Clause": "BSD 3-Clause License\n\nCopyright (c) 2020, Someone\nAll rights reserved.\n\n" + textwrap.fill(bsd, 60),
        "Apache-2.0": apache.replace("[yyyy] [name of copyright owner]", "2020 Someone"),
        "MPL-2.0": textwrap.fill((folder / "MPL-2.0.txt").read_text(), 50),
        "GPL-2.0": (folder / "GPL-2.0.txt").read_text(), "GPL-3.0": (folder / "GPL-3.0.txt").read_text(), "LGPL-2.1": (folder / "LGPL-2.1.txt").read_text(),
    }
    lost = isc.replace(" and this permission notice appear in all copies", "").replace("above copyright notice", "above\ncopyright notice")
    df = spark.createDataFrame([*cases.items(), ("none", lost)], "doc_id string, text string")
    for limit in (1000, 2):
        assert {r["doc_id"]: r["license"] for r in licenses.scan(df, licenses.known(spark), limit=limit).collect()} == {n: n for n in cases} | {"none": None}


def test_decontamination(spark):
    rng = random.Random(9)
    items = [(i, prose(rng, 30)) for i in range(5)] + [(90, None), (91, ""), (92, "one two")]
    edit = items[1][1].split()
    for j in (4, 12, 20):
        edit[j] = "replaced"
    edit = edit[:8] + ["inserted"] + edit[8:]
    rows = [(1, prose(rng, 200) + " " + items[0][1] + " " + prose(rng, 100)), (2, prose(rng, 50) + " " + " ".join(edit)), (3, prose(rng, 400)), (4, None), (5, ""), (6, items[0][1].upper()), (6, items[0][1].upper())]
    out = decontaminate.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()
    assert sorted((r["doc_id"], r["item_id"]) for r in out) == [(1, 0), (2, 1), (6, 0), (6, 0)]
    assert next(r for r in out if r["doc_id"] == 1)["first_word"] == 200
    assert decontaminate.contaminated(empty(spark), spark.createDataFrame(items, "item_id long, text string")).count() == 0
    many = decontaminate.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), block_mb=0.0003)
    assert many.count() == 4


def slow_local(a, b, match=1.0, mismatch=-0.5, gap=-0.5):
    h = np.zeros((len(a) + 1, len(b) + 1))
    for i in range(1, len(a) + 1):
        for j in range(1, len(b) + 1):
            h[i, j] = max(0, h[i - 1, j - 1] + (match if a[i - 1] == b[j - 1] else mismatch), h[i - 1, j] + gap, h[i, j - 1] + gap)
    return h.max()


def test_alignment():
    rng = np.random.default_rng(4)
    for _ in range(200):
        a, b = rng.integers(0, 4, rng.integers(1, 9)), rng.integers(0, 4, rng.integers(1, 14))
        assert decontaminate.align(a, b)[0] == pytest.approx(slow_local(a, b))


def test_html(spark):
    page = lambda body: f"<html><head><title>T</title><style>p{{}}</style></head><body>{body}</body></html>"
    text = "A first paragraph that is long enough to be found by its length alone, &amp; more."
    cases = {
        page(f"<nav><a href=x>Home</a></nav><article><h1>Head</h1><p>{text}<p>Short.</article><footer>f</footer>"): f"Head {text.replace('&amp;', '&')} Short.",
        page(f"<div class='menu'><a>Home</a> <a>About</a></div><div id=content><h2>Head</h2><p>{text}</p><p>{text}</p></div><div class='sidebar'>{text}</div><div id=comments><p>{text}</p></div><div class='cookie-notice'>We use cookies on this site, so accept.</div>"): f"Head {text} {text}".replace("&amp;", "&"),
        page("<script>var t='</p>'</script>"): "", "": "", page(f"<nav><ul><li>x<article><p>{text}</article>"): text.replace("&amp;", "&"),
        page(f"<article><p>{text}</p><aside>no</aside><form><p>no</p></form><section class=comments><p>no</p></section></article>"): text.replace("&amp;", "&"),
    }
    for h, want in cases.items():
        assert html_blocks.main_text(h) == want
    df = spark.createDataFrame([(1, "u", None, 3), (None, None, page(f"<article>{text}</article>"), 4)], "page_id long, url string, html string, text int")
    assert {(r["page_id"], r["n_chars"]) for r in html_blocks.extract(df).collect()} == {(1, 0), (None, len(text) - 4)}


def test_html_runs_the_window_on_every_page():
    page = lambda body: f"<html><body>{body}</body></html>"
    text = "A paragraph of a story that is long enough to be found by its length alone, and more."
    cards = "<article><h3><a href=x>A card</a></h3><p>Its teaser.</p></article>"
    out = html_blocks.main_text(page(f"<div id=story><h1>Head</h1><p>{text}</p><p>{text}</p></div><div>{cards * 3}</div>"))
    assert out.startswith(f"Head {text} {text}")
    assert html_blocks.main_text(page(f"<p>{text}</p><nav>n</nav><nav>n</nav><nav>n</nav><h1>Head</h1><article><p>{text}</p><p>{text}</p></article><p>Firm</p>")) == f"Head {text} {text}"


def test_html_keeps_short_blocks_and_named_wrappers():
    page = lambda body: f"<html><body>{body}</body></html>"
    text = "A paragraph of a story that is long enough to be found by its length alone, and more."
    ad = f"<div class=ad>{'<p>Buy this now</p>' * 4}</div>"
    cases = {
        f"<div><h1>A title</h1><p>By X</p><p>1 May</p>{ad}<p>{text}</p></div>": f"A title By X 1 May {text}",
        f"<div><h1>A title</h1><p>{text}</p>{ad}<p>The end.</p></div>": f"A title {text} The end.",
        "<div>" + "<p>今日は天気がいい日ですね。</p>" * 5 + "</div>": " ".join(["今日は天気がいい日ですね。"] * 5),
        f"<div class='layout with-sidebar'><article><p>{text}</p></article><div class=sidebar>{text}</div></div>": text,
        f"<div id='search-page'><article><p>{text}</p></article><div class=sidebar>{text}</div></div><p>Firm</p>": text,
        f"<div id='search-page'><h2>H</h2><p>{text}</p><p>{text}</p><div class=sidebar>{text}</div></div>": f"H {text} {text}",
        f"<form id=all><div><h1>H</h1><p>{text}</p></div></form>": f"H {text}",
        f"<div><h1>H</h1><p>{text}</p></div><div id=comments>{f'<article><p>{text}</p></article>' * 9}</div>": f"H {text}",
        f"<div class=cookie>{text}</div>": "",
    }
    for body, want in cases.items():
        assert html_blocks.main_text(page(body)) == want


def test_html_class_words_and_owner_lines():
    page = lambda body: f"<html><body>{body}</body></html>"
    text = "A paragraph of a story that is long enough to be found by its length alone, and more."
    cases = {
        f"<article><h1>H</h1><section class='legal-analysis'><p>{text}</p></section><div class='search-results-study'><p>Second.</p></div><div class='search-results'>no</div><div class=related-posts>no</div></article>": f"H {text} Second.",
        f"<div><h1>H</h1><section class='legal-analysis'><p>{text}</p></section><p>{text}</p><p>Copyright 2020 Firm</p></div><div class='site-legal'>{text}</div>": f"H {text} {text}",
        f"<div><h1>H</h1><p>{text}</p><p>{text}</p></div><div>© A Firm. All rights reserved.</div>": f"H {text} {text}",
        f"<main><p>{text}</p><p>Copyright 2020 was the matter.</p></main>": f"{text} Copyright 2020 was the matter.",
        f"<main><p title='a > b' data-x=it's>{text}</p></main><!-- open": text,
    }
    for body, want in cases.items():
        assert html_blocks.main_text(page(body)) == want


def test_html_windows_by_brute_force():
    rng = random.Random(12)
    for _ in range(3000):
        weight = [rng.choice((0, 0, 5, 30, 90)) for _ in range(rng.randint(0, 25))]
        window, least = rng.randint(1, 4), rng.choice((30, 60, 100))
        want = [False] * len(weight)
        for i, w in enumerate(weight):
            if w and sum(weight[i : i + window]) >= least:
                lo = hi = i
                while lo and weight[lo - 1]:
                    lo -= 1
                while hi < len(weight) and any(weight[max(i, hi - window + 1) : hi + 1]):
                    hi += 1
                for j in range(lo, hi):
                    want[j] = want[j] or weight[j] > 0
        assert html_blocks.regions(weight, window, least) == want


def test_html_linear_time():
    """What is left open a hundred thousand times over costs no more than one pass each: a megabyte in seconds."""
    n = 100_000
    for body in ("<a " * n, "<svg>" * n, '<a x=">" ' * n, "<i>" * n + "</b>" * n, "<div class=ad>" + "<article>x" * n, "<span>x" * n, "<p a='" * n, "<nav>" * n + "<main>x" * n):
        start = time.process_time()
        html_blocks.main_text(body)
        assert time.process_time() - start < 15


def test_bm25(spark, docs):
    plain = docs.filter("doc_id is not null").dropDuplicates(["doc_id"])
    src = [(k, Counter(bm25.WORDS(t.lower()))) for k, t in rows_of(plain)]
    n, mean = len(src), sum(sum(c.values()) for _, c in src) / len(src)
    df = Counter(w for _, c in src for w in c)

    def score(q, c):
        size = sum(c.values())
        return sum(f * math.log(1 + (n - df[w] + 0.5) / (df[w] + 0.5)) * c[w] * 2.2 / (c[w] + 1.2 * (0.25 + 0.75 * size / mean)) for w, f in q.items() if w in c)

    asked = plain.filter("doc_id % 7 = 0").select(plain["doc_id"].alias("query_id"), "text")
    got = {}
    for r in bm25.search(plain, asked, k=5, block=4, shard_docs=20, query_block=4).collect():
        got.setdefault(r["query_id"], {})[r["rank"]] = r["score"]
    for k, q in src:
        if k % 7 == 0 and q:
            want = sorted((round(score(q, c), 6) for _, c in src if score(q, c) > 0), reverse=True)[:5]
            assert [got[k][i + 1] for i in range(len(got[k]))] == pytest.approx(want, abs=2e-6)
    assert bm25.search(empty(spark), asked).count() == 0


def test_bm25_shares_and_copies(spark):
    """Many shares and shards, a third of all rows exact copies, repeated queries, extra columns: ids and ties as by brute force."""
    rng = random.Random(8)
    hot = prose(rng, 30)
    src = [(i, hot if i % 3 == 0 else prose(rng, rng.randint(1, 60))) for i in range(300)] + [(900, ""), (901, None)]
    df_docs = spark.createDataFrame([(i, t, 1.0, 2) for i, t in src], "doc_id long, text string, score double, rank int")
    asked = [(i, t) for i, t in src if i % 25 == 0] + [(75, hot), (7, "ka mi"), (8, None)]
    df_asked = spark.createDataFrame([(i, t, 5) for i, t in asked], "query_id long, text string, share int")
    bags = [(i, Counter(bm25.WORDS((t or "").lower()))) for i, t in src]
    n, mean = len(bags), sum(sum(c.values()) for _, c in bags) / len(bags)
    df = Counter(w for _, c in bags for w in c)

    def best(q):
        out = []
        for i, c in bags:
            size = sum(c.values())
            v = sum(f * math.log(1 + (n - df[w] + 0.5) / (df[w] + 0.5)) * c[w] * 2.2 / (c[w] + 1.2 * (0.25 + 0.75 * size / mean)) for w, f in q.items() if w in c)
            if v > 0:
                out.append((-round(v, 6), i))
        return [(r + 1, i, -v) for r, (v, i) in enumerate(sorted(out)[:5])]

    want = sorted((k, *x) for k, t in asked for x in best(Counter(bm25.WORDS((t or "").lower()))))
    for kind in ({"shard_docs": 40, "growth": 2, "query_block": 5, "block": 8}, {"shard_terms": 300}, {}):
        got = sorted(tuple(r) for r in bm25.search(df_docs, df_asked, k=5, **kind).collect())
        assert [x[:3] for x in got] == [x[:3] for x in want]
        assert [x[3] for x in got] == pytest.approx([x[3] for x in want], abs=2e-6)


def test_bm25_counts_words_once(spark, monkeypatch):
    """Document frequencies are counted once, however many blocks of queries there are, and in rounds if words are many."""
    rng = random.Random(9)
    docs = spark.createDataFrame([(i, prose(rng, rng.randint(1, 30))) for i in range(120)] + [(900, None)], "doc_id long, text string")
    asked = docs.filter("doc_id % 10 = 0").withColumnRenamed("doc_id", "query_id")
    want = sorted(tuple(r) for r in bm25.search(docs, asked, k=4).collect())
    calls, count = [], bm25._frequencies
    monkeypatch.setattr(bm25, "_frequencies", lambda *a: calls.append(1) or count(*a))
    got = sorted(tuple(r) for r in bm25.search(docs, asked, k=4, query_block=3, words_at_once=5).collect())
    assert got == want and want and len(calls) == 1


def test_queries_with_sql(spark, sf):
    c = duckdb.connect()
    for t in ("documents", "labels", "benchmark", "pages"):
        c.sql(f"create view {t} as select * from '/root/testdata/sf0.001/{t}.parquet'")
    for name, sql in queries.oracle_sql().items():
        df = queries.queries()[name](spark, "/root/testdata/sf0.001")
        rel = c.sql(sql)
        cols = sorted(df.columns)
        assert sorted(repr(tuple(r[x] for x in cols)) for r in df.collect()) == sorted(repr(tuple(r[rel.columns.index(x)] for x in cols)) for r in rel.fetchall())


def test_pipeline(spark):
    import corpus_pipeline

    d = "/root/testdata/sf0.001"
    src = spark.read.parquet(f"{d}/documents.parquet")
    kept = src
    seen = []
    for name, step in corpus_pipeline.STAGES:
        kept = step(spark, kept, d)
        if name != "bpe":
            assert kept.columns == src.columns
            kept = spark.createDataFrame(kept.collect(), src.schema)
            seen.append({r["doc_id"]: r["text"] for r in kept.collect()})
    groups = simhash.near_duplicates(spark.createDataFrame(src.collect(), src.schema)).collect()
    assert set(seen[1]) <= {r["doc_id"] for r in groups} and len(seen[1]) <= len(seen[0])
    want = suffix_dedup.brute_force([(k, t.encode()) for k, t in seen[1].items()])
    for k, t in seen[2].items():
        assert t == want[k][3].decode(errors="ignore")
    final = {r["doc_id"]: r["decoded_sha256"] for r in kept.collect()}
    assert final == {k: hashlib.sha256(t.encode()).hexdigest() for k, t in seen[3].items()}
    assert len(final) > 0.8 * src.count()


def test_pipeline_null_and_repeated_ids(spark):
    import corpus_pipeline

    d = "/root/testdata/sf0.001"
    steps = dict(corpus_pipeline.STAGES)
    src = spark.read.parquet(f"{d}/documents.parquet")
    some = [tuple(r) for r in src.filter("text is not null and length(text) > 300").orderBy("doc_id").limit(40).collect()]
    item = spark.read.parquet(f"{d}/benchmark.parquet").orderBy(F.length("text").desc()).first()["text"]
    at, n = src.columns.index("doc_id"), src.columns.index("n_chars")
    row = lambda key, text: tuple(key if i == at else text if c == "text" else len(text or "") if i == n else some[0][i] for i, c in enumerate(src.columns))
    run = lambda name, rows: sorted(((r["doc_id"] is None, r["doc_id"], r["text"]) for r in steps[name](spark, spark.createDataFrame(rows, src.schema), d).collect()), key=repr)
    texts = [r[src.columns.index("text")] for r in some]

    out = run("language_id", [*some, row(None, texts[0]), row(some[1][at], texts[2]), row(some[1][at], "12 34"), row(None, None)])
    assert (True, None, texts[0]) in out and (False, some[1][at], texts[2]) in out
    assert not [x for x in out if x[2] in ("12 34", None)]

    out = run("simhash_near_dedup", [row(5, texts[0]), row(5, texts[0]), row(5, texts[0]), row(7, texts[0]), row(None, texts[0]), row(None, texts[7]), row(None, texts[7])])
    assert out == sorted([(False, 5, texts[0]), (True, None, texts[7])], key=repr)

    a, b, c = ("".join(random.Random(i).choices("abcdefgh ", k=120)).strip() + "." for i in range(3))
    out = run("suffix_dedup", [row(1, a), row(2, b), row(2, "x" * 9 + a), row(2, c), row(None, b + "tail"), row(None, b)])
    assert out == sorted([(False, 1, a), (False, 2, b), (False, 2, "x" * 9), (False, 2, c), (True, None, "tail")], key=repr)
    assert run("suffix_dedup", [row(3, a), row(3, a)]) == [(False, 3, a)]

    out = run("decontamination", [row(4, item), row(4, a), row(None, item), row(None, c)])
    assert out == sorted([(False, 4, a), (True, None, c)], key=repr)

    rows = steps["bpe"](spark, spark.createDataFrame([row(4, a), row(4, a), row(None, c)], src.schema), d).collect()
    assert sorted((r["doc_id"] is None, r["decoded_sha256"]) for r in rows) == sorted((k is None, hashlib.sha256(t.encode()).hexdigest()) for k, t in ((4, a), (4, a), (None, c)))
