"""Learned and searched results against slow versions written from the definitions, on fixtures with nulls, ties, repeated rows and clashing columns."""

import math
import random
import re
import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from strata_engine.llm import bm25, decontaminate, importance, langid, toxicity

WORDS = [a + b for a in ("ka", "lo", "mi", "ter", "un") for b in ("ra", "vel", "ship", "do", "ing", "ex", "pol")]
M64 = (1 << 64) - 1


def prose(rng, n, words=WORDS):
    return " ".join(rng.choice(words) for _ in range(n))


def mix(x):
    for m in (0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53):
        x = (x ^ (x >> 33)) * m & M64
    return x ^ (x >> 33)


def slow_features(text, bits, skips):
    h = [zlib.crc32(w.encode()) for w in re.findall(r"\w+", text.lower())]
    out = {mix(x + 1) >> (65 - bits) for x in h}
    for gap in range(1, skips + 2):
        out |= {(mix((a * 0x9E3779B97F4A7C15 + b * 0xC2B2AE3D27D4EB4F + 1 + gap) & M64) >> (65 - bits)) + (1 << (bits - 1)) for a, b in zip(h, h[gap:], strict=False)}
    return sorted(out)


def slow_ftrl(rows, alpha, beta, l1, pair_l1, l2, epochs, bits):
    z, n, z0, n0 = defaultdict(float), defaultdict(float), 0.0, 0.0
    cut = lambda i: pair_l1 if i >= 1 << (bits - 1) else l1
    weight = lambda i: 0.0 if abs(z[i]) <= cut(i) else -(z[i] - math.copysign(cut(i), z[i])) / ((beta + math.sqrt(n[i])) / alpha + l2)
    for _ in range(epochs):
        for f, y in rows:
            w = {i: weight(i) for i in f}
            b = -z0 / ((beta + math.sqrt(n0)) / alpha)
            g = 1 / (1 + math.exp(-sum(w.values()) - b)) - y
            for i in f:
                z[i] += g - (math.sqrt(n[i] + g * g) - math.sqrt(n[i])) / alpha * w[i]
                n[i] += g * g
            z0 += g - (math.sqrt(n0 + g * g) - math.sqrt(n0)) / alpha * b
            n0 += g * g
    return {i: weight(i) for i in list(z) if weight(i)}, -z0 / ((beta + math.sqrt(n0)) / alpha)


def test_toxicity_learns_as_the_slow_version(spark):
    rng = random.Random(3)
    rows = [(i, prose(rng, rng.randint(0, 40)) + (" vile scum" if i % 4 == 0 else ""), int(i % 4 == 0), 1.0, 2) for i in range(120)]
    rows += [rows[5], rows[5], (500, None, 0, 1.0, 2), (501, "", 1, 1.0, 2), (502, "x", None, 1.0, 2), (503, prose(rng, 5_000), 0, 1.0, 2)]
    df = spark.createDataFrame(rows, "doc_id long, text string, toxic int, score double, predicted int")
    kind = dict(bits=16, skips=1, alpha=1.0, beta=1.0, l1=0.05, pair_l1=0.3, l2=0.01, epochs=2)
    at, w, b = toxicity.fit(df, **kind)
    order = {r["t"]: r["h"] for r in df.select(F.coalesce("text", F.lit("")).alias("t")).select("t", F.xxhash64("t").alias("h")).collect()}
    known = sorted(((order[t or ""], y, t or "") for _, t, y, _, _ in rows if y is not None), key=lambda x: x[:2])
    weights, b0 = slow_ftrl([(slow_features(t, 16, 1), y) for _, y, t in known], kind["alpha"], kind["beta"], kind["l1"], kind["pair_l1"], kind["l2"], kind["epochs"], 16)
    assert b == pytest.approx(b0) and sorted(at.tolist()) == sorted(weights)
    assert dict(zip(at.tolist(), w.tolist(), strict=True)) == pytest.approx(weights)
    got = toxicity.score(df, (at, w, b), bits=16, skips=1).collect()
    assert len(got) == len(rows)
    want = {i: 1 / (1 + math.exp(-sum(weights.get(f, 0.0) for f in slow_features(t or "", 16, 1)) - b0)) for i, t, _, _, _ in rows}
    assert all(r["score"] == pytest.approx(want[r["doc_id"]]) and r["predicted"] == int(r["score"] >= 0.5) for r in got)


def slow_vector(text, n, dims, seed):
    """A text's bundle: letters only, one gap for whatever is between, n-grams of rotated letter vectors."""
    flat = "".join(c.lower() if c.isalpha() and len(c.lower()) == 1 else c if c.isalpha() else " " for c in text)
    if not flat.strip():
        return None
    flat = " " + re.sub(" +", " ", flat).strip() + " "
    out = np.zeros(dims)
    for i in range(len(flat) - n + 1):
        bound = np.ones(dims)
        for place, c in enumerate(reversed(flat[i : i + n])):
            bound *= np.roll(np.random.default_rng([seed, ord(c)]).integers(0, 2, dims, dtype=np.int8) * 2 - 1, place)
        out += bound
    return out


def test_language_id_by_brute_force(spark):
    rng = random.Random(4)
    tongues = {"aa": ["gor", "blik", "tang", "rosk"], "bb": ["élune", "maïa", "ouisse"], "cc": ["漢字", "仮名", "語"]}
    rows = [(i, prose(rng, rng.randint(1, 12), tongues[lang]), lang, 0.5, "x") for i, lang in enumerate(["aa", "bb", "cc"] * 5)]
    rows += [rows[0], rows[0], (90, None, "aa", 0.5, "x"), (91, "", "bb", 0.5, "x"), (92, "12 3!", "cc", 0.5, "x"), (93, "Élune-MAÏA  gor", None, 0.5, "x"), (None, "a", None, 0.5, "x"), (94, prose(rng, 2000, tongues["bb"]), "bb", 0.5, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, score double, lang_pred string")
    langs, protos = langid.fit(df, dims=64)
    vec = {t: slow_vector(t, 3, 64, 7) for t in {r[1] or "" for r in rows}}
    unit = lambda v: v / np.linalg.norm(v)
    want = {lang: unit(sum(unit(vec[t]) for _, t, one, _, _ in rows if one == lang and t and vec[t] is not None)) for lang in tongues}
    assert langs == sorted(want) and all(np.allclose(protos[i], want[lang], atol=1e-5) for i, lang in enumerate(langs))
    got = langid.predict(df, (langs, protos), dims=64).collect()
    assert len(got) == len(rows)
    text = {r[0]: r[1] or "" for r in rows}
    for r in got:
        v = vec[text[r["doc_id"]]]
        cos = None if v is None else [float(unit(v) @ want[lang]) for lang in langs]
        assert r["lang_pred"] == ("und" if cos is None else langs[int(np.argmax(cos))])
        assert r["score"] == pytest.approx(0 if cos is None else min(1, max(0, max(cos))), abs=1e-5)
    same = langid.fit(spark.createDataFrame([(1, "gor", "zz"), (2, "gor", "yy")], "doc_id long, text string, lang string"), dims=64)
    assert langid.predict(df.filter("doc_id = 0"), same, dims=64).first()["lang_pred"] == "yy"  # a tie


def test_resampling_by_brute_force(spark):
    rng = random.Random(5)
    rows = [(i, prose(rng, rng.randint(0, 30), WORDS[: 10 + i % 25]), 1.0) for i in range(200)] + [(300, None, 1.0), (301, "", 1.0), (7, "ka ra", 1.0), (None, "mi do", 1.0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, log_weight double")
    target = df.filter("doc_id % 3 = 0")
    got = importance.resample(df, target, 0.25, buckets=500).collect()
    n = lambda some: np.bincount(np.concatenate([importance.buckets_of(t or "", 500) for t in some]), minlength=500) + 1.0
    t, raw = n([x for i, x, _ in rows if i is not None and i % 3 == 0]), n([x for _, x, _ in rows])
    ratio = np.log(t / t.sum()) - np.log(raw / raw.sum())
    u = {r["doc_id"]: (r["h"] % (1 << 52) + 0.5) / (1 << 52) for r in df.select("doc_id", F.xxhash64(F.lit(11), "doc_id").alias("h")).collect()}
    keys = sorted(((float(ratio[importance.buckets_of(x or "", 500)].sum()) - math.log(-math.log(u[i])), -1 if i is None else i) for i, x, _ in rows), key=lambda k: (-k[0], k[1]))
    assert len(got) == round(0.25 * len(rows))
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"]) for r in got) == sorted(i for _, i in keys[: len(got)])


def slow_local(a, b):
    h = np.zeros((len(a) + 1, len(b) + 1))
    for i in range(1, len(a) + 1):
        for j in range(1, len(b) + 1):
            h[i, j] = max(0, h[i - 1, j - 1] + (1 if a[i - 1] == b[j - 1] else -0.5), h[i - 1, j] - 0.5, h[i, j - 1] - 0.5)
    return h.max()


def test_decontamination_finds_what_all_pairs_align(spark):
    """Every document against every item by full alignment: seeds lose no copy with a tenth of its words edited, and few with a fifth."""
    rng = random.Random(6)
    many = [f"{a}{b}" for a in WORDS for b in ("", "s", "ed", "ly", "ous", "al")]
    items = [(i, prose(rng, rng.randint(8, 25), many)) for i in range(8)] + [(50, None), (51, "two words")]
    rows = []
    for d in range(80):
        words = prose(rng, rng.randint(20, 60), many).split()
        if d % 2:
            one = items[d % 8][1].split()
            for k in range(len(one)):
                if rng.random() < (0.1 if d % 4 == 1 else 0.2):
                    one[k] = rng.choice(many)
            at = rng.randint(0, len(words))
            words[at:at] = one
        rows.append((d, " ".join(words), 9))
    rows += [(200, None, 9), (201, "", 9), rows[1], rows[1], (None, items[0][1], 9)]
    got = decontaminate.contaminated(spark.createDataFrame(rows, "doc_id long, text string, item_id int"), spark.createDataFrame(items, "item_id long, text string")).collect()
    found = {(r["doc_id"], r["item_id"]): r["similarity"] for r in got}
    whole = {(d, i): slow_local(t.split(), (x or "").split()) / len(t.split()) for d, x, _ in rows for i, t in items[:8] if t}
    want = {k: v for k, v in whole.items() if v >= 0.5}
    assert set(found) <= set(want) and all(found[k] <= want[k] + 1e-9 for k in found)
    sure = {k for k, v in want.items() if v >= 0.8}
    assert sure <= set(found) and len(set(found)) >= 0.9 * len(want) and len(want) >= 35
    assert sum(r["doc_id"] == 1 for r in got) == 3 * sum(k[0] == 1 for k in found)


def slow_pivots(lists, k, block):
    """Scores of the ``k`` best documents by pivots over posting cursors, one document at a time, and how many pivots that took.

    ``lists`` has (documents, contributions) of each word of a query, documents ascending.
    """
    end = 1 << 60
    lists = [(d, p, max(p), [(d[min(s + block, len(d)) - 1], max(p[s : s + block])) for s in range(0, len(d), block)]) for d, p in lists]
    place, best, pivots = [0] * len(lists), [], 0
    at = lambda c: lists[c][0][place[c]] if place[c] < len(lists[c][0]) else end
    while True:
        order, reach, pivot = sorted((at(c), c) for c in range(len(lists))), 0.0, end
        pivots += 1
        least = best[-1] if len(best) == k else 0.0
        for d, c in order:
            reach += lists[c][2]
            if reach > least:
                pivot = d
                break
        if pivot == end:
            return best, pivots
        ahead = [c for d, c in order if d <= pivot]
        near = [next((x for x in lists[c][3] if x[0] >= pivot), (end, 0.0)) for c in ahead]
        if sum(x[1] for x in near) <= least:  # no document up to the next end of a block or cursor can be among the best
            to = min([x[0] + 1 for x in near] + [d for d, _ in order if d > pivot])
        elif order[0][0] == pivot:
            best = sorted([*best, sum(lists[c][1][place[c]] for c in ahead)], reverse=True)[:k]
            to = pivot + 1
        else:
            to = pivot
        for c in ahead:
            while at(c) < to:
                place[c] += 1


def test_blocks_by_bound_give_what_pivots_give():
    rng = random.Random(31)
    docs = [(i, *bm25.terms_of(prose(rng, rng.randint(1, 40), WORDS[: rng.choice((5, 20, 35))]))) for i in range(300)]
    rows = [(i, t.tobytes(), f.tobytes(), int(f.sum())) for i, t, f in docs]
    asked = bm25.Asked([(r[0], r[0], r[1], r[2]) for r in rows[::20]])
    df = np.zeros(len(asked.vocab), dtype=np.int64)
    for _, t, _ in docs:
        df[bm25.places(t, asked.vocab)[1]] += 1
    shard = bm25.Shard(rows, asked.vocab, df, len(rows), sum(r[3] for r in rows) / len(rows), 5, 1.2, 0.75, 8, most_dense=12)
    doc = np.repeat(np.arange(shard.n), np.diff(shard.first))
    got = dict(shard.top(asked, 0, len(asked.row), np.zeros(len(asked.row)), 5))
    for i in range(len(asked.row)):
        lists = []
        for word, weight in zip(asked.at[asked.first[i] : asked.first[i + 1]], asked.weight[asked.first[i] : asked.first[i + 1]], strict=True):
            mine = np.flatnonzero(shard.at == word)
            lists.append((doc[mine].tolist(), (shard.part[mine] * weight).tolist()))
        want, pivots = slow_pivots(lists, 5, 4)
        once = {shard.ids[d][0] for d in range(shard.n)}  # equal documents are scored once
        scores = sorted((v for v, x in got[i] if x in once), reverse=True)[:5]
        assert scores == pytest.approx(want, abs=1e-6) and pivots > 0


def test_places_are_those_of_a_search():
    rng = np.random.default_rng(5)
    low, high = np.iinfo(np.int64).min, np.iinfo(np.int64).max
    spread = np.unique(rng.integers(low, high, 3000))
    close = np.unique(np.concatenate((np.arange(700), [low, -1, high - 1, high])))  # hashes aren't like that
    for vocab in (spread, close, spread[:1], np.array([high]), spread[:0]):
        words = np.concatenate((vocab, vocab + 1, vocab - 1, rng.integers(low, high, 500), [low, 0, high]))
        known, at = bm25.places(words, vocab)
        assert known.tolist() == np.isin(words, vocab).tolist()
        assert (vocab[at] == words[known]).all()


def test_scores_whatever_counts_as_frequent(monkeypatch):
    """Words as columns of a product or as postings: the same documents and scores."""
    rng = random.Random(32)
    docs = [(i, *bm25.terms_of(prose(rng, rng.randint(1, 90), WORDS[: rng.choice((5, 20, 35))]))) for i in range(260)]
    rows = [(i, t.tobytes(), f.tobytes(), int(f.sum())) for i, t, f in docs]
    asked = bm25.Asked([(r[0], r[0], r[1], r[2]) for r in rows[::9]])
    df = np.ones(len(asked.vocab), dtype=np.int64) * 7
    got = []
    for posting in (0, 1, 350, 10**9):
        monkeypatch.setattr(bm25, "POSTING", posting)
        shard = bm25.Shard(rows, asked.vocab, df, len(rows), 40.0, 5, 1.2, 0.75, 8)
        found = dict(shard.top(asked, 0, len(asked.row), np.zeros(len(asked.row)), 5))
        got.append({i: sorted(((-v, x) for v, x in m), key=lambda y: (round(y[0], 6), y[1]))[:5] for i, m in found.items()})
    assert len(got[0]) == len(asked.row) and all(g == got[0] for g in got)
