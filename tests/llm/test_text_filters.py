from __future__ import annotations

import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from ldpspark.llm import decontamination as dc
from ldpspark.llm import exact_dedup as ed
from ldpspark.llm import quality as q
from ldpspark.llm import substring_dedup as sd
from ldpspark.llm import url_filter as uf

from .helpers import SF, classes, crowded, docs, lower, words


# --- exact dedup

ROWS = [(5, "a  b"), (3, "a\tb"), (3, "a\tb"), (9, "a b "), (4, None), (8, ""), (None, "a b"), (1, "A b"), (6, "\u00a0"), (None, "z"), (None, "z")]


def brute_groups(rows):
    norm = [(i, re.sub(r"[\x20\x09-\x0d]+", " ", t or "")) for i, t in rows]
    out, seen = [], set()
    for i, t in norm:
        ids = [j for j, s in norm if s == t]
        keep = min((j for j in ids if j is not None), default=None)
        kept = i == keep and (keep, t) not in seen
        seen |= {(keep, t)} if kept else set()
        out.append((i, keep, len(ids), kept, hashlib.sha256(t.encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("digest", [ed.hash128, lambda t: F.unhex(F.substring(F.md5(t), 1, 2)), lambda t: F.unhex(F.lit("00"))])
def test_exact_groups_with_and_without_collisions(spark, digest):
    got = ed.exact_groups(crowded(docs(spark, ROWS)), digest).collect()
    assert sorted((tuple(r) for r in got), key=str) == brute_groups(ROWS)


def test_exact_groups_of_nothing(spark):
    assert ed.exact_groups(docs(spark, [])).count() == 0


# --- decontamination

def tokens(text):
    return re.findall(r"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", lower(text or ""))


def brute_hits(rows, items, k=13):
    out = []
    for i, t in rows:
        w, hit, found = tokens(t), set(), set()
        for name, text in items:
            v = tokens(text)
            n = min(k, len(v))
            if n:
                grams = {tuple(v[a : a + n]) for a in range(len(v) - n + 1)}
                for p in range(len(w) - n + 1):
                    if tuple(w[p : p + n]) in grams:
                        hit |= set(range(p, p + n))
                        found.add(str(name))
        out.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=str)


def test_contamination_equals_brute_force(spark):
    rng = random.Random(2)
    items = [(n, " ".join(words(rng.choice([3, 12, 13, 14, 30]), 50 + n, 60))) for n in range(25)] + [(100, "one"), (101, None), (102, "..."), (103, "é Z-9"), (103, "second text of an item")]
    rows = []
    for n in range(60):
        w = words(rng.choice([0, 5, 40, 200]), 900 + n, 60)
        for _ in range(rng.randrange(3)):
            v = tokens(rng.choice(items)[1])
            a = rng.randrange(len(v) + 1)
            w[len(w) // 2 : len(w) // 2] = v[a:] if rng.random() < 0.4 else v
        rows.append((n, "; ".join(w).title()))
    rows += [(None, "One one"), (70, None), (70, items[3][1]), (71, ""), (72, "x " * 3000 + items[4][1])]
    table = spark.createDataFrame(items, "item_id long, text string")
    got = dc.digested(dc.contamination(crowded(docs(spark, rows)), table)).collect()
    assert sorted((tuple(r) for r in got), key=str) == brute_hits(rows, items)
    kept = dc.decontaminated(docs(spark, rows), table)
    clean = [x for x in brute_hits(rows, items) if not x[-1]]
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == sorted(str(x[0]) for x in clean)
    assert dc.contamination(docs(spark, rows[:3]), spark.createDataFrame([], "item_id long, text string")).where("contaminated").count() == 0
    assert dc.contamination(docs(spark, []), table).count() == 0


def test_proximity_finds_a_torn_phrase(spark):
    item = [f"rare{i}" for i in range(13)]
    torn = item[:7] + ["filler"] * 3 + item[7:]
    table = spark.createDataFrame([(1, " ".join(item))], "item_id long, text string")
    _, _, anchors, index = dc.build_index(docs(spark, [(1, " ".join(torn)), (2, "rare0 x"), (3, " ".join(item))]), table)
    near = {r["doc_id"]: r["off_by"] for r in dc.proximity_matches(index, anchors).collect()}
    assert near[3] == 0 and near.get(1, 0) in (0, 3) and 2 not in near


# --- quality

def test_network_separates_and_reads_all_bytes():
    rng = random.Random(4)
    good = [" ".join(words(rng.randrange(5, 300), i)) for i in range(120)]
    bad = [" ".join(w.upper() + "!!" for w in words(rng.randrange(5, 300), 500 + i)) for i in range(120)]
    net = q.fit(good[:80] + bad[:80], [1] * 80 + [0] * 80)
    p = q.predict(net, pa.array(good[80:] + bad[80:]))
    assert ((p >= 0.5) == ([True] * 40 + [False] * 40)).mean() >= 0.95
    tail = good[0] * 40 + " " + bad[0] * 40
    assert q.predict(net, pa.array([good[0] * 40]))[0] > q.predict(net, pa.array([tail]))[0]
    assert np.isfinite(q.predict(net, pa.array(["", None, "x", "é" * 5000]))).all()
    alone = q.predict(net, pa.array([good[5]]))[0]
    assert abs(alone - q.predict(net, pa.array([bad[3], good[5], ""]))[1]) < 1e-5


def test_gradient_is_the_derivative():
    net = q.Network.fresh(3)
    raw, offsets = q.texts_of(pa.array(["some words here " * 200, "short", "OTHER!! " * 90]))
    y, w = np.array([1, 0, 0], np.float32), np.ones(3, np.float32)

    def loss():
        z = q._forward(net, raw, offsets)[0]
        return float((np.log1p(np.exp(-np.abs(z))) + np.maximum(z, 0) - y * z).mean())

    g = q._gradients(net, raw, offsets, y, w)
    for part, d in ((net.mix, g[3]), (net.filters, g[1]), (net.vectors, g[0])):
        at = np.unravel_index(np.abs(d).argmax(), d.shape)
        step = 1e-2
        part[at] += step
        up = loss()
        part[at] -= 2 * step
        down = loss()
        part[at] += step
        assert abs((up - down) / (2 * step) - d[at]) < 0.15 * abs(d[at]) + 1e-3


def test_scores_on_tables(spark):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    got = {r["doc_id"]: r for r in q.quality_scores(d, labels).collect()}
    assert len(got) == d.count()
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1) and r["predicted"] == (r["score"] >= 0.5) for i, r in got.items())
    seen = [(got[r["doc_id"]]["predicted"], r["quality"]) for r in labels.collect() if got[r["doc_id"]]["held_out"]]
    good = [p for p, y in seen if y == 1]
    assert sum(p == y for p, y in seen) / len(seen) > 0.85 and sum(good) / len(good) > 0.9
    odd = docs(spark, [(None, None), (1, ""), (1, "x"), (2, "y" * 300_000)])
    assert q.quality_scores(crowded(odd), labels).count() == 4
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {r["score"] for r in q.quality_scores(odd, none).collect()} == {1.0}
    assert q.good_documents(docs(spark, []), labels).count() == 0


# --- substring dedup

def test_banding_is_tuned_for_recall():
    bands, rows = sd.tuned(0.75, 0.99)
    assert 1 - (1 - 0.75**rows) ** bands >= 0.99
    with pytest.raises(ValueError):
        sd.tuned(0.01, 0.999, most=4)


def test_repeated_passages_and_near_paragraphs(spark):
    passage = ". ".join(" ".join(words(10, 40 + i)) for i in range(6)) + "."
    para = words(80, 7)
    near = list(para)
    near[40] = "changed"
    rows = [
        (10, f"Own start here. {passage} More {' '.join(words(20, 1))}"),
        (4, f"{' '.join(words(30, 2))}.\n{passage}"),
        (20, " ".join(words(200, 3, 10**6))),
        (30, " ".join(para)), (31, "x y z\n" + " ".join(near)),
        (40, None), (41, ""), (None, passage), (42, " ".join(words(49, 5))), (43, " ".join(words(49, 5))),
    ]
    got = {r["doc_id"]: r for r in sd.repeated_spans(crowded(docs(spark, rows))).collect()}
    assert set(got) == {10, 31}
    assert got[10]["keep_doc_ids"] == [4] and got[10]["start"] == 3 and got[10]["n_words"] >= 50
    assert got[31]["keep_doc_ids"] == [30] and (got[31]["start"], got[31]["end"]) == (3, 83)
    cut = {r["doc_id"]: r["text"] for r in sd.without_spans(docs(spark, rows), sd.repeated_spans(docs(spark, rows))).collect()}
    assert cut[4] == dict(rows)[4] and cut[31] == "x y z\n" and cut[10].startswith("Own start here. ")
    assert sd.repeated_spans(docs(spark, [])).count() == 0


def test_repeats_of_the_given_table_are_found(spark):
    rows = spark.read.parquet(f"{SF}/documents.parquet").collect()
    first, want = {}, set()
    for r in sorted(rows, key=lambda r: r["doc_id"]):
        w = [x for x in re.split(r"[\x20\x09-\x0d]+", lower(r["text"])) if x]
        for a in range(len(w) - 49):
            g = tuple(w[a : a + 50])
            if first.setdefault(g, r["doc_id"]) != r["doc_id"]:
                want.add(r["doc_id"])
    got = {r["doc_id"] for r in sd.repeated_spans(spark.read.parquet(f"{SF}/documents.parquet")).collect()}
    assert len(want - got) <= 0.05 * len(want)


def brute_words(rows, n=50):
    """{id: numbers of the words in a window of n words that stands at an earlier place}."""
    texts = [(i, [w for w in re.split(r"[\x20\x09-\x0d]+", lower(t or "")) if w]) for i, t in sorted(rows)]
    first, out = {}, {}
    for i, w in texts:
        for a in range(len(w) - n + 1):
            if first.setdefault(tuple(w[a : a + n]), (i, a)) != (i, a):
                out.setdefault(i, set()).update(range(a, a + n))
    return out


def test_every_repeat_of_fifty_words_is_found_to_the_word(spark):
    rng, rows = random.Random(6), []
    pool = [words(n, 300 + n, 10**6) for n in (50, 51, 52, 60, 75, 120, 300)]
    pool += [words(3, 9) * 60, ["la"] * 170, words(10, 10) * 11]
    for i in range(60):
        out = words(rng.randrange(5, 40), 500 + i, 10**6)
        for _ in range(3):
            p = rng.choice(pool)
            a = rng.randrange(0, max(1, len(p) - 55))
            out[-1] += ","
            out += p[a : a + rng.choice((49, 50, 51, 70, 400))] + words(rng.randrange(1, 30), 900 + rng.randrange(10**6), 10**6)
        rows.append((i, " ".join(out)))
    got = {}
    for r in sd.passages(docs(spark, rows).select("doc_id", "text"), 50).collect():
        got.setdefault(r["doc_id"], set()).update(range(r["start"], r["end"]))
    assert got == brute_words(rows)
    found = {}
    for r in sd.repeated_spans(docs(spark, rows)).collect():
        found.setdefault(r["doc_id"], set()).update(range(r["start"], r["end"]))
    assert all(v <= found.get(i, set()) for i, v in got.items())


def varied(base, places, tag):
    out = list(base)
    for k in places:
        out[k] = f"{tag}x{k}"
    return out


@pytest.mark.parametrize("small, block", [(16, 256), (8, 16)])
def test_linked_pairs_among_unlinked_variants_of_one_template(spark, monkeypatch, small, block):
    monkeypatch.setattr(sd, "SMALL", small, raising=False)
    monkeypatch.setattr(sd, "BLOCK", block, raising=False)
    rng, base, rows = random.Random(4), words(400, 12, 10**6), []
    for f in range(120):
        own = varied(base, rng.sample(range(400), 8), f"a{f}")
        rows += [(2 * f, own), (2 * f + 1, varied(own, rng.sample(range(400), 7), f"b{f}"))]
    want = classes([(i, " ".join(w)) for i, w in rows])
    spans = sd.repeated_spans(docs(spark, [(i, " ".join(w)) for i, w in rows])).collect()
    whole = {r["doc_id"] for r in spans if (r["start"], r["end"]) == (0, 400)}
    linked = {i for i, c in want.items() if i != c}
    assert len(linked) >= 115 and whole <= linked and len(linked - whole) <= 1


# --- URL filter

def test_url_parts_and_rules(spark):
    urls = [None, "", "no scheme", "http://A.com", "http://a.com/x?y#z", "http://WWW.Example.com/en/1", "http://m.example.com/en/1", "x://example.com/EN/", "http://b.net/es/q?r", "http://net/fr/", "http://b.network/fr/", "http://h.net?p=/es/", "a://b://c/d", "http://É.com/é"]
    pages = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id long, url string, key string")
    none = spark.createDataFrame([], "page_id long, bad int")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in uf.judged(pages, none).collect()}
    assert got == {
        0: ("", "", None, "allow"), 1: ("", "", None, "allow"), 2: ("", "", None, "allow"), 3: ("a.com", "", None, "allow"), 4: ("a.com", "/x", "com/", "allow"),
        5: ("www.example.com", "/en/1", "www.example.com/en/", "allow"), 6: ("m.example.com", "/en/1", "example.com/en/", "block"), 7: ("example.com", "/EN/", "com/", "allow"),
        8: ("b.net", "/es/q", "net/es/", "block"), 9: ("net", "/fr/", "net/fr/", "block"), 10: ("b.network", "/fr/", None, "allow"), 11: ("h.net", "", None, "allow"),
        12: ("b:", "//c/d", None, "allow"), 13: ("É.com", "/é", "com/", "allow"),
    }


def test_reputation_needs_evidence(spark):
    rows = [(i, "http://bad.org/x") for i in range(60)] + [(100 + i, "http://good.org/x") for i in range(60)] + [(200, "http://new.org/x"), (201, "http://one.org/x")]
    pages = spark.createDataFrame(rows, "page_id long, url string")
    votes = spark.createDataFrame([(i, 1) for i in range(60)] + [(100 + i, 0) for i in range(60)] + [(201, 1), (999, 1), (None, 1), (5, None)], "page_id long, bad int")
    got = {r["host"]: r for r in uf.judged(pages, votes).collect()}
    assert got["bad.org"]["verdict"] == "block" and got["good.org"]["verdict"] == "allow"
    assert got["new.org"]["verdict"] == "allow"
    rep = {r["host"]: r for r in uf.host_reputation(pages, votes).collect()}
    assert rep["good.org"]["mean"] < rep["new.org"]["mean"] < rep["one.org"]["mean"] < rep["bad.org"]["mean"]
    assert uf.judged(spark.createDataFrame([], "page_id long, url string"), votes).count() == 0


def test_beta_tail_and_public_suffixes(spark):
    a, b = np.array([1.0, 2.0, 0.5, 3.0, 40.0, 0.01]), np.array([1.0, 1.0, 0.5, 1.0, 7.0, 12.0])
    x = 0.35
    got = uf.beta_cdf(a, b, x)
    assert np.allclose(got[[0, 1, 3]], [x, x**2, x**3]) and abs(got[2] - 2 / np.pi * np.arcsin(np.sqrt(x))) < 1e-12
    grid = (np.arange(400_000) + 0.5) / 400_000
    density = lambda p, q: grid ** (p - 1) * (1 - grid) ** (q - 1)
    assert abs(got[4] - density(40, 7)[grid <= x].sum() / density(40, 7).sum()) < 1e-9 and 0.9 < got[5] < 1
    assert len(uf.beta_cdf(np.zeros(0), np.zeros(0), x)) == 0
    hosts = spark.createDataFrame([(h,) for h in ("a.co.uk", "w.b.co.uk", "b.co.uk", "x.y.com", "com", "", "co.uk")], "host string")
    domain, suffix = uf.registered(hosts["host"])
    found = {r["host"]: (r["d"], r["s"]) for r in hosts.select("host", domain.alias("d"), suffix.alias("s")).collect()}
    assert found["a.co.uk"] == ("a.co.uk", "co.uk") and found["w.b.co.uk"] == found["b.co.uk"] == ("b.co.uk", "co.uk")
    assert found["x.y.com"] == ("y.com", "com") and found["com"] == ("com", "com") and found[""] == ("", "") and found["co.uk"] == ("co.uk", "co.uk")


def test_every_repeat_of_the_given_tables_is_found(spark):
    """All runs of 50 words that stand at an earlier place they don't overlap, by brute force over sf0.01; what is found beyond them lies in near copies of lines, or in loops."""
    table = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    rows = sorted((r["doc_id"], [w for w in re.split(r"[\x20\x09-\x0d]+", lower(r["text"] or "")) if w]) for r in table.collect())
    first, repeated, looped = {}, {}, {}
    for i, ws in rows:
        for p in range(len(ws) - 49):
            j, q = first.setdefault(tuple(ws[p : p + 50]), (i, p))
            for at, so in ((repeated, j != i or p - q >= 50), (looped, (j, q) != (i, p))):
                if so:
                    at.setdefault(i, set()).update(range(p, p + 50))
    found = {}
    for r in sd.repeated_spans(table).collect():
        found.setdefault(r["doc_id"], set()).update(range(r["start"], r["end"]))
    assert all(words <= found.get(i, set()) for i, words in repeated.items()) and len(repeated) > 100
    lines = {r["doc_id"]: max(len(x.split()) for x in (r["text"] or "").split("\n")) for r in table.collect()}
    beyond = {i for i in found if found[i] - looped.get(i, set())}
    assert all(lines[i] >= 50 for i in beyond) and len(beyond) < 0.05 * len(rows)
