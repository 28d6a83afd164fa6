from __future__ import annotations

import gzip
import hashlib
import random
import re
import time
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from ldpspark.llm import chat_format as cf
from ldpspark.llm import mixing as mx
from ldpspark.llm import sharding as sh
from ldpspark.llm import warc
from ldpspark.llm.components import components
from ldpspark.llm.merging import id_filter, may_hold
from ldpspark.llm.staging import gathered, stage

from .helpers import crowded, docs, words


# --- chat formatting

@settings(max_examples=200, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "<x>\n", ""]), st.text(alphabet="\\<>/turn #\n[]a", max_size=30)), max_size=6))
def test_written_turns_read_back(turns):
    text = "".join(cf.write_turn(r, t)[0] for r, t in turns)
    assert cf.read_turns(text) == turns


def conversations(spark, rows):
    return spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, part int")


CONV = [
    (1, 0, "system", "be <kind>"), (1, 1, "user", "hi"), (1, 2, "assistant", "</turn>\n### Assistant: \\"), (1, 3, "user", None), (1, 4, "assistant", "é</turn>"),
    (2, 0, "user", "x"), (None, 0, "assistant", "lost"), (3, None, "assistant", ""), (3, 0, None, "y"), (4, 0, "assistant", "b"), (4, 0, "assistant", "a"), (4, 0, "assistant", "a"),
]


@pytest.mark.parametrize("piece", [1 << 22, 1])
def test_digests_are_of_what_was_said(spark, piece):
    written = cf.formatted(conversations(spark, CONV), piece_chars=piece)
    got = {r["conv_id"]: r for r in cf.digests(written).collect()}
    assert set(got) == {1, 2, 3, 4, None}
    for c in got:
        turns = sorted(((-1 if t is None else t), r or "", x or "") for i, t, r, x in CONV if i == c)
        said = [x for _, r, x in turns if r == "assistant"]
        assert got[c]["n_turns"] == len(turns) and got[c]["n_examples"] == len(said)
        assert got[c]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{x}\n" for _, r, x in turns).encode()).hexdigest()
        assert got[c]["loss_chars"] == len("".join(said)) and got[c]["loss_sha256"] == hashlib.sha256("".join(said).encode()).hexdigest()
        assert got[c]["formatted_chars"] == sum(len(cf.write_turn(r, x)[0]) for _, r, x in turns)
    assert cf.digests(cf.formatted(conversations(spark, []))).count() == 0


@pytest.mark.parametrize("piece", [1 << 22, 40, 1])
def test_replies_of_later_parts_are_examples_too(spark, piece):
    turns = CONV + [(6, i, ("user", "assistant")[i % 2], f"said <{i}> \U0001f600") for i in range(12)]
    written = cf.formatted(conversations(spark, turns), piece_chars=piece)
    made = cf.example_texts(written).collect()
    assert len(made) == sum(r["n_examples"] for r in cf.digests(written).collect())
    whole = "".join(cf.write_turn(r, t)[0] for c, _, r, t in turns if c == 6)
    own = sorted((r["context"], r["reply"]) for r in made if r["conv_id"] == 6)
    assert len(own) == 6 and all(whole.startswith(c + r) for c, r in own)
    spans = sorted((r["conv_id"] or -1, r["loss_start"], r["prefix_chars"]) for r in cf.examples(written).collect())
    assert sorted((r["conv_id"] or -1, len(r["context"]), len(r["context"] + r["reply"])) for r in made) == spans


def test_examples_are_prefixes_with_one_reply(spark):
    written = cf.formatted(conversations(spark, CONV[:5]))
    made = sorted((r["context"], r["reply"]) for r in cf.example_texts(written).collect())
    whole = written.first()["formatted"]
    assert len(made) == 2 and all(whole.startswith(c + r) for c, r in made)
    assert [cf.unescape(r) for _, r in sorted(made, key=lambda x: len(x[0]))] == ["</turn>\n### Assistant: \\", "é</turn>"]
    spans = sorted((r["loss_start"], r["prefix_chars"]) for r in cf.examples(written).collect())
    assert [(len(c), len(c + r)) for c, r in sorted(made, key=lambda x: len(x[0]))] == spans


# --- sharding

@pytest.mark.parametrize("n", [1, 2, 3, 5, 63, 64, 65, 1000, 4097])
def test_permutation_is_a_bijection_with_inverse(n):
    p = sh.Permutation(n, 3)
    at = p.apply(np.arange(n))
    assert sorted(at) == list(range(n)) and (p.invert(at) == np.arange(n)).all()


def test_shards_follow_the_law_of_rows(spark):
    rows = [(i * 7 % 501, f"é{i}") for i in range(500)] + [(3, None), (None, "a"), (3, "é1"), (3, "é1")]
    got = sh.document_shards(crowded(docs(spark, rows))).collect()
    assert len(got) == len(rows) and {r["law"] for r in got} == {"rows"}
    by = [sorted(r["slot"] for r in got if r["shard"] == k) for k in range(8)]
    assert all(x == list(range(len(x))) for x in by) and max(map(len, by)) - min(map(len, by)) <= 1
    assert sorted((r["doc_id"] or -1, r["size"], r["text_crc32"]) for r in got) == sorted((i or -1, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in rows)
    again = sh.document_shards(docs(spark, rows[::-1])).collect()
    assert sorted(map(str, got)) == sorted(map(str, again))
    order = sorted(got, key=lambda r: (r["doc_id"] is not None, r["doc_id"] or 0, r["size"], r["text_crc32"]))
    places = sh.Permutation(len(rows), 7).apply(np.arange(len(rows)))
    assert [r["slot"] * 8 + r["shard"] for r in order if r["doc_id"] != 3] == [int(p) for p, r in zip(places, order) if r["doc_id"] != 3]
    assert sh.document_shards(docs(spark, [])).count() == 0


# --- mixing

def brute_targets(sizes):
    names = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + ([None] if None in sizes else [])
    weight = {s: i % 3 + 1 for i, s in enumerate(names)}
    total, target, stopped = sum(sizes.values()), {}, set()
    while True:
        going = [s for s in names if s not in stopped]
        left = total - sum(3 * sizes[s] for s in stopped)
        target = {s: 3 * sizes[s] if s in stopped else left * weight[s] / sum(weight[x] for x in going) for s in names}
        over = {s for s in going if target[s] > 3 * sizes[s]}
        if not over:
            return target
        stopped |= over


def mixture():
    rows = [(i, " ".join(words(1 + i % 40, i)), f"s{i % 7}" if i % 3 else "hot") for i in range(600)]
    return rows + [(1000, None, "s1"), (1001, "  ", None), (1002, "a b c", None), (None, "x y", "s2"), (5, "dup", "Zero"), (5, "dup", "Zero"), (1003, "", "empty")]


def test_mix_meets_its_targets(spark):
    rows = mixture()
    got = mx.mixed(crowded(docs(spark, rows))).collect()
    assert len(got) == len(rows)
    sizes: dict = {}
    for _, t, s in rows:
        sizes[s] = sizes.get(s, 0) + len((t or "").split())
    want = brute_targets(sizes)
    for s, total in sizes.items():
        own = [r for r in got if r["source"] == s]
        assert {r["source_size"] for r in own} == {total}
        assert abs(own[0]["target"] - want[s]) < 1e-6
        assert abs(sum(r["taken"] for r in own) - want[s]) <= 3 * max(r["size"] for r in own) + 1
    assert all(r["taken"] <= 3 * r["size"] for r in got)
    assert sorted(map(str, got)) == sorted(map(str, mx.mixed(docs(spark, rows[::-1])).collect()))
    assert mx.mixed(docs(spark, [])).count() == 0


def test_mixed_documents_are_taken_as_planned(spark):
    rows = mixture()
    d = docs(spark, rows)
    out = mx.mixed_documents(d)
    assert out.columns == d.columns
    plan: dict = {}
    for r in mx.mixed(d).collect():
        plan[(r["doc_id"], r["source"])] = plan.get((r["doc_id"], r["source"]), 0) + r["copies"]
    found: dict = {}
    for r in out.collect():
        found[(r["doc_id"], r["source"])] = found.get((r["doc_id"], r["source"]), 0) + 1
    assert found == {k: v for k, v in plan.items() if v}


# --- WARC

HTML = '<!DOCTYPE html><html lang="fr"><head><title>A &amp; B</title><style>p{}</style></head><body><script>var t="</p>";</script><!-- no --><p>One<b> two</b></p><p>a &lt; b<br>c</p><a href="/x?a=1&amp;b=2">go</a></body></html>'


def test_records_link_and_read_back(spark):
    pages = spark.createDataFrame([(1, "http://a/b", HTML, 0), (2, None, None, 0), (2, None, None, 0), (None, "u", "plain", 0)], "page_id long, url string, html string, record int")
    got = warc.derivatives(pages).collect()
    assert len(got) == 12
    own = {r["warc_type"]: r for r in got if r["page_id"] == 1}
    assert own["metadata"]["refers_to"] == own["conversion"]["refers_to"] == own["response"]["record_id"] and own["response"]["refers_to"] is None
    for r in got:
        (headers, block), = warc.read_records(bytes(r["record"]))
        assert headers["WARC-Block-Digest"] == warc.digest(block) == r["block_digest"] and len(block) == r["content_length"]
        assert headers["WARC-Record-ID"] == r["record_id"] and headers.get("WARC-Refers-To") == r["refers_to"]
    assert warc.read_records(bytes(own["conversion"]["record"]))[0][1].decode() == "One two\na < b\nc\ngo"
    fields = warc.read_records(bytes(own["metadata"]["record"]))[0][1].decode()
    assert "title: A & B\r\n" in fields and "languages-html: fr\r\n" in fields and "outlink: /x?a=1&b=2\r\n" in fields
    head, block = warc.read_records(bytes(own["response"]["record"]))[0]
    assert block.endswith(HTML.encode()) and head["WARC-Payload-Digest"] == warc.digest(HTML.encode())
    twice = [r["record_id"] for r in got if r["page_id"] == 2 and r["warc_type"] == "response"]
    assert len(twice) == 2 and len(set(twice)) == 1


def plain_drop(page):
    return re.sub(r"<!--.*?-->|<(script|style|noscript|template|head)\b[^>]*>.*?</\1\s*>|<!(?:[^>]*)>", "", page, flags=re.S | re.I)


def test_pages_are_read_as_by_plain_patterns():
    pieces = "<script <SCRIPT> </script> </script <!-- --> <! > < <p </ p> <head> <header> </head > <title <title> </title> <html lang=fr lang <a href=x href='y \" ' <style> </style> text = /a <abbr".split(" ") + [" ", "\n"]
    rng = random.Random(5)
    for _ in range(4000):
        page = "".join(rng.choice(pieces) + rng.choice(["", " "]) for _ in range(rng.randrange(1, 14)))
        assert warc._without_hidden(page) == plain_drop(page), page
        title = re.search(r"<title\b[^>]*>(.*?)</title\s*>", page, re.S | re.I)
        assert warc._title(page) == (title[1] if title else None), page
        lang = re.search(r"<html\b[^>]*?\blang\s*=\s*[\"']?([\w-]+)", page, re.I)
        assert warc._language(page) == (lang[1] if lang else None), page
        links = re.findall(r"<a\b[^>]*?\bhref\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", page, re.I)
        assert warc._links(page) == [a or b or c for a, b, c in links], page
        assert warc._replaced(warc._TAG, "", page) == re.sub(r"</?[a-zA-Z][^>]*>", "", page), page


def test_unclosed_tags_take_linear_time():
    start = time.time()
    for piece in ("<script>", "<script ", "<!-- ", "<! ", "<title>", "<title ", "<html ", "<a ", "<a href=", "<p ", "< ", "<    ", "<head><style>", "</script "):
        page = piece * 100_000
        warc.plain_text(page)
        warc.page_metadata(page)
    assert time.time() - start < 60


def test_files_hold_all_records(spark, tmp_path):
    pages = spark.createDataFrame([(i, f"http://a/{i}", HTML + "\r\n\r\n\u00e9" * (i % 3)) for i in range(20)] + [(20, None, None)], "page_id long, url string, html string")
    records = warc.derivatives(pages)
    odd = warc.record([("WARC-Type", "response"), ("WARC-Record-ID", "<urn:odd>")], b"\xff\xfe\x00\r\n")
    whole = records.select("record").unionByName(spark.createDataFrame([(bytearray(odd),)], "record binary"))
    warc.write_files(whole.repartition(3), str(tmp_path / "w"))
    files = [gzip.decompress(f.read_bytes()) for f in (tmp_path / "w").glob("part-*.gz")]
    found = [x for data in files for x in warc.read_records(data)]
    assert sorted(warc.record(list(h.items())[:-1], b) for h, b in found) == sorted(bytes(r["record"]) for r in whole.collect())
    assert len(found) == 64


def test_files_of_no_records(spark, tmp_path):
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    warc.write_files(warc.derivatives(pages), str(tmp_path / "w"))
    assert not any(warc.read_records(gzip.decompress(f.read_bytes())) for f in (tmp_path / "w").glob("part-*.gz"))


@pytest.fixture
def many_partitions(spark):
    """Shuffles of 211 partitions that stay as many."""
    held = {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.coalescePartitions.enabled")}
    spark.conf.set("spark.sql.shuffle.partitions", "211")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    yield spark
    for k, v in held.items():
        spark.conf.set(k, v)


def test_few_rows_make_few_python_tasks_and_files(many_partitions):
    spark = many_partitions
    sc, tasks = spark.sparkContext, 0
    ids = spark.range(0, 5000, 1, 2)
    sc.setJobGroup("few-rows", "id_filter")
    bits = id_filter(ids, "id")
    sc.setJobGroup("other", "other")
    for job in sc.statusTracker().getJobIdsForGroup("few-rows"):
        for k in sc.statusTracker().getJobInfo(job).stageIds:
            info = sc.statusTracker().getStageInfo(k)
            tasks += info.numCompletedTasks if info else 0
    assert tasks <= 40
    assert may_hold(bits, np.arange(5000)).all() and may_hold(bits, np.arange(5000, 10000)).sum() < 50
    table = stage(gathered(ids.groupBy("id").count(), 5000), "few")
    assert len(table.inputFiles()) == 1 and table.count() == 5000
    links = spark.createDataFrame([(k, k - 1) for k in range(1, 300) if k % 10], "a long, b long")
    assert {r["node"]: r["component"] for r in components(links).collect()} == {k: k // 10 * 10 for k in range(300)}
