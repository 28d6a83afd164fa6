"""Repeated passages: paragraph MinHash banding, exact verification, and components.

Two kinds of units are compared over all texts, both as sequences of lower-cased words:

* **paragraphs**, the lines of ``min_words`` or more words: their shingle sets get MinHash signatures, cut into bands that are tuned
  for high recall at the similarity asked for; the exact Jaccard similarity of colliding paragraphs is computed from the texts,
  and the links are clustered by components. In each bucket the neighbours in the order of length are compared first; then all pairs
  of the bucket that are not in one cluster yet, in blocks where the bucket is large;
* **passages**, any ``min_words`` words in a row, which may begin inside a line and run over its end: equal ones
  are found by a 128-bit hash of the words. They catch what is pasted into otherwise different paragraphs. The anchor of such a window is the
  least hash of the shorter runs of words in it, so equal windows have equal anchors; windows in a row with one anchor are a
  segment. Equal segments are matched whole, and only segments that share their anchor with a different one are compared window by window.

In each cluster the occurrence of least document id and position stays; the others are spans to remove.
"""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ldpspark.llm.components import components
from ldpspark.llm.jaccard_join import common_counts, measured
from ldpspark.llm.merging import id_filter, may_hold, only_ids
from ldpspark.llm.staging import lean, lean_group, small_batches, stage
from ldpspark.llm.textkernel import _BASE, NOT_SPACE, _power, mix, runs, shingle_sets, texts_of, word_bounds, word_hashes

MIN_WORDS = 50
SHINGLE = 5
#: Buckets of up to so many lines are compared pair by pair, larger ones in blocks of about so many lines by as many.
SMALL = 16
BLOCK = 256
_A = np.random.Generator(np.random.PCG64(77)).integers(0, 1 << 64, (2, 256), dtype=np.uint64) | np.uint64(1)
_W1 = (_BASE ^ (0x5DEECE66D << 3)) & ((1 << 64) - 1)
_W2 = (_BASE ^ (0x2545F4914F6CDD1D << 3)) & ((1 << 64) - 1)


def tuned(share: float, recall: float, most: int = 64) -> tuple[int, int]:
    """(bands, rows): the fewest hash values, then the most rows, that find a pair of similarity ``share`` with probability ``recall``."""
    best = None
    for rows in range(1, 17):
        for bands in range(1, most // rows + 1):
            if 1 - (1 - share**rows) ** bands >= recall:
                # false candidates weigh with the chance that a pair of half the similarity collides
                cost = bands + 50 * (1 - (1 - (share / 3) ** rows) ** bands)
                if best is None or cost < best[0]:
                    best = (cost, bands, rows)
                break
    if best is None:
        raise ValueError("no banding reaches this recall")
    return best[1], best[2]


def _layout(column: pa.Array):
    """Per run of texts: first text, words' hashes, text, first words of texts, whether a line starts, and byte bounds with the bytes."""
    raw, offsets = texts_of(column)
    for a, b in runs(offsets):
        part, at = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        starts, ends, of = word_bounds(part, at, NOT_SPACE)
        h = word_hashes(part, starts, ends)
        lines = np.concatenate(([0], np.cumsum(part == 10)))[starts] if len(part) else np.zeros(0, np.int64)
        fresh = np.ones(len(h), bool)
        fresh[1:] = of[1:] != of[:-1]
        new_line = fresh.copy()
        new_line[1:] |= lines[1:] != lines[:-1]
        edges = np.searchsorted(of, np.arange(b - a + 1))
        yield a, b, h, of, edges, new_line, starts, ends, part, at


def _sums(h: np.ndarray, name: str, base: int) -> tuple[np.ndarray, np.ndarray]:
    n = len(h)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(h * _power(name, base, n), out=total[1:])
    return total, _power(name + "-inverse", pow(base, -1, 1 << 64), n)


def _span_hash(h: np.ndarray, i: np.ndarray, n: np.ndarray, name: str, base: int) -> np.ndarray:
    total, down = _sums(h, name, base)
    return mix((total[i + n] - total[i]) * down[i] + n.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def _least(x: np.ndarray, width: int) -> np.ndarray:
    """Least of the ``width`` values from each place on."""
    have = 1
    while have < width:
        step = min(have, width - have)
        x = np.minimum(x[:-step], x[step:])
        have += step
    return x


def _segments(h: np.ndarray, of: np.ndarray, edges: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first word, number of windows, anchor) of the segments of a run of texts: at most ``words`` windows, so that any two of them overlap or touch."""
    none = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    if len(h) < words:
        return none
    size = max(1, 2 * words // 5)
    i = np.arange(len(h) - size + 1)
    anchor = _least(_span_hash(h, i, np.full(len(i), size), "w1", _W1), words - size + 1)
    i = np.arange(len(anchor))
    i = i[i + words <= edges[of[i] + 1]]
    if not len(i):
        return none
    anchor = anchor[i]
    fresh = np.ones(len(i), bool)
    fresh[1:] = (anchor[1:] != anchor[:-1]) | (of[i[1:]] != of[i[:-1]])
    cut = np.flatnonzero(fresh)
    fresh |= (np.arange(len(i)) - np.repeat(cut, np.diff(np.append(cut, len(i))))) % words == 0
    cut = np.flatnonzero(fresh)
    return i[cut], np.diff(np.append(cut, len(i))), anchor[cut]


def _named(s1: np.ndarray, ids: np.ndarray, start: np.ndarray) -> np.ndarray:
    """One number for a segment at its place."""
    return mix(s1 + mix(ids.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + start.astype(np.uint64))).view(np.int64)


def segments(docs: DataFrame, words: int) -> DataFrame:
    """(anchor, s1, s2, doc_id, start, k, own): each segment by its anchor and the hash of its words, with its first word and number of windows."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch["doc_id"].to_numpy(zero_copy_only=False)
            for a, _, h, of, edges, *_ in _layout(batch["text"]):
                i, k, anchor = _segments(h, of, edges, words)
                if len(i):
                    n = k + words - 1
                    one, two = _span_hash(h, i, n, "w1", _W1), _span_hash(h, i, n, "w2", _W2)
                    doc, start = ids[a + of[i]], i - edges[of[i]]
                    columns = [anchor.view(np.int64), one.view(np.int64), two.view(np.int64), doc, start, k, _named(one, doc, start)]
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["anchor", "s1", "s2", "doc_id", "start", "k", "own"])

    return docs.mapInArrow(lean(work), "anchor long, s1 long, s2 long, doc_id long, start long, k long, own long")


def windows(docs: DataFrame, words: int, wanted: np.ndarray) -> DataFrame:
    """(s1, s2, doc_id, start, h1, h2, at): the windows, by hash and first word ``at``, of each segment whose ``own`` is in the bit map, and of few others."""
    shared = docs.sparkSession.sparkContext.broadcast(wanted)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch["doc_id"].to_numpy(zero_copy_only=False)
            for a, _, h, of, edges, *_ in _layout(batch["text"]):
                i, k, _ = _segments(h, of, edges, words)
                if not len(i):
                    continue
                s1 = _span_hash(h, i, k + words - 1, "w1", _W1)
                held = may_hold(shared.value, _named(s1, ids[a + of[i]], i - edges[of[i]]))
                i, k, s1 = i[held], k[held], s1[held]
                if not len(i):
                    continue
                s2 = _span_hash(h, i, k + words - 1, "w2", _W2)
                at = np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k) + np.repeat(i, k)
                n = np.full(len(at), words)
                one, two = _span_hash(h, at, n, "w1", _W1), _span_hash(h, at, n, "w2", _W2)
                base = edges[of[at]]
                columns = [np.repeat(s1, k).view(np.int64), np.repeat(s2, k).view(np.int64), ids[a + of[at]], np.repeat(i, k) - base, one.view(np.int64), two.view(np.int64), at - base]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["s1", "s2", "doc_id", "start", "h1", "h2", "at"])

    return docs.mapInArrow(lean(work), "s1 long, s2 long, doc_id long, start long, h1 long, h2 long, at long")


def passages(texts: DataFrame, words: int) -> DataFrame:
    """(doc_id, start, end, keep): all windows of ``words`` words whose words stand at an earlier place, those of a segment and a keeper as one span."""
    every = stage(segments(texts, words), "segments")
    place = F.struct("doc_id", "start", "own")
    kinds = every.groupBy("anchor", "s1", "s2").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("copies"))
    own = Window.partitionBy("anchor")
    kinds = kinds.withColumn("kinds", F.count(F.lit(1)).over(own))
    # an anchor that occurs once has no equal windows
    kinds = stage(kinds.where("kinds > 1 or copies > 1"), "kinds")

    mixed = kinds.where("kinds > 1").select(F.col("first.own").alias("own"))
    same = Window.partitionBy("h1", "h2")
    each = windows(texts, words, id_filter(mixed, "own")).withColumn("k", F.min(F.struct("doc_id", "at")).over(same))
    each = each.groupBy("s1", "s2", "doc_id", "start", F.col("k.doc_id").alias("keep")).agg(*[f(F.when(F.struct("doc_id", "at") != F.col("k"), F.col("at"))).alias(n) for f, n in ((F.min, "low"), (F.max, "high"))])
    each = stage(each, "windows")
    inner = each.where("low is not null").select("doc_id", F.col("low").alias("start"), (F.col("high") + words).alias("end"), "keep")

    keeps = each.groupBy("s1", "s2").agg(F.collect_set("keep").alias("keeps"))
    again = kinds.where("copies > 1").join(keeps, ["s1", "s2"], "left").select("anchor", "s1", "s2", "first", F.coalesce("keeps", F.array("first.doc_id")).alias("keeps"))
    copies = every.join(again, ["anchor", "s1", "s2"]).where((F.col("doc_id") != F.col("first.doc_id")) | (F.col("start") != F.col("first.start")))
    copies = copies.select("doc_id", "start", (F.col("start") + F.col("k") + words - 1).alias("end"), F.explode("keeps").alias("keep"))
    return inner.unionByName(copies)


def _lines(new_line: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    first = np.flatnonzero(new_line)
    n = np.diff(np.concatenate((first, [len(new_line)])))
    return first[n >= words], n[n >= words]


def paragraphs(docs: DataFrame, words: int, bands: int, rows: int) -> DataFrame:
    """(line, doc_id, start, n, keys): each long line by the hash of its words, and its band keys."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, h, of, edges, new_line, *_ in _layout(batch["text"]):
                first, n = _lines(new_line, words)
                if not len(first):
                    continue
                line = _span_hash(h, first, n, "w1", _W1)
                m = n - SHINGLE + 1
                at = np.repeat(first - np.cumsum(m) + m, m) + np.arange(m.sum())
                s = h[at] * _A[1, 0]
                for j in range(1, SHINGLE):
                    s = s + h[at + j] * _A[1, j]
                s = mix(s)
                cut = np.cumsum(m) - m
                keys = np.empty((len(first), bands), np.uint64)
                for band in range(bands):
                    key = np.full(len(first), band, np.uint64)
                    for r in range(rows):
                        value = s * _A[0, band * rows + r]
                        value ^= value >> np.uint64(29)
                        key = mix(key * np.uint64(0x9E3779B97F4A7C15) + np.minimum.reduceat(value, cut))
                    keys[:, band] = key
                yield pa.RecordBatch.from_arrays([pa.array(line.view(np.int64)), batch["doc_id"].slice(a, b - a).take(pa.array(of[first])), pa.array(first - edges[of[first]]), pa.array(n), pa.FixedSizeListArray.from_arrays(pa.array(keys.view(np.int64).ravel()), bands).cast(pa.list_(pa.int64()))], names=["line", "doc_id", "start", "n", "keys"])

    return docs.mapInArrow(lean(work), "line long, doc_id long, start long, n long, keys array<long>")


def _line_texts(docs: DataFrame, words: int, wanted) -> DataFrame:
    """(doc_id: hash of the line, text): texts of the lines in the bit map."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, h, _, _, new_line, starts, ends, part, _ in _layout(batch["text"]):
                first, n = _lines(new_line, words)
                if len(first):
                    line = _span_hash(h, first, n, "w1", _W1)
                    texts = [part[starts[i] : ends[i + k - 1]].tobytes().decode() for i, k in zip(first, n)]
                    yield pa.RecordBatch.from_arrays([pa.array(line.view(np.int64)), pa.array(texts)], names=["doc_id", "text"])

    return only_ids(docs.mapInArrow(lean(work), "doc_id long, text string"), "doc_id", wanted).dropDuplicates(["doc_id"])


def _block_links(share: Fraction):
    """(a, b): one link for each two classes (``c``) that a line of side 0 and a line of side 1 of a pair of blocks link."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        side, c, line = pdf["side"].to_numpy(), pdf["c"].to_numpy(), pdf["line"].to_numpy()
        one, two = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        if not len(one) or not len(two):
            return pd.DataFrame({"a": [], "b": []}, dtype="int64")
        sets = list(shingle_sets(pa.array(pdf["text"]), SHINGLE))
        n = np.array([len(x) for x in sets], np.int64)
        both = common_counts(sets, one, two)
        link = both * share.denominator >= (n[one][:, None] + n[two][None, :] - both) * share.numerator
        i, j = np.nonzero(link & (c[one][:, None] != c[two][None, :]))
        out = pd.DataFrame({"a": line[one[i]], "b": line[two[j]], "ca": c[one[i]], "cb": c[two[j]]})
        return out.drop_duplicates(["ca", "cb"])[["a", "b"]].astype("int64")

    return work


def line_links(keyed: DataFrame, texts: DataFrame, words: int, need: Fraction) -> DataFrame:
    """(a, b): links whose components are those of all links between lines that share a key. ``keyed``: (line, n, key), stored."""
    by = Window.partitionBy("key").orderBy("n", "line")
    ranked = keyed.withColumn("before", F.lag("line").over(by)).withColumn("p", F.first("line").over(by))
    pairs = ranked.where("before is not null").select("line", F.explode(F.array_distinct(F.array("p", "before"))).alias("other")).where("line != other")
    pairs = stage(pairs.select(F.greatest("line", "other").alias("a"), F.least("line", "other").alias("b")).distinct(), "colliding")
    # every line that shares a key is in one of these pairs
    held = stage(_line_texts(texts, words, id_filter(pairs.select("a").union(pairs.select("b")), "a")), "line-texts")
    linked = F.col("common") * need.denominator >= F.col("together") * need.numerator
    links = stage(measured(pairs, held, SHINGLE).where(linked).select("a", "b"), "near")

    # only pairs of two classes are left; those of the largest class of a bucket need no test among themselves
    classes = components(links).select(F.col("node").alias("line"), F.col("component").alias("c"))
    classed = stage(keyed.join(classes, "line", "left").withColumn("c", F.coalesce("c", "line")), "classed")
    size = classed.groupBy("key", "c").agg(F.count(F.lit(1)).alias("k"))
    size = size.groupBy("key").agg(F.max(F.struct("k", "c")).alias("top"), F.sum("k").alias("members"), F.count(F.lit(1)).alias("kinds")).where("kinds > 1")
    open_ = stage(classed.join(size.select("key", F.col("top.c").alias("top"), "members", (F.col("members") - F.col("top.k")).alias("others")), "key"), "open")

    few = open_.where(F.col("members") <= SMALL)
    u, y = few.where("c != top").select("key", F.col("line").alias("a"), F.col("n").alias("na"), F.col("c").alias("ca")), few.select("key", F.col("line").alias("b"), F.col("n").alias("nb"), F.col("c").alias("cb"))
    left = u.join(y, "key").where("ca != cb").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    left = stage(left.join(pairs, ["a", "b"], "left_anti"), "small-buckets")
    more = measured(left, held, SHINGLE).where(linked).select("a", "b")

    many = open_.where(F.col("members") > SMALL)
    last = lambda c: (F.ceil(F.col(c) / BLOCK) - 1).cast("long")
    place = lambda c: F.pmod(F.xxhash64("line"), last(c) + 1)
    zero = F.lit(0).cast("long")
    row = ["key", "line", "c"]
    ones = many.where("c != top").select(*row, F.lit(0).alias("side"), place("others").alias("i"), F.explode(F.sequence(zero, last("members"))).alias("j"))
    twos = many.select(*row, F.lit(1).alias("side"), F.explode(F.sequence(zero, last("others"))).alias("i"), place("members").alias("j"))
    blocks = stage(ones.unionByName(twos), "blocks").join(held.withColumnRenamed("doc_id", "line").hint("merge"), "line")
    found = blocks.groupBy("key", "i", "j").applyInPandas(lean_group(_block_links(need)), "a long, b long")
    return links.unionByName(more).unionByName(found)


def repeated_spans(docs: DataFrame, min_words: int = MIN_WORDS, share: tuple[int, int] = (3, 4), recall: float = 0.99) -> DataFrame:
    """Spans that repeat an earlier document's words: ``doc_id``, ``start``, ``end`` (words, end exclusive), ``n_words``, ``keep_doc_ids``.

    A repeat is an earlier place that does not overlap it: a phrase said over and over in one text only, for fewer than twice ``min_words`` words, may be left out.
    Overlapping and touching spans of a document are one row; ``keep_doc_ids`` lists the documents whose occurrences stay. A document may be its own
    keeper, if it repeats itself. Null or empty texts and texts of fewer than ``min_words`` words have no spans; null ids are left out; rows that repeat
    an id are one document with the spans of each. Further columns are ignored.
    """
    small_batches(docs.sparkSession)
    need = Fraction(*share)
    bands, rows = tuned(float(need), recall)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("doc_id is not null")

    equal = passages(texts, min_words)

    lines = stage(paragraphs(texts, min_words, bands, rows), "paragraphs")
    keyed = lines.groupBy("line").agg(F.first("n").alias("n"), F.first("keys").alias("keys")).select("line", "n", F.explode("keys").alias("key"))
    links = line_links(stage(keyed, "keyed"), texts, min_words, need)
    cluster = components(links).withColumnRenamed("node", "line")
    clustered = lines.drop("keys").join(cluster, "line", "left").withColumn("component", F.coalesce("component", "line"))
    first = clustered.groupBy("component").agg(F.min(F.struct("doc_id", "start")).alias("k"), F.count(F.lit(1)).alias("c")).where("c > 1")
    near = clustered.join(first, "component").where(F.struct("doc_id", "start") != F.col("k")).select("doc_id", "start", (F.col("start") + F.col("n")).alias("end"), F.col("k.doc_id").alias("keep"))

    spans = stage(equal.unionByName(near).groupBy("doc_id", "start", "end").agg(F.collect_set("keep").alias("keep")), "spans")
    order = Window.partitionBy("doc_id").orderBy("start", "end")
    reach = F.max("end").over(order.rowsBetween(Window.unboundedPreceding, -1))
    island = spans.withColumn("fresh", F.when(F.col("start") <= reach, 0).otherwise(1))
    island = island.withColumn("island", F.sum("fresh").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    out = island.groupBy("doc_id", "island").agg(F.min("start").alias("start"), F.max("end").alias("end"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("keep")))).alias("keep_doc_ids"))
    return out.select("doc_id", "start", "end", (F.col("end") - F.col("start")).alias("n_words"), "keep_doc_ids")


def without_spans(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """``docs`` with the words of the spans cut out of ``text``; what stands between other words is left as it was. Columns unchanged."""
    cuts = spans.groupBy(F.col("doc_id").alias("id")).agg(F.sort_array(F.collect_list(F.struct("start", "end"))).alias("cuts"))
    rows = docs.select(F.col("doc_id").cast("long").alias("own"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    joined = rows.join(cuts, rows["own"] == cuts["id"], "left").select("row", "cuts")
    at = docs.columns.index("text")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            row = batch.column(0)
            out = []
            for text, own in zip(row.field(at), batch.column(1).to_pylist()):
                value = text.as_py()
                if own and value:
                    _, _, _, _, _, _, starts, ends, part, _ = next(_layout(pa.array([value])))
                    keep = np.ones(len(part), bool)
                    for s in own:
                        lo = starts[s["start"]] if s["start"] < len(starts) else len(part)
                        hi = starts[s["end"]] if s["end"] < len(starts) else len(part)
                        keep[lo:hi] = False
                    value = part[keep].tobytes().decode()
                out.append(value)
            columns = [pa.array(out, pa.string()) if i == at else row.field(i) for i in range(row.type.num_fields)]
            yield pa.RecordBatch.from_arrays(columns, names=[row.type.field(i).name for i in range(row.type.num_fields)])

    return joined.mapInArrow(lean(work), docs.schema)
