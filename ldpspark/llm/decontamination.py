"""Benchmark decontamination over a distributed positional inverted index.

1. Corpus frequencies of the benchmark's terms are counted over all texts.
2. Every benchmark window (``length`` consecutive words) gets its two rarest terms as anchors; a window with a term that the corpus
   lacks is dropped.
3. The index holds the postings (term, text, position) of all anchor terms.
4. Posting lists are intersected along offset-adjusted positions: a window stays possible at an alignment only
   if both its anchors are posted there.
5. What is left is compared word by word on the whole text, which gives the hit words exactly.
6. Proximity matches come from the same lists: texts where both anchors of a window stand at nearly their distance.

What goes to the executors at once is one bit map of fixed size (``merging.BITS``); terms that it lets
through by chance drop out in the joins.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ldpspark.llm.merging import _places, id_filter, only_ids
from ldpspark.llm.staging import lean, small_batches, stage
from ldpspark.llm.textkernel import ALNUM, runs, texts_of, word_bounds, word_hashes

LENGTH = 13
ANCHORS = 2
#: Words by which the distance of two anchors may differ from theirs in the window.
SLACK = 5
#: Tasks that share the rows of one frequent term or item.
SALTS = 16


def tokens(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Per run of texts: first and last+1 text number, word hashes, text number of each word (from the first)."""
    raw, offsets = texts_of(column)
    for a, b in runs(offsets):
        part, at = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        starts, ends, of = word_bounds(part, at, ALNUM)
        yield a, b, word_hashes(part, starts, ends), of


def item_words(items: DataFrame) -> DataFrame:
    """(ik, item_id as string, words): the word hashes of each benchmark item that has words; ``ik`` tells items of one id apart by their text."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[np.ndarray] = []
            for a, b, h, of in tokens(batch["text"]):
                edges = np.searchsorted(of, np.arange(b - a + 1))
                out += [h[edges[i] : edges[i + 1]].view(np.int64) for i in range(b - a)]
            yield pa.RecordBatch.from_arrays([batch["ik"], batch["item_id"], pa.array(out, pa.list_(pa.int64()))], names=["ik", "item_id", "words"])

    named = items.select(F.xxhash64(F.col("item_id").cast("string"), F.col("text").cast("string")).alias("ik"), F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text"))
    return named.mapInArrow(lean(work), "ik long, item_id string, words array<long>").where(F.size("words") > 0).dropDuplicates(["ik"])


def windows(words: DataFrame, length: int = LENGTH) -> DataFrame:
    """(ik, start, pos, term): each window's terms by position in the item."""
    last = F.greatest(F.size("words") - length, F.lit(0))
    starts = words.withColumn("start", F.explode(F.sequence(F.lit(0), last)))
    inside = F.slice("words", F.col("start") + 1, F.lit(length))
    return starts.select("ik", "start", F.posexplode(inside).alias("off", "term")).select("ik", "start", (F.col("start") + F.col("off")).alias("pos"), "term")


def _seen(h: np.ndarray, packed: np.ndarray) -> np.ndarray:
    known = np.ones(len(h), bool)
    for p in _places(h.view(np.int64)):
        known &= ((packed[(p >> np.uint64(3)).astype(np.int64)] >> (7 - (p & np.uint64(7))).astype(np.uint8)) & 1).astype(bool)
    return known


def term_counts(docs: DataFrame, bits: np.ndarray) -> DataFrame:
    """(term, n): corpus occurrences of all terms in the bit map."""
    shared = docs.sparkSession.sparkContext.broadcast(bits)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        n = 0

        def counted() -> pa.RecordBatch:
            term, count = np.unique(np.concatenate(held), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(term.view(np.int64)), pa.array(count.astype(np.int64))], names=["term", "n"])

        for batch in batches:
            for _, _, h, _ in tokens(batch["text"]):
                h = h[_seen(h, shared.value)]
                held.append(h)
                n += len(h)
                if n > 4_000_000:
                    yield counted()
                    held, n = [], 0
        if n:
            yield counted()

    return docs.select("text").mapInArrow(lean(work), "term long, n long").groupBy("term").agg(F.sum("n").alias("n"))


def anchored(grams: DataFrame, counts: DataFrame, anchors: int = ANCHORS) -> DataFrame:
    """(ik, start, pos, term): the rarest terms of each window that the corpus can hold."""
    by = Window.partitionBy("ik", "start")
    known = grams.join(counts, "term", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    known = known.withColumn("least", F.min("n").over(by)).where("least > 0")
    return known.withColumn("nth", F.row_number().over(by.orderBy("n", "pos"))).where(F.col("nth") <= anchors).select("ik", "start", "pos", "term")


def postings(docs: DataFrame, bits: np.ndarray) -> DataFrame:
    """The index: (doc_id, th, n_words) of each text with ``term`` null, and (doc_id, th, term, pos) of each posting."""
    shared = docs.sparkSession.sparkContext.broadcast(bits)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, h, of in tokens(batch["text"]):
                edges = np.searchsorted(of, np.arange(b - a + 1))
                ids, th = batch["doc_id"].slice(a, b - a), batch["th"].slice(a, b - a)
                k = b - a
                yield pa.RecordBatch.from_arrays([ids, th, pa.array(np.diff(edges)), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64())], names=["doc_id", "th", "n_words", "term", "pos"])
                at = np.flatnonzero(_seen(h, shared.value))
                if len(at):
                    own = pa.array(of[at])
                    yield pa.RecordBatch.from_arrays([ids.take(own), th.take(own), pa.nulls(len(at), pa.int64()), pa.array(h[at].view(np.int64)), pa.array(at - edges[of[at]])], names=["doc_id", "th", "n_words", "term", "pos"])

    return docs.mapInArrow(lean(work), "doc_id long, th long, n_words long, term long, pos long")


def spread(many: DataFrame, few: DataFrame, key: str, *by: str) -> DataFrame:
    """Inner join by ``key``: rows of one key in ``many`` go to SALTS tasks, by the columns ``by``; ``few``, which comes from the items alone, goes to all of them."""
    dealt = many.withColumn("salt", F.pmod(F.xxhash64(*by), F.lit(SALTS).cast("long")))
    copies = few.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    return dealt.join(copies, [key, "salt"]).drop("salt")


def alignments(index: DataFrame, anchors: DataFrame) -> DataFrame:
    """(doc_id, th, ik, shift): where some window's anchors are all posted at their offsets."""
    places = anchors.select("ik", "pos", "term").distinct().withColumnRenamed("pos", "item_pos")
    found = spread(index.where("term is not null"), places, "term", "doc_id", "th", "pos")
    found = found.groupBy("doc_id", "th", "ik", (F.col("pos") - F.col("item_pos")).alias("shift")).agg(F.collect_set("item_pos").alias("posted"))
    wanted = anchors.groupBy("ik", "start").agg(F.collect_set("pos").alias("need")).groupBy("ik").agg(F.collect_set("need").alias("needs"))
    met = F.exists("needs", lambda need: F.size(F.array_except(need, F.col("posted"))) == 0)
    return spread(found, wanted, "ik", "doc_id", "th", "shift").where(met).select("doc_id", "th", "ik", "shift")


def phrase_hits(texts: DataFrame, aligned: DataFrame, words: DataFrame, length: int = LENGTH) -> DataFrame:
    """(doc_id, th, n_hit, items): words of the text inside any occurring window, and the items whose windows occur."""
    listed = spread(aligned, words, "ik", "doc_id", "th").groupBy("doc_id", "th").agg(F.collect_list(F.struct("item_id", "shift", "words")).alias("at"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hits, names = [], []
            lists = batch["at"]
            for a, b, h, of in tokens(batch["text"]):
                edges = np.searchsorted(of, np.arange(b - a + 1))
                for i in range(b - a):
                    own = h[edges[i] : edges[i + 1]].view(np.int64)
                    marked = np.zeros(len(own), bool)
                    found = set()
                    for x in lists[a + i].as_py():
                        w = np.array(x["words"], np.int64)
                        k, s = min(length, len(w)), x["shift"]
                        lo, hi = max(0, -s), min(len(w), len(own) - s)
                        if hi - lo < k:
                            continue
                        same = np.concatenate(([0], np.cumsum(own[lo + s : hi + s] == w[lo:hi])))
                        starts = np.flatnonzero(same[k:] - same[:-k] == k)
                        if len(starts):
                            found.add(x["item_id"])
                            for p in starts:
                                marked[p + lo + s : p + lo + s + k] = True
                    hits.append(int(marked.sum()))
                    names.append(sorted(found))
            yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["th"], pa.array(hits, pa.int64()), pa.array(names, pa.list_(pa.string()))], names=["doc_id", "th", "n_hit", "items"])

    same = texts["doc_id"].eqNullSafe(listed["doc_id"]) & (texts["th"] == listed["th"])
    both = texts.join(listed.hint("merge"), same).select(texts["doc_id"], texts["th"], "text", "at").dropDuplicates(["doc_id", "th"])
    return both.mapInArrow(lean(work), "doc_id long, th long, n_hit long, items array<string>").where("n_hit > 0")


def proximity_matches(index: DataFrame, anchors: DataFrame, length: int = LENGTH, slack: int = SLACK) -> DataFrame:
    """(doc_id, th, ik, off_by): texts that hold the two anchors of some window of an item up to ``slack`` words off their true distance; the least ``off_by``.

    Windows in a row mostly share their anchors, and are one here. Positions are joined by cells of the text of the width of the window, so that a frequent term meets only
    its neighbourhood. A window of one term has no such match.
    """
    pair = anchors.groupBy("ik", "start").agg(F.array_sort(F.collect_list(F.struct("pos", "term"))).alias("p")).where(F.size("p") >= 2)
    pair = pair.select("ik", F.col("p")[0]["term"].alias("term_a"), F.col("p")[1]["term"].alias("term_b"), (F.col("p")[1]["pos"] - F.col("p")[0]["pos"]).alias("gap")).distinct()
    width = length + slack
    posted = index.where("term is not null")
    cell = F.floor(F.col("pos") / width)
    a = posted.select("doc_id", "th", F.col("term").alias("term_a"), F.col("pos").alias("pos_a"), cell.alias("cell"))
    a = spread(a, pair, "term_a", "doc_id", "th", "pos_a")
    b = posted.select("doc_id", "th", F.col("term").alias("term_b"), F.col("pos").alias("pos_b"), F.explode(F.array(*[cell + i for i in (-1, 0, 1)])).alias("cell"))
    off = F.abs(F.col("pos_b") - F.col("pos_a") - F.col("gap"))
    same = a["doc_id"].eqNullSafe(b["doc_id"]) & (a["th"] == b["th"]) & (a["term_b"] == b["term_b"]) & (a["cell"] == b["cell"])
    near = a.join(b, same & (off <= slack)).select(a["doc_id"], a["th"], "ik", off.alias("off_by"))
    return near.groupBy("doc_id", "th", "ik").agg(F.min("off_by").alias("off_by"))


def build_index(docs: DataFrame, items: DataFrame, length: int = LENGTH) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(texts, item words, window anchors, index) over all texts."""
    small_batches(docs.sparkSession)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("th"), text.alias("text"))
    words = stage(item_words(items), "items")
    grams = windows(words, length)
    counts = term_counts(texts, id_filter(words.select(F.explode("words").alias("term")).distinct(), "term"))
    anchors = stage(anchored(grams, counts), "anchors")
    index = stage(postings(texts, id_filter(anchors.select("term").distinct(), "term")), "index")
    return texts, words, anchors, index


def contamination(docs: DataFrame, items: DataFrame, length: int = LENGTH, proximity: bool = False) -> DataFrame:
    """Hit words and items of every text: ``doc_id``, ``n_words``, ``n_hit``, ``n_items``, ``items``, ``contaminated``, ``th``; with ``proximity`` also ``n_near``,
    the number of items of which the text holds two anchors of a window at nearly their distance (``proximity_matches``).

    ``contaminated``: some hit, and at least a twentieth of the words. Null or empty text has no words. An item with fewer words
    than ``length`` is one window; one without words, or with null text, has none. Rows that repeat an id are judged each
    by its own text. Items that share an id are compared each by its own text and count once. Further columns are ignored; empty tables give no hits.
    """
    texts, words, anchors, index = build_index(docs, items, length)
    facts = index.where("n_words is not null").select("doc_id", "th", "n_words")
    aligned = stage(alignments(index, anchors), "alignments")
    held = only_ids(texts, "th", id_filter(aligned, "th"))
    hits = stage(phrase_hits(held, aligned, words, length), "hits").withColumnRenamed("doc_id", "hit_id").withColumnRenamed("th", "hit_th")
    out = facts.join(hits, facts["doc_id"].eqNullSafe(hits["hit_id"]) & (facts["th"] == hits["hit_th"]), "left")
    n_hit = F.coalesce("n_hit", F.lit(0)).cast("long")
    items_found = F.coalesce("items", F.array().cast("array<string>"))
    found = out.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size(items_found).cast("long").alias("n_items"), items_found.alias("items"), ((n_hit > 0) & (20 * n_hit >= F.col("n_words"))).alias("contaminated"), "th")
    if not proximity:
        return found
    named = spread(proximity_matches(index, anchors, length), words.select("ik", "item_id"), "ik", "doc_id", "th")
    near = named.groupBy("doc_id", "th").agg(F.countDistinct("item_id").alias("n_near")).withColumnsRenamed({"doc_id": "near_id", "th": "near_th"})
    both = found.join(near, found["doc_id"].eqNullSafe(near["near_id"]) & (found["th"] == near["near_th"]), "left").drop("near_id", "near_th")
    return both.withColumn("n_near", F.coalesce("n_near", F.lit(0)).cast("long"))


def digested(found: DataFrame) -> DataFrame:
    """The result with the items as one digest of their sorted ids."""
    near = [c for c in ("n_near",) if c in found.columns]
    return found.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.concat_ws(",", F.sort_array("items")), 256).alias("items_sha256"), "contaminated", *near)


def decontaminated(docs: DataFrame, items: DataFrame, length: int = LENGTH) -> DataFrame:
    """``docs`` without contaminated rows; columns unchanged."""
    bad = stage(contamination(docs, items, length).where("contaminated").select(F.col("doc_id").alias("_id"), F.col("th").alias("_th")).distinct(), "contaminated")
    own = F.xxhash64(F.coalesce(docs["text"].cast("string"), F.lit("")))
    return docs.join(bad, docs["doc_id"].cast("long").eqNullSafe(bad["_id"]) & (own == bad["_th"]), "left_anti")


ORACLE = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
i AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
iw AS (SELECT DISTINCT item_id, least(len(ws), 13) AS k, array_to_string(list_slice(ws, p, p + least(len(ws), 13) - 1), ' ') AS g
       FROM (SELECT *, unnest(range(1, greatest(len(ws) - 13, 0) + 2)) AS p FROM i WHERE len(ws) > 0)),
dw AS (SELECT doc_id, k, p, array_to_string(list_slice(ws, p, p + k - 1), ' ') AS g
       FROM (SELECT doc_id, ws, k, unnest(range(1, len(ws) - k + 2)) AS p FROM d, (SELECT DISTINCT k FROM iw) WHERE len(ws) >= k)),
m AS (SELECT doc_id, item_id, p, k FROM dw JOIN iw USING (k, g)),
h AS (SELECT doc_id, count(DISTINCT w) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + k)) AS w FROM (SELECT DISTINCT doc_id, p, k FROM m)) GROUP BY doc_id),
t AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS ids FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS s FROM m) GROUP BY doc_id),
iv AS (SELECT item_id, s, s + o AS pos, ws[s + o] AS t FROM (SELECT item_id, ws, s, unnest(range(0, least(len(ws), 13))) AS o FROM (SELECT *, unnest(range(1, greatest(len(ws) - 13, 0) + 2)) AS s FROM i WHERE len(ws) > 0))),
pos AS MATERIALIZED (SELECT doc_id, p, t FROM (SELECT doc_id, unnest(ws) AS t, unnest(range(1, len(ws) + 1)) AS p FROM d) WHERE t IN (SELECT t FROM iv)),
c AS (SELECT t, count(*) AS n FROM pos GROUP BY t),
ranked AS (SELECT item_id, s, pos, iv.t, min(coalesce(n, 0)) OVER (PARTITION BY item_id, s) AS least, row_number() OVER (PARTITION BY item_id, s ORDER BY coalesce(n, 0), pos) AS nth FROM iv LEFT JOIN c ON iv.t = c.t),
pair AS (SELECT DISTINCT item_id, ta, tb, gap FROM (SELECT item_id, s, arg_min(t, pos) AS ta, arg_max(t, pos) AS tb, max(pos) - min(pos) AS gap FROM ranked WHERE least > 0 AND nth <= 2 GROUP BY item_id, s HAVING count(*) = 2)),
near AS (SELECT a.doc_id, count(DISTINCT pair.item_id) AS n_near FROM pos a JOIN pair ON a.t = pair.ta JOIN pos b ON b.doc_id = a.doc_id AND b.t = pair.tb AND b.p BETWEEN a.p + gap - 5 AND a.p + gap + 5 GROUP BY a.doc_id)
SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated, coalesce(n_near, 0) AS n_near
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN t USING (doc_id) LEFT JOIN near USING (doc_id)
"""
