"""Exact self join of texts under the Jaccard distance of their word shingles.

The distance 1 - |x n y| / |x u y| is a metric. The join works on that alone:

* **Pivots and Voronoi regions.** The pivots of the first level are the one-shingle sets. A text's
  distance to the pivot {s} is 1 - 1/|x| if it holds s and 1 otherwise, so its nearest pivots are its
  own shingles; the tie is broken by one order of all shingles, rarest first (by a counter table of
  fixed size filled from all texts). The text lives in the region of the first of them.
* **Windows.** A partner within distance t can live elsewhere. By the triangle inequality through
  the empty set and the bound on the shared part, it holds one of the text's first
  |x| - ceil((1-t)|x|) + 1 shingles in that order; the text is replicated to exactly these regions.
* **Recursion.** Equal sets are one set from the start. In each region the member of least id is the next pivot p and every member's
  distance to it is computed exactly. Members within t of p are linked to it, and so to each other's class.
  A member u beyond t goes on with the other such members, and with the members y inside
  the ball only if d(u, p) <= 2t and |d(u, p) - d(y, p)| <= t. (Distances are first bounded from below by
  parity maps, which settle most pairs that are not linked without their texts.) Rests of at most ``SMALL`` members are joined
  pair by pair. A larger rest gets ``PIVOTS`` pivots, of different classes where it can: links to them merge classes, every member
  lives in the Voronoi region of its nearest pivot and is replicated to the region of pivot j if d(u, p_j) - d(u, p_home) <= 2t and
  d(u, p_j) is within t of that region's radius; only pairs with one end at home are joined there. Regions of one class end,
  the others recur with pivots of their own.
* **Dense rests.** Where the windows would replicate a rest instead of parting it, all its members lie within about 2t of each other and
  no pivot can tell them apart. What is not of its largest class is then compared with the rest in blocks, by sizes and parity maps.

Every link between different texts lies inside one class of the result, and classes are made of
links only: a pair is left out only where the triangle inequality excludes it or where both ends are
linked to a pivot already. Numbers of links are counted within classes; texts within t/2 of one pivot are linked to each
other by the triangle inequality, and are counted without being compared.
"""

from __future__ import annotations

import functools
from collections.abc import Callable, Iterator
from fractions import Fraction

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ldpspark.llm.components import components
from ldpspark.llm.merging import SLICE_SCHEMA, id_filter, may_hold, merged, only_ids, slices_of
from ldpspark.llm.staging import gathered, lean, lean_group, small_batches, stage
from ldpspark.llm.textkernel import shingle_sets

CELLS = 1 << 20
SMALL = 16
PIVOTS = 4
LEVELS = 6
#: A rest is dense if its regions would hold this many times its rows.
SPREAD = 1.5
BLOCK = 512
#: Different sets of a class whose links are counted at once against as many.
COUNTED = 256
#: Pairs of a task that are measured at once where pairs are few.
MEASURED = 2_000
ROWS = 1 << 18


def in_few(df: DataFrame, name: str, rows: int | None) -> DataFrame:
    """``df`` staged in few files, as it holds about ``rows`` rows at most."""
    return stage(df if rows is None else gathered(df, rows), name)


def _needed(n: int, share: Fraction) -> int:
    return -(-n * share.numerator // share.denominator)


def parity(s: np.ndarray) -> bytes:
    """One bit for each of 2 to 4 times len(s) hash cells (a power of two, 64 at least): whether it holds an odd number of shingles.

    Each shingle in one of two sets only flips one bit, so the number of unlike bits is a lower bound of the
    symmetric difference. Folding a longer map in two gives the shorter one.
    """
    bits = max(64, 1 << (2 * len(s)).bit_length())
    own = np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(own.astype(bool), bitorder="little").tobytes()


def apart(x: bytes, y: bytes) -> int:
    """Lower bound of the symmetric difference of the sets behind two parity maps."""
    a, b = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
    while len(a) > len(b):
        a = a[: len(a) // 2] ^ a[len(a) // 2 :]
    while len(b) > len(a):
        b = b[: len(b) // 2] ^ b[len(b) // 2 :]
    return int(np.bitwise_count(a ^ b).sum())


def _facts(docs: DataFrame, size: int) -> DataFrame:
    """Per text: id, number of shingles, 128-bit hash of the set; and slices of the shingle counters."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = np.zeros(CELLS, np.int64)
        seen = False
        for batch in batches:
            n, one, two, odd = [], [], [], []
            held: list[np.ndarray] = []
            rows = 0
            for s in shingle_sets(batch["text"], size):
                for kept, value in zip((n, one, two), _digest(s)):
                    kept.append(value)
                odd.append(parity(s))
                held.append(s)
                rows += len(s)
                if rows > ROWS:
                    cells += np.bincount((np.concatenate(held) >> np.uint64(44)).astype(np.int64), minlength=CELLS)
                    held, rows = [], 0
            if rows:
                cells += np.bincount((np.concatenate(held) >> np.uint64(44)).astype(np.int64), minlength=CELLS)
            seen = seen or any(n)
            k = len(n)
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(n, pa.int64()), pa.array(one, pa.int64()), pa.array(two, pa.int64()), pa.array(odd, pa.binary()), pa.nulls(k, pa.int32()), pa.nulls(k, pa.binary())], names=["doc_id", "n", "h1", "h2", "odd", "slice", "cells"])
        if seen:
            i, blobs = zip(*slices_of(cells))
            k = len(i)
            yield pa.RecordBatch.from_arrays([pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.binary()), pa.array(i, pa.int32()), pa.array(blobs, pa.binary())], names=["doc_id", "n", "h1", "h2", "odd", "slice", "cells"])

    return docs.mapInArrow(lean(work), f"doc_id long, n long, h1 long, h2 long, odd binary, {SLICE_SCHEMA}")


def _digest(s: np.ndarray) -> tuple[int, int, int]:
    """Size and 128-bit hash of a set, equal for equal sets only."""
    return len(s), int(s.sum(dtype=np.uint64).view(np.int64)), int((s * (s >> np.uint64(7) | np.uint64(1))).sum(dtype=np.uint64).view(np.int64))


def _regions(docs: DataFrame, size: int, share: Fraction, counts: np.ndarray, wanted: np.ndarray) -> DataFrame:
    """(key, doc_id, n): each text whose id is in the bit map with the regions it lives in or is replicated to. Of equal sets in a task the first one goes."""
    shared = docs.sparkSession.sparkContext.broadcast(wanted)
    order = docs.sparkSession.sparkContext.broadcast(np.minimum(counts, (1 << 22) - 1).astype(np.uint32))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weight = order.value
        seen: set[tuple[int, int, int]] = set()
        for batch in batches:
            ids = np.asarray(batch["doc_id"].fill_null(0))
            usable = np.asarray(batch["doc_id"].is_valid()) & may_hold(shared.value, ids)
            batch, ids = batch.filter(pa.array(usable)), ids[usable]
            keys: list[np.ndarray] = []
            who: list[np.ndarray] = []
            rows = 0
            for i, s in enumerate(shingle_sets(batch["text"], size)):
                n = len(s)
                if not n or (own := _digest(s)) in seen:
                    continue
                seen.add(own)
                k = n - _needed(n, share) + 1
                if k < n:
                    rank = (weight[(s >> np.uint64(44)).astype(np.int64)].astype(np.uint64) << np.uint64(42)) | (s >> np.uint64(22))
                    s = s[rank <= np.partition(rank, k - 1)[k - 1]]
                keys.append(s)
                who.append(np.array([[ids[i], n]] * len(s), np.int64))
                rows += len(s)
                if rows > ROWS:
                    yield _batch(keys, who)
                    keys, who, rows = [], [], 0
            if rows:
                yield _batch(keys, who)

    def _batch(keys: list[np.ndarray], who: list[np.ndarray]) -> pa.RecordBatch:
        pairs = np.concatenate(who)
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys).view(np.int64)), pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["key", "doc_id", "n"])

    return docs.mapInArrow(lean(work), "key long, doc_id long, n long")


def _common(x: np.ndarray, y: np.ndarray) -> int:
    if len(x) > len(y):
        x, y = y, x
    at = np.searchsorted(y, x)
    at[at == len(y)] = 0
    return int((y[at] == x).sum()) if len(y) else 0


def measured(pairs: DataFrame, texts: DataFrame, size: int = 5, rows: int | None = None) -> DataFrame:
    """(a, b, common, together): sizes of the shared and the united shingles of each pair ``(a, b)``, from whole texts. ``rows``: the number of pairs, if that is known."""
    left = texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a"))
    right = texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: tuple[object, np.ndarray] = (None, np.zeros(0, np.uint64))
        for batch in batches:
            both, either = [], []
            b_ids = batch["b"].to_pylist()
            text_b = batch["text_b"]
            for i, x in enumerate(shingle_sets(batch["text_a"], size)):
                t = text_b[i].as_py()
                if known[0] != (b_ids[i], t):
                    known = ((b_ids[i], t), next(shingle_sets(text_b.slice(i, 1), size)))
                c = _common(x, known[1])
                both.append(c)
                either.append(len(x) + len(known[1]) - c)
            yield pa.RecordBatch.from_arrays([batch["a"], batch["b"], pa.array(both, pa.int64()), pa.array(either, pa.int64())], names=["a", "b", "common", "together"])

    # by sort and merge at every size: a shuffle stands between two Python steps, so that a task never feeds two workers
    met = pairs.join(left.hint("merge"), "a").join(right.hint("merge"), "b").select("a", "b", "text_a", "text_b")
    # in order of b, as the set of b is made once for its pairs
    met = met if rows is None else gathered(met, rows, MEASURED).sortWithinPartitions("b")
    return met.mapInArrow(lean(work), "a long, b long, common long, together long")


def bounded(pairs: DataFrame, maps: DataFrame, rows: int) -> DataFrame:
    """(a, b, na, nb, least): the ``rows`` pairs with a lower bound of their symmetric difference, from the parity maps alone."""
    left = maps.select(F.col("doc_id").alias("a"), F.col("n").alias("na"), F.col("odd").alias("odd_a"))
    right = maps.select(F.col("doc_id").alias("b"), F.col("n").alias("nb"), F.col("odd").alias("odd_b"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            least = [apart(x, y) for x, y in zip(batch["odd_a"].to_pylist(), batch["odd_b"].to_pylist())]
            yield pa.RecordBatch.from_arrays([batch["a"], batch["b"], batch["na"], batch["nb"], pa.array(least, pa.int64())], names=["a", "b", "na", "nb", "least"])

    met = pairs.join(left.hint("merge"), "a").join(right.hint("merge"), "b").select("a", "b", "na", "nb", "odd_a", "odd_b")
    return gathered(met, rows).mapInArrow(lean(work), "a long, b long, na long, nb long, least long")


def _fold(maps: np.ndarray, words: int) -> np.ndarray:
    while maps.shape[1] > words:
        half = maps.shape[1] // 2
        maps = maps[:, :half] ^ maps[:, half:]
    return maps


def _block_pairs(share: Fraction):
    """Pairs of two classes (``c``) of a text of side 0 and one of side 1 that sizes and parity maps leave possible."""
    p, q = share.numerator, share.denominator

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        out = [pd.DataFrame({"a": [], "b": []}, dtype="int64")]
        sides = [{k: (g["doc_id"].to_numpy(), g["c"].to_numpy(), g["n"].to_numpy(), np.array([np.frombuffer(x, np.uint64) for x in g["odd"]])) for k, g in part.groupby(part["odd"].str.len())} for part in (pdf[pdf["side"] == 0], pdf[pdf["side"] == 1])]
        for la, (ia, ca, na, ma) in sides[0].items():
            for lb, (ib, cb, nb, mb) in sides[1].items():
                words = min(la, lb) // 8
                fa, fb = _fold(ma, words), _fold(mb, words)
                for k in range(len(ia)):
                    could = np.flatnonzero((cb != ca[k]) & (na[k] * q >= nb * p) & (nb * q >= na[k] * p))
                    if len(could):
                        least = np.bitwise_count(fb[could] ^ fa[k]).sum(axis=1, dtype=np.int64)
                        could = could[least * (q + p) <= (na[k] + nb[could]) * (q - p)]
                        out.append(pd.DataFrame({"a": np.maximum(ia[k], ib[could]), "b": np.minimum(ia[k], ib[could])}))
        return pd.concat(out).drop_duplicates().astype("int64")

    return work


def in_blocks(rows: DataFrame, key: str, ones: str, block: int) -> DataFrame:
    """``rows`` dealt so that each row where ``ones`` holds (side 0) meets every row of its ``key`` (side 1) once, in group (key, i, j).

    Only the rows of ``ones`` are weighed against all others: a key of m rows and o such rows makes about 2 m o / block rows.
    """
    some = F.coalesce(F.expr(ones), F.lit(False))
    size = rows.groupBy(key).agg(F.count(F.lit(1)).alias("m"), F.sum(F.when(some, 1).otherwise(0)).alias("o")).where("o > 0 and m > 1")
    each = rows.join(size, key)
    last = lambda c: (F.ceil(F.col(c) / block) - 1).cast("long")
    place = lambda c: F.pmod(F.xxhash64("doc_id", "n"), last(c) + 1)
    span = lambda c: F.explode(F.sequence(F.lit(0).cast("long"), last(c)))
    one = each.where(some).select(*rows.columns, F.lit(0).alias("side"), place("o").alias("i"), span("m").alias("j"))
    two = each.select(*rows.columns, F.lit(1).alias("side"), span("o").alias("i"), place("m").alias("j"))
    return one.unionByName(two)


def _set_hash(s: np.ndarray) -> int:
    return int(s.sum(dtype=np.uint64).astype(np.int64))


def common_counts(sets: list[np.ndarray], one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Sizes of the shared parts of each of the sets ``one`` with each of the sets ``two``."""
    values, inverse, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = int((counts > 1).sum())
    column = np.full(len(values), -1)
    column[counts > 1] = np.arange(shared)
    place, of = column[inverse], np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    out = np.zeros((len(one), len(two)), np.float32)
    for a in range(0, shared, 4096):
        own = (place >= a) & (place < a + 4096)
        grid = np.zeros((len(sets), min(4096, shared - a)), np.float32)
        grid[of[own], place[own] - a] = 1
        out += grid[one] @ grid[two].T
    return out.astype(np.int64)


def _counted(share: Fraction, size: int):
    """(doc_id, h1, links): links of the texts of side 0 with those of side 1 of their class (among themselves, if none), and of side 1's core with side 0; copies counted."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        sets = list(shingle_sets(pa.array(pdf["text"]), size))
        # of rows that repeat an id, the one whose set is meant
        right = np.array([_set_hash(x) == h for x, h in zip(sets, pdf["h1"])], bool)
        pdf = pdf.assign(at=np.arange(len(pdf)))[right].drop_duplicates(["c", "doc_id", "h1", "side"])
        found = [(np.zeros(0, np.int64),) * 3]
        for _, g in pdf.groupby("c"):
            own = [sets[k] for k in g["at"]]
            rep, copies, side, h1, core = (g[k].to_numpy() for k in ("doc_id", "copies", "side", "h1", "core"))
            one, two = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
            two = two if len(two) else one
            if not len(one):
                continue
            both = common_counts(own, one, two)
            n = np.array([len(x) for x in own], np.int64)
            link = both * share.denominator >= (n[one][:, None] + n[two][None, :] - both) * share.numerator
            link &= (rep[one][:, None] != rep[two][None, :]) | (h1[one][:, None] != h1[two][None, :])
            inner = core[two].astype(bool)
            found += [(rep[one], h1[one], link @ copies[two]), (rep[two][inner], h1[two][inner], link[:, inner].T @ copies[one])]
        out = pd.DataFrame({k: np.concatenate([f[i] for f in found]) for i, k in enumerate(("doc_id", "h1", "links"))})
        return out.groupby(["doc_id", "h1"], as_index=False)["links"].sum().astype("int64")

    return work


def _cores(several: DataFrame, texts: DataFrame, size: int, t: Fraction) -> DataFrame:
    """(c, doc_id, d): members of large classes within t/2 of the pivot, of ``PIVOTS`` tried, that has most such members."""
    large = several.where(F.col("k") > COUNTED)
    most = PIVOTS * large.count()
    tried = [F.min(F.struct(F.xxhash64("h1", "h2", F.lit(i)).alias("h"), "doc_id"))["doc_id"].alias(f"p{i}") for i in range(PIVOTS)]
    pivots = large.groupBy("c").agg(*tried).select("c", F.explode(F.array_distinct(F.array(*[f"p{i}" for i in range(PIVOTS)]))).alias("p"))
    pairs = in_few(large.join(pivots, "c").select("c", F.col("doc_id").alias("a"), F.col("p").alias("b")).distinct(), "core-pairs", most)
    held = only_ids(texts, "doc_id", id_filter(pairs.select("a").union(pairs.select("b")), "a"))
    # an id with several texts is in no core: its distances differ
    near = measured(pairs.select("a", "b"), held, size, pairs.count()).groupBy("a", "b").agg(F.max(F.col("together") - F.col("common")).alias("apart"), F.min("together").alias("together"), F.count(F.lit(1)).alias("texts"))
    inside = in_few(pairs.join(near.where((F.col("texts") == 1) & (2 * t.denominator * F.col("apart") <= t.numerator * F.col("together"))), ["a", "b"]).select("c", "a", "b"), "cores", most)
    best = inside.groupBy("c", "b").agg(F.count(F.lit(1)).alias("m")).groupBy("c").agg(F.max(F.struct("m", "b"))["b"].alias("b"))
    return inside.join(best, ["c", "b"]).select("c", F.col("a").alias("doc_id"), F.lit(True).alias("core"))


def link_counts(rows: DataFrame, texts: DataFrame, size: int, share: Fraction) -> DataFrame:
    """(c, h1, h2, n_links): exact number of rows that each text of a class is linked with, itself aside.

    ``rows`` holds (doc_id, n, h1, h2, c). Equal sets are one, with their number of copies. Small classes are counted many to a group. Of a class of
    more than ``COUNTED`` different sets, those within t/2 of one pivot (the core) are linked to each other and counted by a sum; the others are
    compared with all, in pairs of blocks.
    """
    sets = rows.where("n > 0 and doc_id is not null").groupBy("c", "h1", "h2").agg(F.count(F.lit(1)).alias("copies"), F.min("doc_id").alias("doc_id"), F.first("n").alias("n"))
    n_rows = rows.count()
    sets = in_few(sets, "sets", n_rows)
    width = sets.groupBy("c").agg(F.count(F.lit(1)).alias("k")).where("k > 1")
    several = in_few(sets.join(width, "c"), "several", n_rows)
    known = texts.where("doc_id is not null")
    cores = _cores(several, known, size, 1 - share)
    several = in_few(several.join(cores, ["c", "doc_id"], "left").withColumn("core", F.coalesce("core", F.lit(False))), "cored", n_rows)
    groups = max(1, several.count() // COUNTED)
    large = F.col("k") > COUNTED
    row = ["c", "doc_id", "n", "h1", "copies", "core"]
    some = several.where(~large).select(*row, F.lit(0).alias("side"), F.lit(0).cast("long").alias("i"), F.lit(0).cast("long").alias("j"), F.concat(F.lit("b"), F.pmod(F.xxhash64("c"), F.lit(groups)).cast("string")).alias("g"))
    many = in_blocks(several.where(large).select(*row), "c", "not core", COUNTED).withColumn("g", F.concat(F.lit("c"), F.col("c").cast("string")))
    each = stage(some.unionByName(many), "counted")
    held = only_ids(known, "doc_id", id_filter(each, "doc_id"))
    found = each.join(held, "doc_id").groupBy("g", "i", "j").applyInPandas(lean_group(_counted(share, size)), "doc_id long, h1 long, links long")
    found = found.groupBy("doc_id", "h1").agg(F.sum("links").alias("links"))
    within = several.where("core").groupBy("c").agg(F.sum("copies").alias("within"))
    out = sets.join(found, ["doc_id", "h1"], "left").join(several.select("c", "h1", "h2", "core"), ["c", "h1", "h2"], "left").join(within, "c", "left")
    total = F.coalesce("links", F.lit(0)) + F.when(F.col("core"), F.col("within")).otherwise(F.col("copies")) - 1
    return out.select("c", "h1", "h2", total.cast("long").alias("n_links"))


def parted(rest: DataFrame, steps: list[DataFrame], named: DataFrame, resolved: Callable[[DataFrame, str], DataFrame], t: float) -> tuple[DataFrame, DataFrame]:
    """(cells, dense): what is left of large rests after recursion by pivots; links found on the way are added to ``steps``.

    ``rest`` holds (key, doc_id, n), ``named`` (doc_id, c) the classes of the links in ``steps``. ``cells``: (key, doc_id, n, c, home) of at most ``SMALL`` members;
    ``dense``: (key, doc_id, n, c, top) of those that windows don't part, with the largest class ``top``.

    Distances are intervals [lo, hi]. A member lives with the pivot of least hi; where no hi is known, with all such members. Let x live with
    pivot i, and y lie within t of x. Then d(y, p_i) <= t + d(x, p_i), so y lies within t of the region's radius; and d(y, p_i) - d(y, p_k) <= 2t + d(x, p_i) -
    d(x, p_k) for every pivot k, so its windows leave out no partner, whatever the intervals.
    """
    schema = "key long, doc_id long, n long, c long"
    spark = rest.sparkSession
    cells = [spark.createDataFrame([], f"{schema}, home boolean")]
    dense = [spark.createDataFrame([], f"{schema}, top long")]

    def classed(rows: DataFrame) -> DataFrame:
        return rows.drop("c").join(named, "doc_id", "left").withColumn("c", F.coalesce("c", "doc_id"))

    def opened(rows: DataFrame, name: str, most: int) -> DataFrame:
        """Rows of keys where someone at home meets another class, with the number of rows and the largest class of the key."""
        kinds = rows.groupBy("key", "c").agg(F.count(F.lit(1)).alias("k"), F.max("home").alias("host"))
        keys = kinds.groupBy("key").agg(F.sum("k").alias("members"), F.max(F.struct("k", "c"))["c"].alias("top"), F.count(F.lit(1)).alias("kinds"), F.max("host").alias("host")).where("kinds > 1 and host")
        return in_few(rows.drop("members", "top").join(keys.select("key", "members", "top"), "key"), name, most)

    live = opened(classed(rest.withColumn("home", F.lit(True))), "level-0", rest.count())
    for level in range(1, LEVELS + 1):
        small = F.col("members") <= SMALL
        cells.append(live.where(small).select("key", "doc_id", "n", "c", "home"))
        live = live.where(~small)
        held = live.count()
        if not held:
            break
        # pivots of random classes, so that small classes have theirs too
        salt = lambda c, i: F.xxhash64(c, "key", F.lit(level * PIVOTS + i))  # noqa: B023, E731
        tried = [F.min(F.struct(salt("c", i).alias("x"), salt("doc_id", i).alias("y"), "doc_id"))["doc_id"].alias(f"p{i}") for i in range(PIVOTS)]
        pivots = live.where("home").groupBy("key").agg(*tried).select("key", F.explode(F.array_distinct(F.array(*[f"p{i}" for i in range(PIVOTS)]))).alias("p"))
        met = live.join(pivots, "key").withColumns({"a": F.greatest("doc_id", "p"), "b": F.least("doc_id", "p")})
        met = in_few(met.select("key", "doc_id", "n", "home", "p", "a", "b"), f"level-{level}-met", PIVOTS * held)
        tested = resolved(met.where("a != b").select("a", "b").distinct(), f"level-{level}", PIVOTS * held)
        steps.append(tested.where("link").select("a", "b"))
        named = stage(components(functools.reduce(DataFrame.unionByName, steps)), "level-classes").select(F.col("node").alias("doc_id"), F.col("component").alias("c"))

        own = F.col("a") == F.col("b")
        far = met.join(tested, ["a", "b"], "left").select("key", "doc_id", "n", "home", "p", *[F.when(own, 0.0).otherwise(F.col(c)).alias(c) for c in ("lo", "hi")])
        near = far.groupBy("key", "doc_id").agg(F.min(F.struct("hi", "lo", "p")).alias("near"), F.min("lo").alias("least"))
        far = in_few(far.join(near, ["key", "doc_id"]).withColumn("lives", F.col("home") & (F.col("p") == F.col("near.p")) & (F.col("hi") < 1)), f"level-{level}-distances", PIVOTS * held)
        bounds = far.where("lives").groupBy("key", "p").agg(F.max("hi").alias("radius"), F.max(F.col("hi") - F.col("least")).alias("slack"))
        window = (F.col("lo") <= F.col("radius") + t) & (F.col("lo") - F.col("near.hi") <= 2 * t + F.col("slack"))
        inside = far.join(bounds, ["key", "p"]).where(F.col("lives") | window)
        lone = far.where(~F.col("home") | (F.col("near.hi") >= 1)).select("key", "doc_id", "n", "home").distinct()
        row = ["doc_id", "n", F.col("key").alias("parent")]
        parts = inside.select(*row, F.xxhash64("key", "p").alias("key"), F.col("lives").alias("home")).unionByName(lone.select(*row, F.xxhash64("key", F.lit("lone")).alias("key"), "home"))
        parts = opened(classed(parts), f"level-{level}-parts", (PIVOTS + 1) * held)

        after = parts.groupBy("parent").agg(F.count(F.lit(1)).alias("rows"), F.max("members").alias("widest"))
        grown = live.select(F.col("key").alias("parent"), "members").distinct().join(after, "parent")
        whole = (F.col("rows") > SPREAD * F.col("members")) | (F.col("widest") > 0.8 * F.col("members")) | F.lit(level == LEVELS)
        grown = in_few(grown.select("parent", whole.alias("whole")), f"level-{level}-growth", held)
        left = live.join(grown.where("whole").select(F.col("parent").alias("key")), "key", "left_semi")
        dense.append(opened(classed(left), f"level-{level}-dense", held).select("key", "doc_id", "n", "c", "top"))
        live = in_few(parts.join(grown.where("not whole").select("parent"), "parent", "left_semi").drop("parent"), f"level-{level}", (PIVOTS + 1) * held)
    join = lambda parts: functools.reduce(DataFrame.unionByName, parts)
    return stage(classed(join(cells)), "small-cells"), stage(join(dense), "dense")


def similar_classes(docs: DataFrame, size: int = 5, share: tuple[int, int] = (3, 4), count_links: bool = False) -> DataFrame:
    """Classes of texts joined by links of Jaccard similarity ``share`` or more.

    Args: ``docs`` with ``doc_id`` and ``text``; further columns are ignored.
    Returns one row per row of ``docs``: ``doc_id``, ``n_shingles``, ``component_id`` (the least id reachable by links); with ``count_links`` also ``n_links``,
    the exact number of rows that the text is linked with (copies counted, itself not).

    Null or empty text, or text of separators only: no shingles, a class of its own, no links. Texts of fewer than ``size``
    words are one shingle. Rows that repeat an id are one node, linked by any of its texts. Null ids
    link with nothing and get a null class. An empty table gives an empty result.
    """
    small_batches(docs.sparkSession)
    need = Fraction(*share)
    t = 1 - need
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    facts = stage(_facts(texts, size), "facts")
    counts = merged(facts.where("cells is not null").select("slice", "cells"), np.dtype(np.int64), np.add, CELLS)
    facts = facts.where("cells is null").drop("slice", "cells")

    # equal sets are one: its least id stands for all
    known = facts.where("n > 0 and doc_id is not null").select("doc_id", "n", "h1", "h2")
    sets = known.groupBy("n", "h1", "h2").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("rows"))
    n_docs = facts.count()
    sets = in_few(sets, "reps", n_docs)
    copies = in_few(known.join(sets.where("rows > 1"), ["n", "h1", "h2"]).where("doc_id != rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b")).distinct(), "copies", n_docs)

    w = Window.partitionBy("key")
    region = _regions(texts, size, need, counts, id_filter(sets, "rep"))
    region = region.withColumn("p", F.min(F.struct("doc_id", "n")).over(w)).withColumn("members", F.count(F.lit(1)).over(w))
    region = stage(region.where("members > 1").select("key", "doc_id", "n", F.col("p.doc_id").alias("p"), F.col("p.n").alias("pn")), "regions")

    maps = facts.where("doc_id is not null").select("doc_id", "n", "odd")
    near = texts.where("doc_id is not null")
    eps = 1e-9

    def resolved(pairs: DataFrame, name: str, rows: int | None = None) -> DataFrame:
        """Pairs with the interval [lo, hi] of their distance, which is one exact value wherever a link is possible."""
        pairs = in_few(pairs, f"{name}-pairs", rows)
        rows = pairs.count()
        some = maps if name == "all" else only_ids(maps, "doc_id", id_filter(pairs.select("a").union(pairs.select("b")), "a"))
        # |x sym y| <= (1-s)/(1+s) (|x|+|y|) for every pair of similarity s or more
        may = F.col("least") * (need.denominator + need.numerator) <= (F.col("na") + F.col("nb")) * (need.denominator - need.numerator)
        low = 2 * F.col("least") / (F.col("na") + F.col("nb") + F.col("least"))
        bound = bounded(pairs, some, rows).select("a", "b", may.alias("may"), low.alias("low"))
        bound = in_few(bound.groupBy("a", "b").agg(F.max("may").alias("may"), F.min("low").alias("low"), F.count(F.lit(1)).alias("texts")), f"{name}-bounds", rows)
        left = bound.where("may").select("a", "b")
        held = only_ids(near, "doc_id", id_filter(left.select("a").union(left.select("b")), "a"))
        exact = measured(left, held, size, left.count()).groupBy("a", "b").agg(F.min(1 - F.col("common") / F.col("together")).alias("d"), F.max(F.col("common") * need.denominator >= F.col("together") * need.numerator).alias("link"))
        # an id of several texts is no point of the metric: its distances say nothing of others
        one = F.col("texts") == 1
        bound = bound.join(exact, ["a", "b"], "left").select("a", "b", F.when(one, F.coalesce("d", "low")).otherwise(0.0).alias("lo"), F.when(one, F.coalesce("d", F.lit(1.0))).otherwise(1.0).alias("hi"), F.coalesce("link", F.lit(False)).alias("link"))
        return in_few(bound, f"{name}-distances", rows)

    n_region = region.count()
    others = region.where(F.col("doc_id") != F.col("p"))
    fits = (F.col("n") * need.denominator >= F.col("pn") * need.numerator) & (F.col("pn") * need.denominator >= F.col("n") * need.numerator)
    met = in_few(others.select(F.col("doc_id").alias("a"), F.col("p").alias("b"), "n", "pn", fits.alias("fits")).distinct(), "met", n_region)
    n_met = met.count()
    tested = resolved(met.where("fits").select("a", "b"), "pivot", n_met)
    linked = tested.where("link")

    # what is one class already needs no further test
    first = in_few(components(linked.select("a", "b")), "first-classes", n_docs)
    status = met.join(tested, ["a", "b"], "left").join(first.select(F.col("node").alias("a"), F.col("component").alias("c")), "a", "left").join(first.select(F.col("node").alias("b"), F.col("component").alias("pc")), "b", "left")
    status = status.withColumn("c", F.coalesce("c", "a")).withColumn("pc", F.coalesce("pc", "b"))
    # beyond a factor 3/4 in size no distance was computed; the sizes bound it from below
    status = status.withColumn("lo", F.coalesce("lo", 1 - F.least("n", "pn") / F.greatest("n", "pn"))).withColumn("hi", F.coalesce("hi", F.lit(1.0)))
    status = status.withColumn("inside", F.coalesce("link", F.lit(False))).withColumn("open", F.col("c") != F.col("pc"))
    status = status.withColumn("edge", F.col("open") & (F.col("lo") <= 2 * float(t) + eps)).withColumn("pair", F.xxhash64("a", "b"))
    status = in_few(status.select("a", "b", "pair", "lo", "hi", "inside", "c", "open", "edge"), "status", n_met)

    # only regions that hold a pair of two classes go on: found by bit maps of fixed size, so that the others' rows never move
    opened = only_ids(others.withColumn("pair", F.xxhash64("doc_id", "p")), "pair", id_filter(status.where("open"), "pair"))
    opened = stage(opened.select("key"), "opened")
    live = only_ids(others, "key", id_filter(opened, "key"))
    far = in_few(live.join(status.withColumnRenamed("a", "doc_id").withColumnRenamed("b", "p"), ["doc_id", "p"]), "rings", n_region)
    count = lambda c: F.sum(F.when(c, 1).otherwise(0))
    keys = far.groupBy("key").agg(count(F.col("open")).alias("opens"), count(F.col("edge")).alias("edges")).where("opens > 0")
    # members of the ball matter only where the ring between t and 2t has someone of another class
    rest = far.join(keys, "key").where(F.col("open") | ~F.col("inside") | (F.col("edges") > 0))
    total = lambda h: F.sum(h.cast("decimal(20,0)"))
    width = rest.groupBy("key").agg(F.count(F.lit(1)).alias("others"), total(F.xxhash64("doc_id", "n", "inside")).alias("like"), total(F.xxhash64("inside", "n", "doc_id", F.lit(1))).alias("like2"))
    # regions of the same members are one; sums tell rows that stand twice from none, and decimals don't overflow
    width = width.where("others > 1").groupBy("like", "like2", "others").agg(F.min("key").alias("key"))
    rest = in_few(rest.join(width.select("key", "others"), "key"), "rest", n_region)
    steps = [linked.select("a", "b")]
    cells, dense = parted(rest.where(F.col("others") > SMALL).select("key", "doc_id", "n"), steps, first.select(F.col("node").alias("doc_id"), F.col("component").alias("c")), resolved, float(t) + eps)

    few = rest.where(F.col("others") <= SMALL)
    u = few.where("open").select("key", F.col("doc_id").alias("a"), F.col("n").alias("na"), F.col("lo").alias("la"), F.col("hi").alias("ha"), F.col("c").alias("ca"))
    y = few.select("key", F.col("doc_id").alias("b"), F.col("n").alias("nb"), F.col("lo").alias("lb"), F.col("hi").alias("hb"), F.col("inside").alias("ball"), F.col("c").alias("cb"))
    window = (F.col("la") - F.col("hb") <= float(t) + eps) & (F.col("lb") - F.col("ha") <= float(t) + eps)
    close = window & (~F.col("ball") | (F.col("la") <= 2 * float(t) + eps)) & (F.col("na") * need.denominator >= F.col("nb") * need.numerator) & (F.col("nb") * need.denominator >= F.col("na") * need.numerator)
    extra = u.join(y, "key").where(close & (F.col("ca") != F.col("cb"))).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    fit = (F.col("na") * need.denominator >= F.col("nb") * need.numerator) & (F.col("nb") * need.denominator >= F.col("na") * need.numerator)
    left = cells.select("key", F.col("doc_id").alias("a"), F.col("n").alias("na"), F.col("c").alias("ca"), F.col("home").alias("ha"))
    right = cells.select("key", F.col("doc_id").alias("b"), F.col("n").alias("nb"), F.col("c").alias("cb"), F.col("home").alias("hb"))
    inner = left.join(right, "key").where((F.col("a") > F.col("b")) & (F.col("ca") != F.col("cb")) & (F.col("ha") | F.col("hb")) & fit).select("a", "b").distinct()

    blocks = stage(in_blocks(dense, "key", "c != top", BLOCK).drop("n", "top").distinct(), "blocks")
    held = only_ids(maps, "doc_id", id_filter(blocks, "doc_id"))
    blocks = blocks.join(held, "doc_id").groupBy("key", "i", "j").applyInPandas(lean_group(_block_pairs(need)), "a long, b long")
    found = resolved(extra.unionByName(inner).unionByName(blocks).distinct(), "rest").where("link").select("a", "b")

    links = copies.unionByName(found)
    for step in steps:
        links = links.unionByName(step)
    classes = components(links)
    out = facts.join(classes.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("c", F.coalesce("component", "doc_id"))
    base = [F.col("doc_id"), F.col("n").alias("n_shingles"), F.col("c").alias("component_id")]
    if not count_links:
        return out.select(*base)
    out = in_few(out.select("doc_id", "n", "h1", "h2", "c"), "members", n_docs)
    counted = link_counts(out, texts, size, need)
    return out.join(counted, ["c", "h1", "h2"], "left").select(*base, F.when(F.col("n") > 0, F.coalesce("n_links", F.lit(0))).otherwise(F.lit(0)).cast("long").alias("n_links"))


def one_per_class(docs: DataFrame, size: int = 5, share: tuple[int, int] = (3, 4)) -> DataFrame:
    """``docs`` without the rows whose class holds a smaller id; columns unchanged.

    Rows with a null id stay. Of rows that repeat an id all stay or go together.
    """
    classes = similar_classes(docs, size, share).where("doc_id is not null and doc_id != component_id").select("doc_id").distinct()
    gone = stage(classes, "superseded").withColumnRenamed("doc_id", "_superseded")
    return docs.join(gone, docs["doc_id"] == gone["_superseded"], "left_anti")
