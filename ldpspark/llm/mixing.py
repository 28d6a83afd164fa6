"""Mixing sources to target weights by systematic sampling, in DataFrame operations only."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ldpspark.llm.staging import stage

#: Fixed pattern: a word is a run of anything but the separators 0x20 and 0x09-0x0D.
WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (1, 2, 3)
LIMIT = 3
STRIDE = 4096


def source_targets(totals: DataFrame, weights: tuple[int, ...] = WEIGHTS, limit: int = LIMIT) -> DataFrame:
    """Adds ``target`` to (skey, source_size): shares by weight of all sizes, none above ``limit`` times its source.

    The sources that stop at their limit are those of least limit per weight: along that order, a source stops
    if its limit is at most its share of what the stopped ones before it leave. One row per source is
    ordered here, documents are not.
    """
    by_name = Window.orderBy("skey")
    every = Window.partitionBy()
    t = totals.withColumn("w", F.element_at(F.array(*[F.lit(x) for x in weights]), (F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1).cast("int")))
    t = t.withColumn("cap", F.col("source_size") * limit).withColumn("words", F.sum("source_size").over(every)).withColumn("weights", F.sum("w").over(every))
    line = Window.orderBy(F.col("cap") / F.col("w"), "skey").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    t = t.withColumn("caps", F.sum("cap").over(line)).withColumn("ws", F.sum("w").over(line))
    left = F.col("words") - (F.col("caps") - F.col("cap"))
    rest = F.col("weights") - (F.col("ws") - F.col("w"))
    t = t.withColumn("stops", F.col("cap") * rest <= left * F.col("w"))
    t = t.withColumn("stopped", F.sum(F.when(F.col("stops"), F.col("cap")).otherwise(0)).over(every)).withColumn("going", F.sum(F.when(F.col("stops"), 0).otherwise(F.col("w"))).over(every))
    share = (F.col("words") - F.col("stopped")).cast("double") * F.col("w") / F.greatest(F.col("going"), F.lit(1))
    return t.select("skey", "source_size", F.when(F.col("stops"), F.col("cap").cast("double")).otherwise(share).alias("target"))


def mixed(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, limit: int = LIMIT, seed: str = "mix") -> DataFrame:
    """Size, target and copies of each document: ``doc_id``, ``source``, ``size``, ``source_size``, ``target``, ``copies``, ``taken``.

    Within a source all documents have the same expected number of copies, target over source size. Along the order by
    size and id, the sum of these before and after a document, plus the source's one offset,
    crosses some whole numbers: so often the document is taken. Neighbours have near sizes, hence the words taken come
    near the target. The place in the order is found from counts: of sizes within the source, of id
    ranges within a size, and of ids within such a range, so that no task sees more than a range.

    Null text has size 0; a null source is a source of its own, after all others; null ids come last. Rows
    that repeat an id are taken each for itself. A source without words has target 0. Further columns are ignored. Reruns agree.
    """
    base = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("source").cast("string").alias("source"),
        F.coalesce(F.regexp_count(F.col("text").cast("string"), F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
    ).withColumn("skey", F.when(F.col("source").isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), "source")))
    base = base.withColumn("span", F.coalesce(F.floor(F.col("doc_id") / STRIDE), F.lit((1 << 63) - 1)))
    base = stage(base, "sizes")
    bins = stage(base.groupBy("skey", "size", "span").agg(F.count(F.lit(1)).alias("n")), "spans")
    sizes = stage(bins.groupBy("skey", "size").agg(F.sum("n").alias("n")), "source-sizes")
    totals = sizes.groupBy("skey").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"))
    targets = stage(source_targets(totals, weights, limit), "targets")

    upto = lambda *by: Window.partitionBy(*by).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    lower = sizes.select("skey", "size", (F.sum("n").over(upto("skey").orderBy("size")) - F.col("n")).alias("lower"))
    earlier = bins.select("skey", "size", "span", (F.sum("n").over(upto("skey", "size").orderBy("span")) - F.col("n")).alias("earlier"))
    offsets = earlier.join(lower, ["skey", "size"]).join(targets, "skey")
    nth = F.row_number().over(Window.partitionBy("skey", "size", "span").orderBy(F.col("doc_id").asc_nulls_last()))
    placed = base.withColumn("nth", nth).join(offsets, ["skey", "size", "span"])

    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    offset = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), "skey")), 1, 5), 16, 10).cast("double") / float(1 << 20)
    place = F.col("lower") + F.col("earlier") + F.col("nth")
    placed = placed.withColumn("rate", rate).withColumn("offset", offset).withColumn("place", place.cast("double"))
    copies = F.floor(F.col("place") * F.col("rate") + F.col("offset")) - F.floor((F.col("place") - 1) * F.col("rate") + F.col("offset"))
    placed = placed.withColumn("copies", F.least(copies, F.lit(limit)).cast("long"))
    return placed.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mixed_documents(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, limit: int = LIMIT, seed: str = "mix") -> DataFrame:
    """The mix itself: each row of ``docs`` as often as it is taken, with its own columns.

    Rows that agree in id, source and size share the copies that ``mixed`` gives them, dealt out by the order of their texts. Without such
    rows the texts move once, to meet their number of copies.
    """
    plan = mixed(docs, weights, limit, seed).groupBy(F.col("doc_id").alias("id"), F.col("source").alias("origin"), F.col("size").alias("words"))
    plan = stage(plan.agg(F.sum("copies").alias("copies"), F.count(F.lit(1)).alias("rows")).where("copies > 0"), "copies")
    text = F.col("text").cast("string")
    size = F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")
    # the row travels as one struct, so that none of its names meets one of ours
    own = docs.select(F.col("doc_id").cast("long").alias("own_id"), F.col("source").cast("string").alias("own_origin"), size.alias("own_words"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    match = own["own_id"].eqNullSafe(plan["id"]) & own["own_origin"].eqNullSafe(plan["origin"]) & (own["own_words"] == plan["words"])
    single, repeated = plan.where("rows = 1"), plan.where("rows > 1")
    # one plan at every size: by sort and merge, never by a broadcast of the plan, which grows with the documents
    taken = own.join(single.hint("merge"), match).select("row", "copies")
    if not repeated.isEmpty():
        several = own.join(repeated.hint("merge"), match)
        nth = F.row_number().over(Window.partitionBy("id", "origin", "words").orderBy(F.col("row.text").cast("string")))
        share = F.floor(F.col("copies") / F.col("rows")) + F.when(nth <= F.col("copies") % F.col("rows"), 1).otherwise(0)
        taken = taken.unionByName(several.select("row", share.cast("long").alias("copies")).where("copies > 0"))
    return taken.select("row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select("row.*")


ORACLE = r"""
WITH b AS (
  SELECT doc_id, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         CASE WHEN source IS NULL THEN '1' ELSE '0' || source END AS skey FROM documents),
s AS (SELECT skey, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY skey COLLATE C) AS rn FROM b GROUP BY skey),
w AS (SELECT skey, source_size, 3 * source_size AS cap, (rn - 1) % 3 + 1 AS w,
             sum(source_size) OVER () AS t, sum((rn - 1) % 3 + 1) OVER () AS ws FROM s),
walk AS (SELECT *, coalesce(sum(cap) OVER o, 0) AS caps, coalesce(sum(w) OVER o, 0) AS seen FROM w
         WINDOW o AS (ORDER BY cap::DOUBLE / w, skey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
stop AS (SELECT *, cap * (ws - seen) <= (t - caps) * w AS stops FROM walk),
level AS (SELECT *, sum(CASE WHEN stops THEN cap ELSE 0 END) OVER () AS c, sum(CASE WHEN stops THEN 0 ELSE w END) OVER () AS v FROM stop),
target AS (SELECT skey, source_size, CASE WHEN stops THEN cap::DOUBLE ELSE (t - c)::DOUBLE * w / greatest(v, 1) END AS target FROM level),
r AS (SELECT b.doc_id, b.size, g.source_size, g.target,
             row_number() OVER (PARTITION BY b.skey ORDER BY b.size, b.doc_id NULLS LAST)::DOUBLE AS place,
             CASE WHEN g.source_size > 0 THEN g.target / g.source_size ELSE 0 END AS rate,
             cast('0x' || substr(md5('mix|' || b.skey), 1, 5) AS BIGINT)::DOUBLE / 1048576 AS u
      FROM b JOIN target g USING (skey))
SELECT doc_id, size, source_size, target,
       size * least(floor(place * rate + u) - floor((place - 1) * rate + u), 3)::BIGINT AS taken FROM r
"""
