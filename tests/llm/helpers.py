"""Brute-force versions and small tables."""

from __future__ import annotations

import random
import re

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
SF = "/root/testdata/sf0.001"


CROWD = (
    "key n h _id _part shard_ component slice cells th size norm row part nth before number o0 o1 own_id own_origin own_words copies rows words id origin "
    "cuts own _row _nth _before _copies _copy _len _size _rows _cuts _source _score0 _superseded _th score c a b p pn members start end skey span"
).split()


def docs(spark, rows):
    """rows: (doc_id, text[, source])."""
    full = [(r[0], r[1], "en", r[2] if len(r) > 2 else "src0", len(r[1]) if r[1] is not None else None) for r in rows]
    return spark.createDataFrame(full, DOCS)


def crowded(df):
    """The same rows with further columns whose names the operators use inside."""
    from pyspark.sql import functions as F

    return df.withColumns({c: F.lit(1) for c in CROWD})


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text)


def shingles(text, k=5):
    words = [w for w in re.split(r"[\x20\x09-\x0d]+", lower(text or "")) if w]
    if len(words) < k:
        return {tuple(words)} if words else set()
    return {tuple(words[i : i + k]) for i in range(len(words) - k + 1)}


def classes(rows, a=3, b=4):
    """{id: least id reachable by links of similarity a/b or more}."""
    sets = [(i, shingles(t)) for i, t in rows if i is not None]
    root = {i: i for i, _ in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for n, (i, x) in enumerate(sets):
        for j, y in sets[:n]:
            if x and y and b * len(x & y) >= a * len(x | y):
                p, q = sorted((find(i), find(j)))
                root[q] = p
    return {i: find(i) for i in root}


def words(n, seed, vocabulary=400):
    rng = random.Random(seed)
    return [f"w{rng.randrange(vocabulary)}" for _ in range(n)]
