"""Benchmark decontamination by spaced seeds, in DataFrame functions only.

A seed is a window of words of which a fixed mask leaves some out. Training and test seeds with equal hashes are hits; around every
hit the item is laid along the document, and the document is contaminated if some window of the item
(13 words, or all of a shorter item) agrees with it but for the tolerated substitutions.

Defined cases: words are lower-cased and split at white space; null or empty texts have no words; an item with fewer words
than the span of the masks is searched by masks of its own length, which leave out as many words as may be substituted; items with fewer words than
LEAST_WORDS are no passages and never match, nor do documents without words; documents that share a doc_id share their decision; a null doc_id is never
contaminated; repeated items and rows count once; extra columns are ignored; empty tables give no hits.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, small_or_plain, table

#: Fixed masks over windows of words: 1 counts, 0 is ignored. By enumeration, any two substituted words of 13 leave a hit, and any one of 9 to 12.
MASKS = ("101001111", "011110101", "110111010")
WINDOW, SUBSTITUTIONS = 13, 2
#: Words of the shortest item that can contaminate a document.
LEAST_WORDS = 2


def words(text: Column) -> Column:
    w = F.split(F.trim(F.translate(F.lower(F.coalesce(text.cast("string"), F.lit(""))), "\t\n\x0b\f\r", "     ")), " +")
    return F.when(F.element_at(w, 1) == "", F.array().cast("array<string>")).otherwise(w)


def _hashes(w: Column) -> Column:
    return F.transform(w, lambda x: F.xxhash64(x))


def seeds(rows: DataFrame, key: str, masks=MASKS) -> DataFrame:
    """(key, at, seed) for every window of ``h``, an array of word hashes, and every mask; at counts from 0."""
    span = len(masks[0])
    n = F.greatest(F.size("h") - span + 1, F.lit(0))
    shifted = [F.slice("h", F.lit(j + 1), n).alias(f"w{j}") for j in range(span)]
    wide = rows.where(F.size("h") >= span).select(key, F.posexplode(F.arrays_zip(*shifted)).alias("at", "w"))
    hashed = [F.xxhash64(F.lit(i), *[F.col(f"w.w{j}") for j, bit in enumerate(mask) if bit == "1"]) for i, mask in enumerate(masks)]
    return wide.select(key, "at", F.explode(F.array(*hashed)).alias("seed"))


def _own_masks(k: int, window: int, substitutions: int) -> list[tuple[int, ...]]:
    """Items of ``k`` words, fewer than the span: the places that count, for every set of words that may be substituted."""
    return list(combinations(range(k), k - min(k, window) * substitutions // window))


def hits(docs: DataFrame, items: DataFrame, masks=MASKS, window: int = WINDOW, substitutions: int = SUBSTITUTIONS, least_words: int = LEAST_WORDS) -> DataFrame:
    """Distinct (doc_id, item_id, shift): the item's word 0 lies at the document's word ``shift``."""
    d = docs.select("doc_id", _hashes(words(F.col("text"))).alias("h"))
    i = items.select("item_id", _hashes(words(F.col("text"))).alias("h")).where(F.size("h") >= least_words)
    wanted = materialise(seeds(i, "item_id", masks).select("item_id", F.col("at").alias("offset"), "seed").distinct())
    found = seeds(d, "doc_id", masks).join(small_or_plain(wanted), "seed")
    out = found.select("doc_id", "item_id", (F.col("at") - F.col("offset")).alias("shift"))
    span = len(masks[0])
    short = materialise(i.where((F.size("h") > 0) & (F.size("h") < span)).select("item_id", F.size("h").alias("len"), "h"))
    for row in short.select("len").distinct().collect():  # at most one pass for each length below the span
        k = row.len
        seed = F.explode(F.array(*[F.xxhash64(F.lit(-1 - n), *[F.element_at("h", F.col("p") + F.lit(j + 1)) for j in places]) for n, places in enumerate(_own_masks(k, window, substitutions))])).alias("seed")
        own = materialise(short.where(F.col("len") == k).withColumn("p", F.lit(0)).select("item_id", seed).distinct())
        at = d.where(F.size("h") >= k).select("doc_id", "h", F.explode(F.sequence(F.lit(0), F.size("h") - k)).alias("p")).select("doc_id", "p", seed)
        out = out.union(at.join(small_or_plain(own), "seed").select("doc_id", "item_id", F.col("p").alias("shift")))
    return out.where("doc_id IS NOT NULL").distinct()


def _windows_ok(match: Column, size: Column, window: int, substitutions: int) -> Column:
    """True if some ``window`` neighbours (all, if fewer) of a 0/1 array hold enough ones."""
    w = F.least(size, F.lit(window))
    # with fewer words than the window, the tolerance shrinks in proportion
    slack = F.floor(w * substitutions / window)
    starts = F.sequence(F.lit(1), size - w + 1)
    return F.exists(starts, lambda s: F.aggregate(F.slice(match, s, w), F.lit(0), lambda a, x: a + x) >= w - slack)


def overlaps(docs: DataFrame, items: DataFrame, masks=MASKS, window: int = WINDOW, substitutions: int = SUBSTITUTIONS, least_words: int = LEAST_WORDS) -> DataFrame:
    """(doc_id, item_id, matched, item_words): confirmed overlaps, with the most equal words along any shift."""
    h = materialise(hits(docs, items, masks, window, substitutions, least_words))
    near = h.select("doc_id").distinct()
    near = materialise(near)
    d = docs.join(small_or_plain(near), "doc_id", "left_semi").select("doc_id", _hashes(words(F.col("text"))).alias("d"))
    i = items.select("item_id", _hashes(words(F.col("text"))).alias("i"))
    laid = h.join(d, "doc_id").join(i, "item_id")
    equal = F.transform("i", lambda x, p: F.coalesce((F.get("d", p + F.col("shift")) == x).cast("int"), F.lit(0)))
    laid = laid.select("doc_id", "item_id", equal.alias("match"), F.size("i").alias("size"))
    ok = laid.where(_windows_ok(F.col("match"), F.col("size"), window, substitutions))
    matched = F.aggregate("match", F.lit(0), lambda a, x: a + x)
    return ok.groupBy("doc_id", "item_id").agg(F.max(matched).alias("matched"), F.max("size").alias("item_words"))


def op8_spaced_seed_decontam(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row a document: whether it is contaminated, by how many items, and the least such item."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    items = table(spark, sf_dir, "benchmark").select("item_id", "text")
    found = overlaps(docs, items).groupBy("doc_id").agg(F.count("*").alias("n_items"), F.min("item_id").alias("first_item"), F.max("matched").alias("most_matched"))
    found = materialise(found)
    rows = docs.select("doc_id").join(small_or_plain(found), "doc_id", "left")
    return rows.select("doc_id", F.col("n_items").isNotNull().alias("contaminated"), F.coalesce("n_items", F.lit(0).cast("long")).alias("n_items"), "first_item", F.coalesce(F.col("most_matched").cast("long"), F.lit(0).cast("long")).alias("most_matched"))


def drop_contaminated(docs: DataFrame, items: DataFrame) -> DataFrame:
    """Pipeline form: contaminated documents go, the others stay as they are."""
    gone = materialise(overlaps(docs.select("doc_id", "text"), items.select("item_id", "text")).select("doc_id").distinct())
    return docs.join(small_or_plain(gone), "doc_id", "left_anti").select(docs.columns)


_WORDS = "SELECT {0}, list_filter(regexp_split_to_array(trim(translate(lower(coalesce(text, '')), chr(9) || chr(10) || chr(11) || chr(12) || chr(13), '     ')), ' +'), lambda x: x <> '') AS ws FROM {1}".format

#: Every shift of every item along every document that shares a word with it there; no seeds, so that it tells whether the seeds miss anything.
ORACLE = f"""
WITH d AS (SELECT doc_id, unnest(ws) AS w, generate_subscripts(ws, 1) AS pos FROM ({_WORDS("doc_id", "documents")})),
i AS (SELECT item_id, len(ws) AS size, unnest(ws) AS w, generate_subscripts(ws, 1) AS pos FROM ({_WORDS("item_id", "benchmark")}) WHERE len(ws) >= {LEAST_WORDS}),
laid AS (SELECT doc_id, item_id, any_value(size) AS size, list(i.pos ORDER BY i.pos) AS p, count(*) AS matched FROM d JOIN i ON d.w = i.w GROUP BY doc_id, item_id, d.pos - i.pos
  HAVING count(*) >= least(any_value(size), {WINDOW}) - least(any_value(size), {WINDOW}) * {SUBSTITUTIONS} // {WINDOW}),
sized AS (SELECT *, least(size, {WINDOW}) AS wide, least(size, {WINDOW}) - least(size, {WINDOW}) * {SUBSTITUTIONS} // {WINDOW} AS need FROM laid),
found AS (SELECT doc_id, item_id, max(matched) AS matched FROM sized WHERE len(list_filter(range(1, matched - need + 2), lambda k: p[k + need - 1] - p[k] < wide)) > 0 GROUP BY 1, 2),
told AS (SELECT doc_id, count(*) AS n_items, min(item_id) AS first_item, max(matched) AS most_matched FROM found GROUP BY 1)
SELECT documents.doc_id, n_items IS NOT NULL AS contaminated, coalesce(n_items, 0)::BIGINT AS n_items, first_item, coalesce(most_matched, 0)::BIGINT AS most_matched FROM documents LEFT JOIN told ON documents.doc_id = told.doc_id
"""
