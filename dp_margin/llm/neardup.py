"""Near-duplicate groups: super-minwise signatures, banding, verification on full sets, union-find grouping.

1. One Arrow pass sketches every text. Exact copies (equal word sequences) fold into their smallest doc_id.
2. In every band bucket, members are compared with the bucket's smallest member only: a star, never all pairs.
   Links are confirmed on the full shingle sets, and grouped by union-find within partitions and then by
   alternating star contraction between them.
3. Buckets whose members lie in more than one group hold the pairs that are left. While these are many, stars around
   other centres join more groups; in the end every left pair that sizes and parities can't exclude is compared.

Defined cases: null or empty text, or one without words: an empty set, linked with nothing; a null doc_id is linked with
nothing, its component is null and it is kept; repeated rows are copies; rows that share a doc_id are linked by any of
their texts; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, hot_join, materialise, small_or_plain, table, utf8
from .words import SHINGLE, band_hashes, shingles, super_minhash, word_hashes

#: 40 bands of 5 rows miss a link of similarity 0.75 with probability 2e-5, one of 0.8 with 1e-7.
BANDS, ROWS = 40, 5
SIMILARITY = 75
#: Texts of one numpy run inside a batch, in bytes.
RUN_BYTES = 1 << 20
#: 64-bit words of a text's parities.
PARITY_WORDS = 16
#: Left pairs a document above which more stars go first (a matter of speed only).
LEFT_PER_DOC, MOST_STARS = 200, 2


def runs(texts: list, most: int = RUN_BYTES):
    """(from, to) of runs of texts (or of ranges as long as they are) with bounded bytes; a longer text is a run of its own."""
    start = size = 0
    for i, t in enumerate(texts):
        if size and size + len(t) > most:
            yield start, i
            start, size = i, 0
        size += len(t)
    if start < len(texts):
        yield start, len(texts)


def parity(d: np.ndarray, e: np.ndarray, texts: int) -> np.ndarray:
    """(texts, PARITY_WORDS) of int64: for every hash bucket, whether a text has an odd number of shingles in it.

    Two sets differ in at least as many shingles as their parities differ in bits: an exact bound, with no sampling in it.
    """
    places = PARITY_WORDS * 64
    odd = np.bincount(d * places + (e & np.uint64(places - 1)).astype(np.int64), minlength=texts * places) & 1
    return np.packbits(odd.astype(np.uint8).reshape(texts, places), axis=1, bitorder="little").view("<i8").astype(np.int64)


def _lists(rows: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(0, rows.size + 1, rows.shape[1], dtype=np.int32)), pa.array(rows.ravel()))


def _may_link(similarity: int):
    """Sizes and parities of u and v leave a link possible: |u| and |v| are close, and no more shingles differ than the similarity allows."""
    differ = reduce(lambda a, b: a + b, [F.bit_count(F.get("bu", F.lit(i)).bitwiseXOR(F.get("bv", F.lit(i)))) for i in range(PARITY_WORDS)])
    sizes = F.least("nu", "nv") * 100 >= F.greatest("nu", "nv") * similarity
    return sizes & (differ * (100 + similarity) <= (F.col("nu") + F.col("nv")) * (100 - similarity))


def possible(pairs: DataFrame, marks: DataFrame, similarity: int) -> DataFrame:
    """Pairs (u, v) that may be links, by marks (doc_id, n, bits); v may be the centre of many pairs."""
    u = marks.select(F.col("doc_id").alias("u"), F.col("n").alias("nu"), F.col("bits").alias("bu"))
    v = marks.select(F.col("doc_id").alias("v"), F.col("n").alias("nv"), F.col("bits").alias("bv"))
    return hot_join(pairs, v, "v", "u").join(u, "u").where(_may_link(similarity)).select("u", "v").distinct()


def _sketch(bands: int, rows: int):
    def run(batches):
        for b in batches:
            ids, texts = b.column(0), utf8(b.column(1))
            for lo, hi in runs(texts):
                h, counts = word_hashes(texts[lo:hi])
                d, e, seq = shingles(h, counts)
                n = np.bincount(d, minlength=hi - lo)
                other = np.zeros(hi - lo, np.uint64)
                np.add.at(other, d, e)
                odd = parity(d, e, hi - lo)
                bh = band_hashes(super_minhash(d, e, hi - lo, bands * rows), bands, rows)
                lists = _lists(bh)
                yield pa.record_batch([ids[lo:hi], pa.array(seq.astype(np.int64)), pa.array(other.astype(np.int64)), pa.array(n.astype(np.int64)), lists, _lists(odd)], ["doc_id", "g1", "g2", "n_shingles", "bands", "bits"])

    return run


def sketch(docs: DataFrame, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(doc_id, g1, g2, n_shingles, bands, bits): g1 and g2 tell word sequences apart, bits are parities."""
    bound_batches(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_sketch(bands, rows), "doc_id long, g1 long, g2 long, n_shingles long, bands array<long>, bits array<long>")


def _similarity(batches):
    for b in batches:
        left, right = utf8(b.column(2)), utf8(b.column(3))
        out = np.zeros((b.num_rows, 3), np.int64)
        for lo, hi in runs([range(len(x) + len(y)) for x, y in zip(left, right, strict=True)]):
            m = hi - lo
            h, counts = word_hashes(left[lo:hi] + right[lo:hi])
            d, e, _ = shingles(h, counts)
            n = np.bincount(d, minlength=2 * m)
            pair = np.where(d >= m, d - m, d)
            order = np.lexsort((e, pair))
            p, x = pair[order], e[order]
            same = (p[1:] == p[:-1]) & (x[1:] == x[:-1])
            both = np.bincount(p[1:][same], minlength=m)
            out[lo:hi] = np.stack([both, n[:m], n[m:]], 1)
        yield pa.record_batch([b.column(0), b.column(1), *(pa.array(out[:, j]) for j in range(3))], ["u", "v", "both", "nu", "nv"])


def verify(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """(u, v, both, nu, nv) of pairs, from the whole texts (doc_id, text) of their members."""
    left = texts.select(F.col("doc_id").alias("u"), F.col("text").alias("tu"))
    right = texts.select(F.col("doc_id").alias("v"), F.col("text").alias("tv"))
    both = hot_join(materialise(pairs), right, "v", "u").join(left, "u").select("u", "v", "tu", "tv")
    return both.mapInArrow(_similarity, "u long, v long, both long, nu long, nv long")


def _local_union(batches):
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for b in batches:
        for u, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            a, c = root(u), root(v)
            if a != c:
                parent[max(a, c)] = min(a, c)
    nodes = [x for x in parent if root(x) != x]
    for lo in range(0, len(nodes), 1 << 16):
        part = nodes[lo : lo + (1 << 16)]
        yield pa.record_batch([pa.array(part, pa.int64()), pa.array([root(x) for x in part], pa.int64())], ["u", "v"])


def _stars_only(e: DataFrame) -> bool:
    """Whether every node of distinct edges (u, v) with u > v either has one edge down or is a root."""
    ends = e.select(F.col("u").alias("x"), F.lit(1).alias("down"), F.lit(0).alias("root")).union(e.select(F.col("v"), F.lit(0), F.lit(1)))
    return ends.groupBy("x").agg(F.sum("down").alias("down"), F.max("root").alias("root")).where("down > 1 OR (down = 1 AND root = 1)").isEmpty()


def components(links: DataFrame) -> DataFrame:
    """(node, comp) for every node of links (u, v): comp is the smallest node reachable.

    Union-find inside each partition, then rounds of large-star and small-star contraction; all state stays in
    distributed tables, and only whether stars are left alone reaches the driver.
    """
    e = materialise(links.select("u", "v").where("u <> v").mapInArrow(_local_union, "u long, v long"))
    while not _stars_only(e):
        # large star: every larger neighbour of u goes to the smallest of u and its neighbours
        near = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = near.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = hot_join(near.where("v > u"), least, "u", "v").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        # small star: every smaller neighbour of u, and u itself, goes to the smallest
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
        e = materialise(moved.where("u <> v").distinct())
    return e.select(F.col("u").alias("node"), F.col("v").alias("comp")).union(e.select("v", "v")).distinct()


def join_groups(comp: DataFrame, links: DataFrame) -> DataFrame:
    """comp (node, comp) after more links (u, v): only the roots that links connect are grouped again."""
    ends = links.select("u", "v").join(comp.select(F.col("node").alias("u"), F.col("comp").alias("cu")), "u", "left").join(comp.select(F.col("node").alias("v"), F.col("comp").alias("cv")), "v", "left")
    between = ends.select(F.coalesce("cu", "u").alias("u"), F.coalesce("cv", "v").alias("v")).where("u <> v").distinct()
    moved = materialise(components(between.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))))
    known = comp.join(moved.select(F.col("node").alias("comp"), F.col("comp").alias("to")), "comp", "left").select("node", F.coalesce("to", "comp").alias("comp"))
    return known.union(moved.join(comp.select("node"), "node", "left_anti"))


def _linked(found: DataFrame, similarity: int) -> DataFrame:
    return found.where(F.lit(100) * F.col("both") >= F.lit(similarity) * (F.col("nu") + F.col("nv") - F.col("both")))


def group(docs: DataFrame, similarity: int = SIMILARITY, bands: int = BANDS, rows: int = ROWS, left_per_doc: int = LEFT_PER_DOC) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of docs (doc_id, text)."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    s = materialise(sketch(docs, bands, rows))
    usable = s.where("n_shingles > 0 AND doc_id IS NOT NULL")
    # only sequences that recur are joined back, and from a table of their own, so that a large group of copies can be split
    copies = materialise(usable.groupBy("g1", "g2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")).where("n > 1").select("g1", "g2", "rep"))
    member = materialise(usable.select("doc_id", "n_shingles", "g1", "g2").join(small_or_plain(copies), ["g1", "g2"], "left").select("doc_id", "n_shingles", F.coalesce("rep", "doc_id").alias("rep")))
    reps = member.where("doc_id = rep").select("doc_id", F.col("n_shingles").alias("n")).distinct()
    bucketed = usable.join(reps, "doc_id", "left_semi").select(F.col("doc_id").alias("rep"), F.col("n_shingles").alias("n"), F.explode("bands").alias("bh"))
    shared = materialise(bucketed.groupBy("bh").agg(F.min("rep").alias("c"), F.count("*").alias("k")).where("k >= 2"))
    # members of shared buckets only
    held = materialise(hot_join(bucketed, shared, "bh", "rep", sizes=shared.select("bh", F.col("k").alias("n"))))
    stars = held.where("rep <> c").select(F.col("rep").alias("u"), F.col("c").alias("v")).distinct()
    stars = materialise(stars)
    touched = materialise(stars.select("u").union(stars.select("v")).distinct().withColumnRenamed("u", "doc_id"))
    count = touched.count()
    small = small_or_plain(touched)
    texts = materialise(docs.join(small, "doc_id", "left_semi")) if count else docs.sparkSession.createDataFrame([], docs.schema)
    marks = materialise(usable.join(small, "doc_id", "left_semi").select("doc_id", F.col("n_shingles").alias("n"), "bits"))
    found = materialise(verify(possible(stars, marks, similarity), texts))
    comp = materialise(components(_linked(found, similarity)))
    for step in range(MOST_STARS + 1):
        where = materialise(held.where("k >= 3").join(comp.withColumnRenamed("node", "rep"), "rep", "left").withColumn("comp", F.coalesce("comp", "rep")))
        parts = where.groupBy("bh", "comp").agg(F.count("*").alias("a")).groupBy("bh").agg(F.sum("a").alias("a"), F.sum(F.col("a") * F.col("a")).alias("aa"), F.count("*").alias("parts")).where("parts > 1")
        parts = materialise(parts)
        pairs_left = parts.agg(F.coalesce(F.sum((F.col("a") * F.col("a") - F.col("aa")) / 2), F.lit(0.0))).first()[0]
        if not pairs_left:
            break
        mixed = materialise(where.join(parts.select("bh"), "bh", "left_semi"))
        last = pairs_left <= left_per_doc * max(count, 1000) or step == MOST_STARS
        if last:
            fresh = _left_pairs(mixed, marks, similarity)
        else:
            centre = F.max_by("rep", F.xxhash64("rep", F.lit(step)))
            other = materialise(mixed.groupBy("bh").agg(centre.alias("c2")))
            near = mixed.join(other, "bh").select("rep", "c2", "comp").join(mixed.select(F.col("rep").alias("c2"), F.col("comp").alias("comp2")).distinct(), "c2").where("comp <> comp2")
            fresh = possible(materialise(near.select(F.greatest("rep", "c2").alias("u"), F.least("rep", "c2").alias("v")).distinct()), marks, similarity)
        fresh = fresh.join(found.select("u", "v"), ["u", "v"], "left_anti")
        more = materialise(verify(fresh, texts))
        found = found.union(more)
        comp = materialise(join_groups(comp, _linked(more, similarity)))
        if last:
            break
    named = hot_join(member, comp.withColumnRenamed("node", "rep"), "rep", "doc_id", "left").select("doc_id", "n_shingles", F.coalesce("comp", "rep").alias("component_id"))
    alone = s.where("n_shingles = 0 OR doc_id IS NULL").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return named.union(alone).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def _left_pairs(mixed: DataFrame, marks: DataFrame, similarity: int) -> DataFrame:
    """Pairs of one bucket in different groups that sizes and parities don't exclude."""
    own = mixed.select("bh", "rep", "comp").join(marks.withColumnRenamed("doc_id", "rep"), "rep")
    v = own.select("bh", F.col("rep").alias("v"), F.col("comp").alias("cv"), F.col("n").alias("nv"), F.col("bits").alias("bv"))
    u = own.select("bh", F.col("rep").alias("u"), F.col("comp").alias("cu"), F.col("n").alias("nu"), F.col("bits").alias("bu"))
    near = v.join(u, "bh").where((F.col("v") < F.col("u")) & (F.col("cu") != F.col("cv")) & _may_link(similarity))
    return near.select("u", "v").distinct()


def op7_minhash_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return group(table(spark, sf_dir, "documents"))


def keep_first(docs: DataFrame) -> DataFrame:
    """Pipeline form: one document of each group, with all its columns; rows without a doc_id stay.

    Rows that share the kept doc_id but hold other texts all stay; of rows with the same doc_id and text one stays.
    """
    gone = materialise(group(docs).where("NOT kept").select("doc_id").distinct())
    kept = docs.join(small_or_plain(gone), "doc_id", "left_anti").select(docs.columns)
    if not docs.where("doc_id IS NOT NULL").groupBy("doc_id").count().where("count > 1").isEmpty():
        kept = kept.where("doc_id IS NOT NULL").dropDuplicates(["doc_id", "text"]).union(kept.where("doc_id IS NULL"))
    return kept
