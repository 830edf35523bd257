"""Line deduplication with sharded cuckoo filters over exact reference counts.

State: ``refs(shard, k1, k2, refs)``, the exact number of documents that hold a line key, and
``filters(shard, bits)``, one cuckoo filter a shard of the keys with at least ``min_docs`` documents.
Documents can be inserted and deleted again; the counts make every step reversible.

Defined cases: null or empty text is one empty line; empty keys are never dropped; each row is a
document, repeated rows, rows that share a doc_id and rows without one too; a null doc_id is carried; extra columns are
ignored by the query and kept by ``apply_lines``, whose own get underscores after them where a name is taken; an empty table
gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, free_name, materialise, utf8
from .cuckoo import CuckooFilter

MIN_DOCS, MIN_CHARS = 10, 1
#: Keys a filter shard is sized for, and bytes of filters up to which they are broadcast.
SHARD_KEYS, FILTER_BYTES = 250_000, 64 << 20
#: Exact exceptions (false positives of the filters) up to which they go with the broadcast.
EXCEPTIONS = 200_000


def line_keys(text: bytes) -> list[bytes]:
    """The key of every line: stripped of ASCII white space at both ends, A-Z lower-cased."""
    return [x.strip() for x in text.lower().split(b"\n")]


def digest(keys) -> np.ndarray:
    """Two signed 64-bit halves a key."""
    d = xxhash.xxh128_digest
    return np.frombuffer(b"".join(map(d, keys)), ">i8").astype(np.int64).reshape(-1, 2)


def _counts(min_chars: int):
    def run(batches):
        for b in batches:
            seen: Counter = Counter()
            for text in utf8(b.column(0)):
                keys = set(line_keys(text))
                keys.discard(b"")
                if min_chars > 1:
                    keys = {k for k in keys if len(k.decode()) >= min_chars}
                seen.update(keys)
            k = digest(seen)
            yield pa.record_batch([pa.array(k[:, 0]), pa.array(k[:, 1]), pa.array(np.fromiter(seen.values(), np.int64, len(seen)))], ["k1", "k2", "refs"])

    return run


def count_refs(docs: DataFrame, text: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """(k1, k2, refs): documents that hold each key; counted within batches before the shuffle."""
    bound_batches(docs.sparkSession)
    return docs.select(F.col(text).cast("string")).mapInArrow(_counts(min_chars), "k1 long, k2 long, refs long").groupBy("k1", "k2").agg(F.sum("refs").alias("refs"))


def _shard(n: int) -> Column:
    return F.pmod("k1", F.lit(n)).cast("int").alias("shard")


def _build(t: pa.Table) -> pa.Table:
    bits = CuckooFilter.for_keys(t["k1"].to_numpy(), t["k2"].to_numpy()).to_bytes()
    return pa.table({"shard": t["shard"][:1].cast(pa.int32()), "bits": pa.array([bits], pa.binary())})


@dataclass(frozen=True)
class LineState:
    refs: DataFrame
    filters: DataFrame
    shards: int
    min_docs: int
    min_chars: int

    def hot(self) -> DataFrame:
        return self.refs.where(F.col("refs") >= self.min_docs)


def build_state(docs: DataFrame, min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS, text: str = "text", shard_keys: int = SHARD_KEYS) -> LineState:
    refs = materialise(count_refs(docs, text, min_chars))
    return _with_filters(refs, min_docs, min_chars, shard_keys)


def _with_filters(refs: DataFrame, min_docs: int, min_chars: int, shard_keys: int) -> LineState:
    hot = refs.where(F.col("refs") >= min_docs)
    shards = max(1, -(-hot.count() // shard_keys))
    made = hot.select(_shard(shards), "k1", "k2").groupBy("shard").applyInArrow(_build, "shard int, bits binary")
    return LineState(refs, materialise(made), shards, min_docs, min_chars)


def change(state: LineState, docs: DataFrame, sign: int, text: str = "text") -> LineState:
    """The state after inserting (+1) or deleting (-1) documents; only keys that cross the limit touch a filter."""
    delta = count_refs(docs, text, state.min_chars).select("k1", "k2", (F.col("refs") * sign).alias("step"))
    both = state.refs.join(delta, ["k1", "k2"], "full").select("k1", "k2", F.coalesce("refs", F.lit(0)).alias("old"), (F.coalesce("refs", F.lit(0)) + F.coalesce("step", F.lit(0))).alias("refs"))
    both = materialise(both)
    crossing = both.where((F.col("old") >= state.min_docs) != (F.col("refs") >= state.min_docs)).select(_shard(state.shards), "k1", "k2", (F.col("refs") >= state.min_docs).alias("enters"))

    def step(held: pa.Table, moved: pa.Table) -> pa.Table:
        shard = (held if len(held) else moved)["shard"][0].as_py()
        f = CuckooFilter.from_bytes(held["bits"][0].as_py()) if len(held) else CuckooFilter()
        if len(moved):
            k1, k2, enters = (moved[c].to_numpy() for c in ("k1", "k2", "enters"))
            f.delete(k1[~enters], k2[~enters])
            while not f.insert(k1[enters], k2[enters]):
                raise OverflowError("a filter shard is full: rebuild the state from its counts")
        return pa.table({"shard": pa.array([shard], pa.int32()), "bits": pa.array([f.to_bytes()], pa.binary())})

    refs = both.where("refs > 0").select("k1", "k2", "refs")
    try:
        filters = materialise(state.filters.groupBy("shard").cogroup(crossing.groupBy("shard")).applyInArrow(step, "shard int, bits binary"))
    except Exception as e:
        if "a filter shard is full" not in str(e):
            raise
        return _with_filters(refs, state.min_docs, state.min_chars, SHARD_KEYS)
    return LineState(refs, filters, state.shards, state.min_docs, state.min_chars)


class _Member:
    """Exact membership: the filters of all shards and the few keys that they hold wrongly."""

    def __init__(self, filters: dict[int, bytes], shards: int, wrong: set[tuple[int, int]]):
        self.data, self.shards, self.wrong, self.filters = filters, shards, wrong, None

    def __getstate__(self):
        return self.__dict__ | {"filters": None}

    def positive(self, k: np.ndarray) -> np.ndarray:
        if self.filters is None:
            self.filters = {s: CuckooFilter.from_bytes(x) for s, x in self.data.items()}
        out = np.zeros(len(k), bool)
        shard = np.mod(k[:, 0], self.shards)
        for s, f in self.filters.items():
            at = np.flatnonzero(shard == s) if self.shards > 1 else slice(None)
            out[at] = f.contains(k[at, 0], k[at, 1])
        return out

    def exact(self, k: np.ndarray) -> np.ndarray:
        out = self.positive(k)
        if self.wrong and out.any():
            at = np.flatnonzero(out)
            out[at] = [tuple(x) not in self.wrong for x in k[at].tolist()]
        return out


def membership(state: LineState, limit: int = FILTER_BYTES) -> _Member | None:
    """None if the filters or their exceptions are too large to broadcast."""
    total = state.filters.agg(F.sum(F.length("bits"))).first()[0] or 0
    if total > limit:
        return None
    member = _Member({r.shard: bytes(r.bits) for r in state.filters.collect()}, state.shards, set())
    bound_batches(state.refs.sparkSession)

    def probe(batches):
        for b in batches:
            hit = member.positive(np.stack([b.column(0).to_numpy(), b.column(1).to_numpy()], 1)) if b.num_rows else []
            yield b.filter(pa.array(hit, pa.bool_()))

    cold = state.refs.where(F.col("refs") < state.min_docs).select("k1", "k2")
    wrong = cold.mapInArrow(probe, cold.schema).limit(EXCEPTIONS + 1).collect()
    if len(wrong) > EXCEPTIONS:
        return None
    member.wrong = {(r.k1, r.k2) for r in wrong}
    return member


def _cut(texts: list[bytes], drops, min_chars: int) -> tuple[list[bytes], list[int], list[int]]:
    """Texts without their dropped lines, lines of each, dropped lines of each."""
    lines = [x.split(b"\n") for x in texts]
    keys = [k for x in texts for k in line_keys(x)]
    gone = drops(keys) if keys else []
    kept, dropped, at = [], [], 0
    for own in lines:
        mask = gone[at : at + len(own)]
        at += len(own)
        n = int(np.count_nonzero(mask))
        dropped.append(n)
        kept.append(b"\n".join([x for x, g in zip(own, mask, strict=True) if not g]) if n else b"\n".join(own))
    return kept, [len(x) for x in lines], dropped


def _dropper(member: _Member, min_chars: int):
    def drops(keys: list[bytes]) -> np.ndarray:
        gone = member.exact(digest(keys))
        gone &= np.fromiter((len(k) > 0 if min_chars <= 1 else len(k.decode()) >= min_chars for k in keys), bool, len(keys))
        return gone

    return drops


def added_names(docs: DataFrame) -> list[str]:
    """Names of the columns that ``apply_lines`` adds to docs."""
    return [free_name(docs, c) for c in ("dm_n_lines", "dm_n_dropped")]


def apply_lines(docs: DataFrame, state: LineState, text: str = "text", limit: int = FILTER_BYTES) -> DataFrame:
    """docs with ``text`` cut, and ``dm_n_lines``, ``dm_n_dropped`` beside their own columns."""
    spark: SparkSession = docs.sparkSession
    bound_batches(spark)
    member = membership(state, limit)
    docs = docs.withColumn(text, F.col(text).cast("string"))
    schema = docs.withColumns({c: F.lit(0).cast("long") for c in added_names(docs)}).schema
    for f in schema:
        f.nullable = True
    if member is None:
        return _apply_by_join(docs, state, text)
    at, held = docs.columns.index(text), spark.sparkContext.broadcast(member)
    min_chars = state.min_chars

    def run(batches):
        drops = _dropper(held.value, min_chars)
        for b in batches:
            kept, n, gone = _cut(utf8(b.column(at)), drops, min_chars)
            cols = list(b.columns)
            cols[at] = pa.array(kept, pa.binary()).cast(pa.string())
            yield pa.record_batch([*cols, pa.array(n, pa.int64()), pa.array(gone, pa.int64())], schema.names)

    return docs.mapInArrow(run, schema)


def _apply_by_join(docs: DataFrame, state: LineState, text: str) -> DataFrame:
    """The way for filters beyond the broadcast limit: lines meet the exact counts in a shuffled join (skewed keys are split by AQE)."""
    names, added = docs.columns, added_names(docs)
    at, said = names.index(text), F.coalesce(F.col(text), F.lit(""))
    # the documents' own columns travel under numbers, so that none of them clashes with the join's
    own = docs.select(*[F.col(f"`{c}`").alias(f"own_{i}") for i, c in enumerate(names)], F.xxhash64(said).alias("key"), F.sha1(said).alias("key2"))
    text = f"own_{at}"
    min_chars = state.min_chars

    def lines(batches):
        for b in batches:
            out = ([], [], [], [])
            for text_, a, c in zip(utf8(b.column(0)), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                keys = line_keys(text_)
                for j, k in enumerate(keys):
                    if len(k.decode()) >= max(1, min_chars):
                        out[0].append(a), out[1].append(c), out[2].append(j), out[3].append(k)
            k = digest(out[3])
            yield pa.record_batch([pa.array(out[0], pa.int64()), pa.array(out[1], pa.string()), pa.array(out[2], pa.int64()), pa.array(k[:, 0]), pa.array(k[:, 1])], ["key", "key2", "at", "k1", "k2"])

    found = own.select(text, "key", "key2").distinct().mapInArrow(lines, "key long, key2 string, at long, k1 long, k2 long")
    gone = found.join(materialise(state.hot().select("k1", "k2")), ["k1", "k2"]).groupBy("key", "key2").agg(F.collect_list("at").alias("gone"))
    parts = F.split(F.coalesce(F.col(text), F.lit("")), "\n", -1)
    joined = own.join(gone, ["key", "key2"], "left").withColumn("parts", parts).withColumn("gone", F.coalesce("gone", F.array().cast("array<long>")))
    kept = F.array_join(F.filter("parts", lambda _, i: ~F.array_contains("gone", i.cast("long"))), "\n")
    cols = [(kept if i == at else F.col(f"own_{i}")).alias(c) for i, c in enumerate(names)]
    return joined.select(*cols, F.size("parts").cast("long").alias(added[0]), F.size("gone").cast("long").alias(added[1]))


def drop_repeated_lines(docs: DataFrame, min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS) -> DataFrame:
    """Counts, builds the filters and applies them, over all documents."""
    return apply_lines(docs, build_state(docs, min_docs, min_chars))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .common import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    done = drop_repeated_lines(docs)
    return done.select("doc_id", F.col("dm_n_lines").alias("n_lines"), F.col("dm_n_dropped").alias("n_dropped"), F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


ORACLE = r"""
WITH lines AS (
  SELECT doc_id, rid, u.line, u.pos FROM (SELECT doc_id, row_number() OVER () AS rid, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents),
  LATERAL (SELECT unnest(parts) AS line, generate_subscripts(parts, 1) AS pos) AS u
), keyed AS (
  SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines
), hot AS (
  SELECT k FROM keyed WHERE k <> '' GROUP BY k HAVING count(DISTINCT rid) >= 10
)
SELECT any_value(doc_id) AS doc_id, count(*)::BIGINT AS n_lines, count(hot.k)::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE hot.k IS NULL), '')) AS kept_sha256
FROM keyed LEFT JOIN hot ON keyed.k = hot.k GROUP BY rid
"""
