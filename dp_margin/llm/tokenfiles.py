"""Token-id files: Arrow stream files of fixed-size lists, and flat unindexed files with a separator scan.

Arrow files. A shard holds a run of documents in ascending doc_id order. Its ids, each document closed by the end id, are cut into
sequences of equal length; a record batch has columns ``ids`` (fixed_size_list of the narrowest unsigned integers that hold the vocabulary)
and ``mask`` (fixed_size_list of bits: 0 where the shard's last sequence is padded). All batches but the last have the same number
of sequences, so sequence k lies in batch k // BATCH at a place known beforehand and is read without a copy from a memory map.
A second file of the shard holds the documents: doc_id, start within the shard, n_tokens.

Flat files. Ids of a task's documents one after another, two bytes each, a separator after each document, nothing else. The scan
searches blocks for separators, and a prefix scan over the blocks' carries joins the documents that cross block borders. Which document is the how
manieth of a file stands in a file of doc_ids beside it, whose records a block of the scan reads at their place.

Defined cases: a null or empty text has the end id only; rows that share a doc_id are ordered by their text (in one shard of Arrow files); null
doc_ids come first there, and stay null; extra columns are ignored; an empty table gives no files and an empty result.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .bpe import encoder, vocabulary
from .common import bound_batches, materialise, open_store, shared_dir, table

END_ID = 1
#: End-of-document id of the flat files; texts never give it, as strings of special tokens are encoded as ordinary text there.
SEPARATOR = 49407
SEQUENCE, SEQUENCES_A_BATCH = 2048, 256
#: Bytes of text a shard is sized for.
SHARD_BYTES = 32 << 20
#: Ids of a block of the separator scan.
BLOCK_IDS = 1 << 20
#: A record of the doc_ids beside a flat file.
NAME = np.dtype([("doc_id", "<i8"), ("null", "u1")])


def encode_documents(batch_texts: pa.Array, path: str, end_id: int, literal: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Ids of the texts with the end id after each, and ids of each text with it."""
    ids, n = encoder(path, literal).encode(batch_texts)
    total = np.concatenate(([0], np.cumsum(n + 1)))
    out = np.full(int(total[-1]), end_id, np.uint32)
    inner = np.ones(len(out), bool)
    inner[total[1:] - 1] = False
    out[inner] = ids
    return out, n + 1


def shards_of(docs: DataFrame, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """docs dealt out to shards by ascending ranges of doc_id and sorted within them."""
    size = docs.agg(F.sum(F.length(F.encode("text", "utf-8")))).first()[0] or 0
    n = max(1, -(-size // shard_bytes), min(8, size >> 20))
    return docs.repartitionByRange(int(n), F.col("doc_id")).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")


class _Sequences:
    """Writes ids as batches of equal sequences."""

    def __init__(self, sink, width, sequence: int, per_batch: int):
        self.kind, self.sequence, self.per_batch = width, sequence, per_batch
        self.schema = pa.schema([("ids", pa.list_(pa.from_numpy_dtype(width), sequence)), ("mask", pa.list_(pa.bool_(), sequence))])
        self.writer = pa.ipc.new_file(sink, self.schema)
        self.rest: list[np.ndarray] = []
        self.held = 0

    def add(self, ids: np.ndarray) -> None:
        self.rest.append(ids.astype(self.kind))
        self.held += len(ids)
        full = self.sequence * self.per_batch
        if self.held >= full:
            flat = np.concatenate(self.rest)
            whole = len(flat) // full * full
            for lo in range(0, whole, full):
                self._batch(flat[lo : lo + full], full)
            self.rest, self.held = [flat[whole:]], len(flat) - whole

    def _batch(self, flat: np.ndarray, real: int) -> None:
        mask = np.arange(len(flat)) < real
        cols = [pa.FixedSizeListArray.from_arrays(pa.array(x), self.sequence) for x in (flat, mask)]
        self.writer.write_batch(pa.record_batch(cols, schema=self.schema))

    def close(self) -> None:
        if self.held:
            flat = np.concatenate(self.rest)
            padded = np.zeros(-(-len(flat) // self.sequence) * self.sequence, self.kind)
            padded[: len(flat)] = flat
            self._batch(padded, len(flat))
        self.writer.close()


def _publish(fs, at: str, final: str) -> None:
    """A retried or speculative task writes the same bytes, so the last move may win."""
    fs.move(at, final)


def write_shards(docs: DataFrame, path: str, uri: str, end_id: int = END_ID, sequence: int = SEQUENCE, per_batch: int = SEQUENCES_A_BATCH) -> DataFrame:
    """Writes the files of every shard of docs (doc_id, text; already dealt out) and returns (shard, n_ids, n_docs)."""
    bound_batches(docs.sparkSession)
    fs, base = open_store(uri)
    fs.create_dir(base, recursive=True)

    def run(batches):
        from pyspark import TaskContext

        shard, store, docs_seen, ids_seen, out, index = TaskContext.get().partitionId(), None, 0, 0, None, None
        for b in batches:
            if not b.num_rows:
                continue
            if out is None:
                store, root = open_store(uri)
                mark = uuid.uuid4().hex
                width = np.uint16 if encoder(path).size <= 1 << 16 else np.uint32
                files = [(f"{root}/.{mark}.{k}", f"{root}/shard-{shard:08d}.{k}") for k in ("arrow", "docs.arrow")]
                sinks = [store.open_output_stream(f[0]) for f in files]
                out = _Sequences(sinks[0], width, sequence, per_batch)
                index = pa.ipc.new_file(sinks[1], pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())]))
            ids, n = encode_documents(b.column(1), path, end_id)
            out.add(ids)
            index.write_batch(pa.record_batch([b.column(0), pa.array(ids_seen + np.cumsum(n) - n), pa.array(n)], ["doc_id", "start", "n_tokens"]))
            docs_seen, ids_seen = docs_seen + b.num_rows, ids_seen + int(n.sum())
        if out is not None:
            out.close(), index.close()
            for s, f in zip(sinks, files, strict=True):
                s.close()
                _publish(store, *f)
            yield pa.record_batch([pa.array([shard], pa.int64()), pa.array([ids_seen], pa.int64()), pa.array([docs_seen], pa.int64())], ["shard", "n_ids", "n_docs"])

    return materialise(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "shard long, n_ids long, n_docs long"))


class ShardReader:
    """Random access to the sequences and documents of one shard."""

    def __init__(self, uri: str, shard: int, per_batch: int = SEQUENCES_A_BATCH):
        store, root = open_store(uri)
        name = f"{root}/shard-{shard:08d}"
        self.file, self.per_batch = pa.ipc.open_file(_opened(store, f"{name}.arrow")), per_batch
        self.index = pa.ipc.open_file(_opened(store, f"{name}.docs.arrow"))
        self.sequence = self.file.schema.field("ids").type.list_size

    def sequence_at(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Sequence k as a view of the mapped file, and its mask."""
        b, j = self.file.get_batch(k // self.per_batch), k % self.per_batch
        ids = b.column(0).values.to_numpy()[j * self.sequence : (j + 1) * self.sequence]
        return ids, np.array(b.column(1)[j].as_py())

    def ids(self, lo: int, hi: int) -> np.ndarray:
        """Ids lo to hi of the shard; only the batches that hold them are read."""
        full, parts = self.per_batch * self.sequence, []
        for k in range(lo // full, -(-hi // full)):
            flat = self.file.get_batch(k).column(0).values.to_numpy()
            parts.append(flat[max(0, lo - k * full) : hi - k * full])
        return np.concatenate(parts) if parts else np.zeros(0, np.uint16)

    def documents(self):
        for k in range(self.index.num_record_batches):
            yield self.index.get_batch(k)


def _opened(store, path: str):
    from pyarrow import fs

    return pa.memory_map(path) if isinstance(store, fs.LocalFileSystem) else store.open_input_file(path)


def read_documents(manifest: DataFrame, uri: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of all documents, from the files; start counts the ids of all shards before."""
    spark = manifest.sparkSession
    shards = manifest.orderBy("shard").collect()  # one row a file
    start, rows = 0, []
    for r in shards:
        rows.append((r.shard, start))
        start += r.n_ids
    plan = spark.createDataFrame(rows, "shard long, before long")
    plan = plan.repartition(max(1, len(rows)), "shard") if rows else plan

    def run(batches):
        for b in batches:
            for shard, before in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                reader = ShardReader(uri, shard)
                for d in reader.documents():
                    begin, n = d.column(1).to_numpy(), d.column(2).to_numpy()
                    flat = reader.ids(int(begin[0]), int(begin[-1] + n[-1])).astype("<u4")
                    at = begin - begin[0]
                    crc = [zlib.crc32(flat[a : a + k]) for a, k in zip(at.tolist(), n.tolist(), strict=True)]
                    yield pa.record_batch([d.column(0), pa.array(begin + before), d.column(2), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return plan.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op10_arrow_token_files(spark: SparkSession, sf_dir: str, vocab: str | None = None) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    uri = shared_dir(spark)
    manifest = write_shards(shards_of(docs), vocab or vocabulary(), uri)
    return read_documents(manifest, uri)


# --- flat files -----------------------------------------------------------------------------------------------------


def write_flat(docs: DataFrame, path: str, uri: str, separator: int = SEPARATOR) -> DataFrame:
    """One flat file a task, little-endian 16-bit ids, and one of its doc_ids; returns (file, n_docs)."""
    bound_batches(docs.sparkSession)
    fs, base = open_store(uri)
    fs.create_dir(base, recursive=True)

    def run(batches):
        from pyspark import TaskContext

        part, out, seen = TaskContext.get().partitionId(), None, 0
        for b in batches:
            if not b.num_rows:
                continue
            if out is None:
                if encoder(path, True).size > 1 << 16:
                    raise ValueError("this vocabulary needs more than 16 bits an id")
                store, root = open_store(uri)
                mark = uuid.uuid4().hex
                files = [(f"{root}/.{mark}.{k}", f"{root}/{k}-{part:08d}.bin") for k in ("names", "flat")]
                names, out = (store.open_output_stream(f[0]) for f in files)
            ids, _ = encode_documents(b.column(1), path, separator, literal=True)
            out.write(ids.astype("<u2").tobytes())
            own = np.zeros(b.num_rows, NAME)
            own["doc_id"], own["null"] = b.column(0).fill_null(0).to_numpy(), b.column(0).is_null().to_numpy(zero_copy_only=False)
            names.write(own.tobytes())
            seen += b.num_rows
        if out is not None:
            for sink, f in zip((names, out), files, strict=True):
                sink.close()
                _publish(store, *f)
            yield pa.record_batch([pa.array([part], pa.int64()), pa.array([seen], pa.int64())], ["file", "n_docs"])

    return materialise(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "file long, n_docs long"))


def scan_separators(spark: SparkSession, uri: str, separator: int = SEPARATOR, block_ids: int = BLOCK_IDS) -> DataFrame:
    """(doc_id, file, ordinal, start, n_tokens) of every document in the flat files below uri, without an index.

    Blocks are scanned apart; a block knows only where its separators lie. A prefix scan over the blocks' counts and last separators
    (one row a block) gives the ordinal and the start of the document that a block begins in.
    """
    from pyarrow import fs as pafs

    bound_batches(spark)
    fs, base = open_store(uri)
    files = [f for f in fs.get_file_info(pafs.FileSelector(base)) if f.base_name.startswith("flat-")]
    spread = max(1, sum(-(-f.size // (2 * block_ids)) for f in files))
    plan = spark.createDataFrame([(int(f.base_name[5:13]), f.size // 2) for f in files if f.size], "file long, ids long")
    plan = plan.select("file", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("ids") - 1) / block_ids))).alias("block"))
    plan = plan.repartition(min(spread, 4096), "file", "block")

    def found(file: int, block: int) -> np.ndarray:
        store, root = open_store(uri)
        with store.open_input_file(f"{root}/flat-{file:08d}.bin") as f:
            f.seek(2 * block * block_ids)
            return np.flatnonzero(np.frombuffer(f.read(2 * block_ids), "<u2") == separator) + block * block_ids

    def carries(batches):
        for b in batches:
            rows = [(f, k, x) for f, k in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True) for x in [found(f, k)]]
            yield pa.record_batch([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([len(r[2]) for r in rows], pa.int64()), pa.array([int(r[2][-1]) if len(r[2]) else None for r in rows], pa.int64())], ["file", "block", "n", "last"])

    carry = materialise(plan.mapInArrow(carries, "file long, block long, n long, last long"))
    before = Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    joined = carry.withColumn("ordinal", F.coalesce(F.sum("n").over(before), F.lit(0))).withColumn("begin", F.coalesce(F.max("last").over(before) + 1, F.lit(0))).where("n > 0")

    def named(file: int, lo: int, n: int) -> pa.Array:
        store, root = open_store(uri)
        with store.open_input_file(f"{root}/names-{file:08d}.bin") as f:
            f.seek(NAME.itemsize * lo)
            own = np.frombuffer(f.read(NAME.itemsize * n), NAME)
        return pa.array(own["doc_id"].astype(np.int64), mask=own["null"] > 0)

    def rows(batches):
        for b in batches:
            for file, block, ordinal, begin in zip(*(b.column(c).to_pylist() for c in ("file", "block", "ordinal", "begin")), strict=True):
                ends = found(file, block)
                start = np.concatenate(([begin], ends[:-1] + 1))
                yield pa.record_batch([named(file, ordinal, len(ends)), pa.array(np.full(len(ends), file)), pa.array(ordinal + np.arange(len(ends))), pa.array(start), pa.array(ends - start)], ["doc_id", "file", "ordinal", "start", "n_tokens"])

    return joined.select("file", "block", "ordinal", "begin").repartition(min(spread, 4096), "file", "block").mapInArrow(rows, "doc_id long, file long, ordinal long, start long, n_tokens long")


def op3_separator_scan(spark: SparkSession, sf_dir: str, vocab: str | None = None) -> DataFrame:
    """(doc_id, file, ordinal, start, n_tokens) for every document, as scanned from flat files; n_tokens without the separator."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    uri = shared_dir(spark)
    write_flat(docs, vocab or vocabulary(), uri)
    return scan_separators(spark, uri)
