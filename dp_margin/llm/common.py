"""What the operators of this subpackage share: tables, scratch space and batch bounds."""

from __future__ import annotations

import os
import tempfile
import uuid
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Rows and bytes of one Arrow batch sent to a Python worker.
BATCH_ROWS, BATCH_BYTES = 1024, 8 << 20
#: Estimated bytes up to which a key table is broadcast; a larger one is joined by shuffle.
BROADCAST_LIMIT = 64 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A new folder below the cluster's shared checkpoint folder; a session within one machine may do without one, a cluster may not."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        master = spark.conf.get("spark.master", "")
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = "file://" + os.path.join(tempfile.gettempdir(), "checkpoints")
    return f"{base.rstrip('/')}/dp-margin-{uuid.uuid4().hex}"


def materialise(df: DataFrame, level: int = 3) -> DataFrame:
    """Cuts the lineage: writes df to shared storage, compressed at a level of zstd, and reads it back."""
    spark = df.sparkSession
    path = shared_dir(spark)
    df.write.option("compression", "zstd").option("parquet.compression.codec.zstd.level", str(level)).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bound_batches(spark: SparkSession, rows: int = BATCH_ROWS) -> None:
    """Runtime SQL settings: no Python worker gets more than so many rows or bytes at once."""
    for key, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", rows), ("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)):
        now = spark.conf.get(key)
        if not (now.isdigit() and 0 < int(now) <= most):
            spark.conf.set(key, str(most))


def _row_bytes(kind: T.DataType, c: Column) -> Column:
    """Estimated bytes of a value in a broadcast table."""
    if isinstance(kind, T.StringType | T.BinaryType):
        return F.coalesce(F.octet_length(c), F.lit(0)) + 16
    if isinstance(kind, T.ArrayType):
        return F.greatest(F.size(c), F.lit(0)) * 8 + 24 if not isinstance(kind.elementType, T.StringType) else F.coalesce(F.octet_length(F.array_join(c, "")), F.lit(0)) + F.greatest(F.size(c), F.lit(0)) * 16 + 24
    return F.lit(8)


def estimated_bytes(df: DataFrame) -> int:
    """Bytes of df's rows as a broadcast hash table holds them, from all its rows; df should be a written table."""
    row = reduce(lambda a, b: a + b, [_row_bytes(f.dataType, F.col(f"`{f.name}`")) for f in df.schema], F.lit(48))
    return int(df.agg(F.sum(row.cast("long"))).first()[0] or 0)


def small_or_plain(df: DataFrame, limit: int = BROADCAST_LIMIT) -> DataFrame:
    """df with a broadcast hint if its measured bytes are within the limit, else left to a shuffled join."""
    return F.broadcast(df) if estimated_bytes(df) <= limit else df.hint("merge")


def hot_join(big: DataFrame, side: DataFrame, key: str, by: str, how: str = "inner", sizes: DataFrame | None = None) -> DataFrame:
    """big joined with side on key, where one key may hold any share of big's rows; big should be a written table.

    A key with more rows than an average task's share is dealt over several tasks by a hash of the column ``by``, and side's
    rows of it are repeated as often. Fewer keys than there are shuffle partitions can be so frequent, so their table is
    broadcast, and all repeats together are below twice the partitions times side's rows a key. ``sizes`` (key, n), if given,
    holds the number of rows of every key that side has.
    """
    parts = int(big.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = (big.count() if sizes is None else sizes.agg(F.sum("n")).first()[0]) or 0
    share = max(rows // parts, 1)
    sizes = big.groupBy(key).agg(F.count("*").alias("n")) if sizes is None else sizes.select(key, "n")
    hot = materialise(sizes.where(F.col(key).isNotNull() & (F.col("n") > share)).select(key, F.ceil(F.col("n") / share).cast("int").alias("dm_deal")))
    if hot.isEmpty():
        return big.join(side, key, how)
    dealt = big.join(F.broadcast(hot), key, "left").withColumn("dm_salt", F.coalesce(F.pmod(F.xxhash64(by), F.col("dm_deal")).cast("int"), F.lit(0)))
    repeated = side.join(F.broadcast(hot), key, "left").withColumn("dm_salt", F.explode(F.sequence(F.lit(0), F.coalesce("dm_deal", F.lit(1)) - 1)))
    return dealt.drop("dm_deal").join(repeated.drop("dm_deal"), [key, "dm_salt"], how).drop("dm_salt")


def free_name(docs: DataFrame, name: str) -> str:
    """name, with underscores after it while docs has a column of that name (in any case)."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name += "_"
    return name


def open_store(uri: str):
    """(file system, path) for a folder on shared storage, from a driver or an executor."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri else "file://" + (uri.removeprefix("file:")))


def utf8(values) -> list[bytes]:
    """The UTF-8 bytes of an Arrow string array; null counts as empty."""
    import pyarrow as pa

    return [x or b"" for x in values.cast(pa.binary()).to_pylist()]


_M1, _M2, _GOLD = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)


class IdTable:
    """Ids of strings that a worker has seen, packed into arrays; ``full`` once its bytes pass the limit."""

    def __init__(self, limit: int, kind=np.uint32):
        self.limit, self.kind = limit, kind
        self.clear()

    def clear(self) -> None:
        self.where: dict[str, int] = {}
        self.arena = np.zeros(1 << 16, self.kind)
        self.begin, self.length = np.zeros(1 << 12, np.int64), np.zeros(1 << 12, np.int32)
        self.used = self.key_bytes = 0

    @property
    def full(self) -> bool:
        # an entry of the dictionary takes about 100 bytes, a string 60 and its characters
        return self.arena.nbytes + self.begin.nbytes + self.length.nbytes + 160 * len(self.where) + self.key_bytes > self.limit

    def store(self, words: list[str], ids: np.ndarray, lengths: np.ndarray) -> None:
        n, k = len(self.where), len(words)
        self.arena = _room(self.arena, self.used + len(ids))
        self.begin, self.length = _room(self.begin, n + k), _room(self.length, n + k)
        self.arena[self.used : self.used + len(ids)] = ids
        self.begin[n : n + k] = self.used + np.cumsum(lengths) - lengths
        self.length[n : n + k] = lengths
        self.used += len(ids)
        self.key_bytes += sum(map(len, words))
        self.where.update(zip(words, range(n, n + k), strict=True))

    def gather(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of entries in a row, and the number of ids of each."""
        lengths = self.length[at].astype(np.int64)
        return self.arena[spread(self.begin[at], lengths)], lengths


def _room(x: np.ndarray, n: int) -> np.ndarray:
    if n <= len(x):
        return x
    out = np.zeros(max(n, len(x) + len(x) // 2), x.dtype)
    out[: len(x)] = x
    return out


def spread(begin: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The places begin[k], begin[k] + 1, ... of all spans in a row."""
    out = np.repeat(begin - (np.cumsum(lengths) - lengths), lengths)
    out += np.arange(len(out))
    return out


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit integers (the splitmix finaliser)."""
    x = x + _GOLD
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))
