"""Shared plumbing of the text operators: shared folder, written tables, Arrow batches, word ids.

Every operator selects the id and text columns it needs before it adds its own, so extra columns of the
input never clash with an operator's names.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side of a join is broadcast only if its rows and their width stay within this many bytes.
BROADCAST_BYTES = 12_000_000
#: Python kernels take a batch apart into pieces of about this many bytes of text.
CHUNK_BYTES = 6_000_000

_OWN_DIRS: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: ``spark.checkpoint.dir`` of the session.

    Only where it is unset and the master is local (tests) a folder of our own is made.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    app = spark.sparkContext.applicationId
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if app not in _OWN_DIRS:
        _OWN_DIRS[app] = "file://" + tempfile.mkdtemp(prefix="cellspace-")
    return _OWN_DIRS[app]


def staged(df: DataFrame, tag: str) -> DataFrame:
    """``df`` written to the shared folder and read back: short lineage that survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def maybe_broadcast(df: DataFrame, rows: int, width: int = 32) -> DataFrame:
    """A hint to broadcast ``df`` if ``rows`` rows of about ``width`` bytes are within BROADCAST_BYTES; else Spark's
    own joins shuffle."""
    return F.broadcast(df) if rows * width <= BROADCAST_BYTES else df


def tokenizer_path(name: str) -> str:
    """Place of a public vocabulary file (a parameter of every operator that needs one)."""
    return str(Path("/opt/tokenizers") / name)


def map_batches(df: DataFrame, kernel: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    return df.mapInArrow(kernel, schema)


def pieces(batches: Iterator[pa.RecordBatch], text: int = 1, limit: int = CHUNK_BYTES) -> Iterator[tuple[pa.RecordBatch, list]]:
    """Slices of batches with at most ``limit`` bytes of text each (one text at least), with the texts."""
    for batch in batches:
        if not batch.num_rows:
            continue
        column = batch.column(text)
        sizes = np.asarray(pc.fill_null(pc.binary_length(column), 0), dtype=np.int64)
        ends = np.cumsum(sizes)
        at = 0
        while at < len(sizes):
            before = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, before + limit, "right")))
            part = batch.slice(at, to - at)
            yield part, part.column(text).to_pylist()
            at = to


#: ASCII punctuation and control bytes become blanks; letters become lower case.
_FOLD = bytearray(range(256))
for _c in range(128):
    if not chr(_c).isalnum():
        _FOLD[_c] = 32
FOLD = bytes(_FOLD)


def folded_words(text: str) -> list[bytes]:
    """Lower-case words without ASCII punctuation, as UTF-8."""
    return text.lower().encode("utf-8", "replace").translate(FOLD).split()


class WordIds:
    """Ids 0, 1, ... of the words met, kept over batches and forgotten beyond ``limit`` words.

    ``features(new_words)`` gives arrays with a row for each new word; ``rows[k]`` holds the k-th of them.
    """

    def __init__(self, features: Callable[[list[bytes]], list[np.ndarray]], limit: int = 400_000):
        self.features, self.limit = features, limit
        self.ids: dict[bytes, int] = {}
        self.rows: list[np.ndarray] = []
        self.used = 0

    def __call__(self, docs: list[list[bytes]]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all words one after the other, number of words of each document)."""
        if len(self.ids) > self.limit:
            self.ids, self.rows, self.used = {}, [], 0
        ids, flat = self.ids, [w for d in docs for w in d]
        new = [w for w in dict.fromkeys(flat) if w not in ids]
        for k, w in enumerate(new, len(ids)):
            ids[w] = k
        if new or not self.rows:
            made = self.features(new)
            if not self.rows:
                self.rows = [np.empty((max(1024, 2 * len(m)), *m.shape[1:]), m.dtype) for m in made]
            for k, m in enumerate(made):
                if self.used + len(m) > len(self.rows[k]):
                    grown = np.empty((2 * (self.used + len(m)), *m.shape[1:]), m.dtype)
                    grown[: self.used] = self.rows[k][: self.used]
                    self.rows[k] = grown
                self.rows[k][self.used : self.used + len(m)] = m
            self.used += len(new)
        return np.fromiter(map(ids.__getitem__, flat), np.int64, len(flat)), np.array([len(d) for d in docs], np.int64)


_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= _M1
    x ^= x >> np.uint64(27)
    x *= _M2
    x ^= x >> np.uint64(31)
    return x


def word_hashes(words: list[bytes]) -> np.ndarray:
    import xxhash

    h = xxhash.xxh3_64_intdigest
    return np.fromiter(map(h, words), np.uint64, len(words))
