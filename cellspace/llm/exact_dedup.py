"""Exact duplicates by an extendible-hash index that lies in the shared folder.

The 64-bit hash of a text is its key. The directory has ``2**global_depth`` slots; a slot names a bucket and a
bucket with more keys than ``capacity`` is split, which doubles the directory when the bucket already uses all of
its bits. Buckets are ranges of keys. Each belongs to one owner task, and owners hold runs of buckets of about as many
keys: entries (owner, bucket, key, rows) are sent to their owners and written in key order, a file an owner. Only rows
whose key occurs more than once travel; they go to the owner of their bucket, which walks them in key order with a
chain of the distinct byte strings seen under the current key, so equal hashes of different texts stay apart.

At scale: one scan makes the keys (16 bytes a row are shuffled after a partial count), a second scan fetches the
texts of repeated keys. Copies within an input batch are merged before the shuffle, so a text that occurs a million
times is sent once a batch and its owner keeps one copy in memory.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pyspark.sql.pandas.types import to_arrow_type

from cellspace.llm.common import map_batches, maybe_broadcast, staged

KEY, BUCKET, OWNER = "__cs_key", "__cs_bucket", "__cs_owner"
#: Least keys of a full bucket; in larger tables buckets are larger, so that the directory stays within 2**20 slots.
CAPACITY = 4096


class ExtendibleDirectory:
    """Slots to buckets. ``counts[i]`` keys begin with the ``depth`` bits ``i``."""

    def __init__(self, counts: np.ndarray, depth: int, capacity: int):
        self.global_depth, self.capacity, self.max_depth = 0, capacity, depth
        self.slots = np.zeros(1, np.int64)
        self.local_depth, self.first = [0], [0]
        self._sums = np.concatenate([[0], np.cumsum(counts)])
        open_buckets = [0]
        while open_buckets:
            b = open_buckets.pop()
            if self.size(b) > capacity and self.local_depth[b] < depth:
                open_buckets += [b, self.split(b)]

    def size(self, bucket: int) -> int:
        shift = self.max_depth - self.local_depth[bucket]
        lo = self.first[bucket] << shift
        return int(self._sums[lo + (1 << shift)] - self._sums[lo])

    def split(self, bucket: int) -> int:
        """The upper half of the bucket's keys moves to a new bucket, whose number is returned."""
        if self.local_depth[bucket] == self.global_depth:
            self.slots = np.repeat(self.slots, 2)
            self.global_depth += 1
        self.local_depth[bucket] += 1
        self.first[bucket] *= 2
        self.local_depth.append(self.local_depth[bucket])
        self.first.append(self.first[bucket] + 1)
        new = len(self.first) - 1
        shift = self.global_depth - self.local_depth[new]
        self.slots[self.first[new] << shift : (self.first[new] + 1) << shift] = new
        return new

    def lookup(self, keys: np.ndarray) -> np.ndarray:
        """Buckets of unsigned 64-bit keys."""
        if not self.global_depth:
            return np.zeros(len(keys), np.int64)
        return self.slots[(keys.astype(np.uint64) >> np.uint64(64 - self.global_depth)).astype(np.int64)]


def _prefix(depth: int):
    return F.shiftrightunsigned(F.col(KEY), 64 - depth) if depth else F.lit(0).cast("long")


class TextIndex:
    """The index of one table: the directory, and entry files (owner, bucket, key, rows with it) in key order."""

    def __init__(self, entries: DataFrame, directory: ExtendibleDirectory, repeated: int, owners: int):
        self.entries, self.directory, self.repeated, self.owners = entries, directory, repeated, owners


def owners_of(d: ExtendibleDirectory, owners: int) -> list[tuple[int, int, int]]:
    """(slot, bucket, owner) in key order: each owner has a run of whole buckets, of about as many keys as the others."""
    out, seen, total, last, owner = [], 0, max(1, int(d._sums[-1])), -1, 0
    for slot, bucket in enumerate(d.slots.tolist()):
        if bucket != last:
            owner = min(owners - 1, seen * owners // total)
            seen, last = seen + d.size(bucket), bucket
        out.append((slot, bucket, owner))
    return out


def _placed(df: DataFrame, d: ExtendibleDirectory, owners: int) -> DataFrame:
    """Adds bucket and owner; ``df`` has a key."""
    slots = df.sparkSession.createDataFrame(owners_of(d, owners), f"__cs_slot long, {BUCKET} long, {OWNER} int")
    slot = _prefix(d.global_depth)
    return df.withColumn("__cs_slot", slot).join(maybe_broadcast(slots, len(d.slots), 12), "__cs_slot").drop("__cs_slot")


def build_index(docs: DataFrame, text_col: str = "text", capacity: int | None = None) -> TextIndex:
    """Keys of all texts that aren't null, in entry files of the shared folder."""
    owners = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keys = docs.select(F.xxhash64(text_col).alias(KEY)).where(F.col(text_col).isNotNull())
    counts = staged(keys.groupBy(KEY).agg(F.count("*").alias("n")), "keys")
    total, repeated = counts.agg(F.count("*"), F.count_if(F.col("n") > 1)).first()
    capacity = max(CAPACITY, total >> 17) if capacity is None else capacity
    depth = min(20, max(0, int(np.ceil(np.log2(max(1, total / capacity)))) + 3)) if total > capacity else 0
    histogram = np.zeros(1 << depth, np.int64)
    if depth:
        for r in counts.groupBy(_prefix(depth).alias("p")).count().collect():  # at most 2**depth rows
            histogram[r["p"]] = r["count"]
    else:
        histogram[0] = total
    directory = ExtendibleDirectory(histogram, depth, capacity)
    entries = _owned(_placed(counts, directory, owners), owners, []).select(OWNER, BUCKET, KEY, "n")
    return TextIndex(staged(entries, "entries"), directory, repeated or 0, owners)


def _candidates(docs: DataFrame, text_col: str, index: TextIndex) -> tuple[DataFrame, DataFrame]:
    """(rows whose key repeats, with owner, bucket and key; the other rows)."""
    repeated = maybe_broadcast(index.entries.where("n > 1").select(KEY), index.repeated, 16)
    keyed = docs.withColumn(KEY, F.when(docs[text_col].isNotNull(), F.xxhash64(text_col)))
    return _placed(keyed.join(repeated, KEY, "left_semi"), index.directory, index.owners), keyed.join(repeated, KEY, "left_anti").drop(KEY)


def _owned(df: DataFrame, owners: int, order: list) -> DataFrame:
    """Rows at their owners, in the order of unsigned keys."""
    upper, lower = F.shiftrightunsigned(F.col(KEY), 32), F.col(KEY).bitwiseAND(F.lit(0xFFFFFFFF))
    return df.repartitionById(owners, F.col(OWNER)).sortWithinPartitions(upper, lower, *order)


def _local_groups(id_at: int, text_at: int, key_at: int, owner_at: int):
    """Copies within a batch become one row with all their ids."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            groups: dict[tuple, list] = {}
            rows = zip(b.column(owner_at).to_pylist(), b.column(key_at).to_pylist(), b.column(text_at).to_pylist(), b.column(id_at).to_pylist(), strict=True)
            for owner, key, text, i in rows:
                groups.setdefault((owner, key, text), []).append(i)
            if groups:
                ks = list(groups)
                yield pa.RecordBatch.from_arrays([pa.array([k[j] for k in ks], t) for j, t in ((0, pa.int32()), (1, pa.int64()), (2, pa.string()))] + [pa.array(list(groups.values()), pa.list_(b.schema.field(id_at).type))], names=[OWNER, KEY, "text", "ids"])

    return kernel


def _chain_groups(id_type: pa.DataType, step: int = 100_000):
    """Rows in key order: a chain of distinct texts for the current key; its groups when the key changes."""

    def emit(chain: dict) -> Iterator[pa.RecordBatch]:
        for ids in chain.values():
            known = sorted(i for i in ids if i is not None)
            ids = known + [None] * (len(ids) - len(known))
            for at in range(0, len(ids), step):
                part = ids[at : at + step]
                yield pa.RecordBatch.from_arrays([pa.array(part, id_type), pa.array([ids[0]] * len(part), id_type), pa.array([len(ids)] * len(part), pa.int64()), pa.array([at + k > 0 for k in range(len(part))], pa.bool_())], names=["id", "keep_id", "copies", "is_copy"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, chain, waiting, size = None, {}, [], 0
        for b in batches:
            for key, text, ids in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
                if key != current:
                    for x in emit(chain):
                        waiting.append(x)
                        size += x.num_rows
                    current, chain = key, {}
                    if size > 20_000:
                        yield from pa.Table.from_batches(waiting).combine_chunks().to_batches()
                        waiting, size = [], 0
                chain.setdefault(text, []).extend(ids)
        waiting += list(emit(chain))
        if waiting:
            yield from pa.Table.from_batches(waiting).combine_chunks().to_batches()

    return kernel


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int | None = None) -> DataFrame:
    """A row for each document: its id, ``keep_id`` (least id with the same bytes), ``copies`` (rows with these
    bytes) and ``is_copy`` (all but the first in id order).

    Null texts equal nothing: they keep themselves, with ``copies`` 1. Empty texts equal one another. Null ids sort
    last; a group of null ids only has a null ``keep_id``. Repeated rows count as copies. Ids may be
    of any type that can be ordered. An empty table gives none.
    """
    docs = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    id_type = docs.schema["id"].dataType.simpleString()
    arrow = to_arrow_type(docs.schema["id"].dataType)
    index = build_index(docs, "text", capacity)
    twice, once = _candidates(docs, "text", index)
    single = once.select("id", F.col("id").alias("keep_id"), F.lit(1).cast("long").alias("copies"), F.lit(False).alias("is_copy"))
    twice = twice.select("id", "text", KEY, OWNER)
    merged = map_batches(twice, _local_groups(0, 1, 2, 3), f"{OWNER} int, {KEY} long, text string, ids array<{id_type}>")
    found = map_batches(_owned(merged, index.owners, []), _chain_groups(arrow), f"id {id_type}, keep_id {id_type}, copies long, is_copy boolean")
    return single.unionByName(found).withColumnRenamed("id", id_col)


def _first_of_each(key_at: int, text_at: int):
    """Keeps the first row of each distinct text under a key; rows come in key order."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, chain = None, set()
        for b in batches:
            take = []
            for k, (key, text) in enumerate(zip(b.column(key_at).to_pylist(), b.column(text_at).to_pylist(), strict=True)):
                if key != current:
                    current, chain = key, set()
                if text not in chain:
                    chain.add(text)
                    take.append(k)
            if take:
                yield b.take(pa.array(take))

    return kernel


def _first_in_batch(key_at: int, text_at: int, id_at: int):
    """Of copies within a batch only the row with the least id (nulls last) goes on."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            best: dict[tuple, tuple] = {}
            ids = b.column(id_at).to_pylist()
            for k, (key, text) in enumerate(zip(b.column(key_at).to_pylist(), b.column(text_at).to_pylist(), strict=True)):
                mine = (ids[k] is None, ids[k] if ids[k] is not None else 0, k)
                if (key, text) not in best or mine < best[key, text]:
                    best[key, text] = mine
            if best:
                yield b.take(pa.array(sorted(x[2] for x in best.values())))

    return kernel


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int | None = None) -> DataFrame:
    """``docs`` with one row of each distinct text, that of the least id (nulls last); all columns stay.

    Null texts equal nothing and all stay; of empty texts one stays. Of repeated rows one stays. An empty table stays
    empty.
    """
    index = build_index(docs, text_col, capacity)
    twice, once = _candidates(docs, text_col, index)
    names, schema = twice.columns, twice.schema
    at = [names.index(c) for c in (KEY, text_col, id_col)]
    twice = map_batches(twice, _first_in_batch(*at), schema)
    kept = map_batches(_owned(twice, index.owners, [F.col(id_col).asc_nulls_last()]), _first_of_each(*at[:2]), schema)
    return once.unionByName(kept.drop(KEY, BUCKET, OWNER))
