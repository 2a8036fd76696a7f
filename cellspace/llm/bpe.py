"""BPE encoding with reuse of content-defined chunks.

A rolling hash over 32 bytes cuts texts where its low bits are zero, so equal passages of different documents give
equal chunks. Chunks that occur more than once in the corpus, whatever their number, are encoded once, into a table by
hash in the shared folder; it is joined to the places where they occur, and each document gets the tokens of its shared
chunks as a list. All other chunks are encoded where they lie. Tokens of neighbouring chunks are joined and repaired: the stretch between the last sure break
of the left chunk and the first sure break of the right one is encoded again, and widened chunk by chunk until both
ends are breaks, so the result equals the encoding of the whole text. A sure break is a blank after a non-blank: no
piece of the pre-tokeniser spans it.

At scale: 24 bytes a chunk are shuffled, each shared chunk once, and its tokens once for each different text it is in.
Of the documents only those with shared chunks are shuffled, by the hash of their text; the set of these hashes is
broadcast within a checked size, beyond it all documents are shuffled once. Decoding is a lookup.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellspace.llm.common import map_batches, maybe_broadcast, pieces, staged, tokenizer_path

PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Mean chunk of about 2**MASK_BITS bytes above the least.
MASK_BITS, LEAST = 10, 256
_GEAR = np.random.default_rng(20240117).integers(0, 2**32, 256, dtype=np.uint32)
_BLANKS = np.zeros(256, bool)
_BLANKS[[9, 10, 11, 12, 13, 32]] = True


@cache
def encoding(path: str):
    import base64

    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("vocabulary", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})


def cut_points(data: np.ndarray, mask_bits: int = MASK_BITS, least: int = LEAST) -> list[int]:
    """Ends of chunks, the last of which is the length; they lie between characters."""
    h = _GEAR[data]
    for k in (1, 2, 4, 8, 16):
        h[k:] += h[:-k] << np.uint32(k)
    # a cut after byte i; the next byte begins a character
    ok = (h >> np.uint32(32 - mask_bits)) == 0
    cuts, last = [], 0
    for i in (np.flatnonzero(ok) + 1).tolist():
        while i < len(data) and data[i] & 0xC0 == 0x80:
            i += 1
        if i - last >= least and len(data) - i >= 1:
            cuts.append(i)
            last = i
    return [*cuts, len(data)]


def chunks_of(text: str) -> list[bytes]:
    raw = text.encode("utf-8", "replace")
    if not raw:
        return []
    ends = cut_points(np.frombuffer(raw, np.uint8))
    return [raw[a:b] for a, b in zip([0, *ends], ends, strict=False)]


def chunk_hash(chunk: bytes) -> int:
    import xxhash

    return xxhash.xxh3_64_intdigest(chunk) - 2**63


_BREAK = re.compile(rb"[^\s\x80-\xff](?=[ \t\n\r\f\v])")


def first_break(chunk: bytes) -> int:
    """First place where a blank follows an ASCII non-blank, or -1."""
    m = _BREAK.search(chunk)
    return m.end() if m else -1


def last_break(chunk: bytes) -> int:
    at = len(chunk)
    while (at := max(chunk.rfind(b" ", 0, at), chunk.rfind(b"\n", 0, at))) > 0:
        if chunk[at - 1] < 128 and not _BLANKS[chunk[at - 1]]:
            return at
    return -1


class ChunkEncoder:
    """Encodes texts from chunks, some of which may come with their tokens."""

    def __init__(self, vocabulary: str, cache_bytes: int = 16_000_000):
        self.enc = encoding(vocabulary)
        self.lengths = np.zeros(self.enc.n_vocab, np.int64)
        for piece, rank in self.enc._mergeable_ranks.items():
            self.lengths[rank] = len(piece)
        self.cache, self.cache_bytes, self.cached = {}, cache_bytes, 0
        self.reused = self.made = self.repaired = 0

    def encode(self, raw: bytes) -> np.ndarray:
        return np.array(self.enc.encode_ordinary(raw.decode("utf-8")), np.int32)

    def chunk(self, raw: bytes, h: int) -> np.ndarray:
        hit = self.cache.get(h)
        if hit is not None and hit[0] == raw:
            self.reused += 1
            return hit[1]
        tokens = self.encode(raw)
        self.made += 1
        if self.cached > self.cache_bytes:
            self.cache, self.cached = {}, 0
        self.cache[h] = (raw, tokens)
        self.cached += len(raw) + tokens.nbytes
        return tokens

    def given(self, raw: bytes, tokens: bytes) -> np.ndarray | None:
        """Tokens that came with a chunk, if they are those of its bytes (hashes may be equal by chance)."""
        found = np.frombuffer(tokens, np.int32)
        return found if self.enc.decode_bytes(found.tolist()) == raw else None

    def text(self, text: str, shared: dict[int, bytes] | None = None) -> np.ndarray:
        """``shared``: tokens of some chunks by their number."""
        parts = chunks_of(text)
        tokens = []
        for k, p in enumerate(parts):
            mine = self.given(p, shared[k]) if shared and k in shared else None
            self.reused += mine is not None
            tokens.append(self.chunk(p, chunk_hash(p)) if mine is None else mine)
        if len(parts) < 2:
            return tokens[0] if parts else np.zeros(0, np.int32)
        out, k = [], 0
        left, mine = parts[0], tokens[0]
        while k + 1 < len(parts):
            a = last_break(left)
            if a > 0:
                keep = self._upto(mine, a)
                if keep < 0:
                    a = -1
            if a <= 0:
                keep, a = 0, 0
            out.append(mine[:keep])
            middle = left[a:]
            while True:
                k += 1
                right, theirs = parts[k], tokens[k]
                b = first_break(right)
                skip = self._upto(theirs, b) if b > 0 else -1
                if skip >= 0 or k + 1 == len(parts):
                    break
                middle += right
            self.repaired += 1
            if skip < 0:
                middle, left, mine = middle + right, b"", tokens[k][:0]
            else:
                middle, left, mine = middle + right[:b], right[b:], theirs[skip:]
            out.append(self.encode(middle))
        out.append(mine)
        return np.concatenate(out)

    def _upto(self, tokens: np.ndarray, n: int) -> int:
        """How many tokens make the first ``n`` bytes; -1 if none ends there."""
        ends = np.cumsum(self.lengths[tokens])
        k = int(np.searchsorted(ends, n))
        return k + 1 if k < len(ends) and ends[k] == n else -1

    def decode(self, tokens) -> str:
        return self.enc.decode_bytes(tokens.tolist() if isinstance(tokens, np.ndarray) else list(tokens)).decode("utf-8", "replace")


def shared_chunks(docs: DataFrame, vocabulary: str) -> tuple[DataFrame, DataFrame]:
    """From (text_hash, text): the table (h, tokens) of chunks that occur more than once, each encoded once, and
    (text_hash, shared) with (number, tokens) of the shared chunks of each different text that has any."""

    def hashes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in pieces(batches, 1):
            found = [(d, k, chunk_hash(c)) for d, t in zip(part.column(0).to_pylist(), texts, strict=True) if t for k, c in enumerate(chunks_of(t))]
            if found:
                cols = zip(*found, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(cols, (pa.int64(), pa.int32(), pa.int64()), strict=True)], names=["text_hash", "k", "h"])

    places = staged(map_batches(docs, hashes, "text_hash long, k int, h long"), "chunks")
    often = places.groupBy("h").agg(F.count("*").alias("n"), F.min(F.struct("text_hash", "k")).alias("first")).where("n > 1")
    often = staged(often.select("h", F.col("first.text_hash").alias("text_hash"), F.col("first.k").alias("k")), "shared-hashes")
    owners = staged(often.groupBy("text_hash").agg(F.collect_list(F.struct("k", "h")).alias("want")), "owners")
    holders = docs.join(maybe_broadcast(owners, often.count(), 24), "text_hash").select("text_hash", "text", "want")

    def wanted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = set()
        for part, texts in pieces(batches, 1):
            rows = []
            for t, want in zip(texts, part.column(2).to_pylist(), strict=True):
                cut = None
                for w in want:
                    if w["h"] not in seen:
                        seen.add(w["h"])
                        cut = chunks_of(t) if cut is None else cut
                        rows += [(w["h"], cut[w["k"]])] if w["k"] < len(cut) else []
            if rows:
                h, c = zip(*rows, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(c, pa.binary())], names=["h", "chunk"])

    def once(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoding(vocabulary)
        for part in batches:
            tokens = [np.array(enc.encode_ordinary(c.decode("utf-8")), np.int32).tobytes() for c in part.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(tokens, pa.binary())], names=["h", "tokens"])

    distinct = map_batches(holders, wanted, "h long, chunk binary").groupBy("h").agg(F.min("chunk").alias("chunk"))
    table = staged(map_batches(distinct, once, "h long, tokens binary"), "shared-chunks")
    lists = places.distinct().join(table, "h").groupBy("text_hash").agg(F.collect_list(F.struct("k", "tokens")).alias("shared"))
    return table, staged(lists, "shared-lists")


def bpe_encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = tokenizer_path("byte_bpe_50k.tiktoken")) -> DataFrame:
    """(id, tokens, n_tokens, n_bytes, decodes): the token ids of each whole text, equal to encoding it at once, and
    whether they decode to the text.

    A null text gives nulls, an empty one an empty list. Null ids stay null, repeated rows repeat. An empty table gives
    none.
    """
    df = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.xxhash64(text_col).alias("text_hash"))
    kind = df.schema["id"].dataType.simpleString()
    _, lists = shared_chunks(df.select("text_hash", "text").where(F.col("text").isNotNull()), vocabulary)
    count = lists.count()
    some = maybe_broadcast(lists.select("text_hash"), count, 12)
    alone = df.join(some, "text_hash", "left_anti").select("id", "text", F.lit(None).cast(lists.schema["shared"].dataType).alias("shared"))
    both = alone.unionByName(df.join(some, "text_hash", "left_semi").join(lists, "text_hash").select("id", "text", "shared"))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = ChunkEncoder(vocabulary)
        for part, texts in pieces(batches, 1, 2_000_000):
            shared = [s and {x["k"]: x["tokens"] for x in s} for s in part.column(2).to_pylist()]
            made = [None if t is None else coder.text(t, s) for t, s in zip(texts, shared, strict=True)]
            flat = np.concatenate([m for m in made if m is not None] or [np.zeros(0, np.int32)])
            counts = [None if m is None else len(m) for m in made]
            ends = np.concatenate([[0], np.cumsum([c or 0 for c in counts])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(flat, pa.int32()), mask=pa.array([c is None for c in counts]))
            size = [None if t is None else len(t.encode("utf-8", "replace")) for t in texts]
            same = [None if t is None else coder.decode(m) == t for t, m in zip(texts, made, strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0), lists, pa.array(counts, pa.int32()), pa.array(size, pa.int64()), pa.array(same, pa.bool_())], names=["id", "tokens", "n_tokens", "n_bytes", "decodes"])

    return map_batches(both, kernel, f"id {kind}, tokens array<int>, n_tokens int, n_bytes long, decodes boolean").withColumnRenamed("id", id_col)


def token_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = tokenizer_path("byte_bpe_50k.tiktoken"), carried: tuple[str, ...] = ()) -> DataFrame:
    """(id, *carried, tokens): the number of tokens of each whole text, without the tokens; null texts have none."""
    df = docs.select(F.col(id_col).alias("id"), *carried, F.col(text_col).alias("text"))
    kept = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema[:-1])
    at = len(df.columns) - 1

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoding(vocabulary)
        for part, texts in pieces(batches, at, 2_000_000):
            n = [len(enc.encode_ordinary(t)) if t else 0 for t in texts]
            yield pa.RecordBatch.from_arrays([*part.columns[:at], pa.array(n, pa.int64())], names=[*part.schema.names[:at], "tokens"])

    return map_batches(df, kernel, f"{kept}, tokens long")


def bpe_decode(tokens: DataFrame, id_col: str = "doc_id", tokens_col: str = "tokens", vocabulary: str = tokenizer_path("byte_bpe_50k.tiktoken")) -> DataFrame:
    """(id, text) from token lists; null lists give null texts, empty ones empty texts. Null ids stay null, repeated rows
    repeat, an empty table gives none."""
    df = tokens.select(F.col(id_col).alias("id"), F.col(tokens_col).alias("tokens"))
    kind = df.schema["id"].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoding(vocabulary)
        for part in batches:
            texts = [None if t is None else enc.decode_bytes(t).decode("utf-8", "replace") for t in part.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(texts, pa.string())], names=["id", "text"])

    return map_batches(df, kernel, f"id {kind}, text string").withColumnRenamed("id", id_col)
