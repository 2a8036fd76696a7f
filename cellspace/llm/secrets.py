"""Secrets by token efficiency.

A vocabulary made from prose needs few tokens for words and many for random strings, so few characters per token
expose a key. Candidates are runs of 16 or more of the characters that keys are made of with a digit among them.
Left out, unless an assignment to a key-like name comes before: digests (hex of a digest's length), UUIDs, names
joined from words that the vocabulary knows, and parts of addresses and paths. Left out always: digests in the caller's
table and numbers.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellspace.llm.bpe import encoding
from cellspace.llm.common import map_batches, pieces, tokenizer_path

#: Most characters per token of a string that counts as random.
MAX_RATIO = 2.6
MIN_LENGTH = 16
MASK = "[SECRET]"

_RUN = re.compile(r"[A-Za-z0-9+/_=\-]{16,}")
#: True for exactly the texts that hold a run of 16 with a digit in it.
JVM_RUN = r"(?=[A-Za-z+/_=\-]{0,15}[0-9])[A-Za-z0-9+/_=\-]{16}"
_ASSIGNED = re.compile(r"(?:api[_\- ]?key|secret|token|passw(?:or)?d|pwd|credential|private[_\- ]?key|access[_\- ]?key|auth(?:orization)?|bearer|client[_\- ]?id)[\w\-]{0,20}[\"']?\s{0,3}(?:=>|:=|[=:]|\s)\s{0,3}[\"'`]?$", re.IGNORECASE)
_DIGEST_NAME = re.compile(r"(?:sha-?\d{0,3}|md5|digest|checksum|commit|etag|revision|integrity|fingerprint)[\w\-]{0,10}[\"']?\s{0,3}[=:]?\s{0,3}[\"'`(]?$", re.IGNORECASE)
_HEX = re.compile(r"[0-9a-f]+|[0-9A-F]+")
_UUID = re.compile(r"[0-9a-fA-F]{8}(?:-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}")
_WORD = r"(?:[A-Z]?[a-z]{2,}(?:[A-Z][a-z]+)*|[A-Z]{2,})"
#: Words (case changes begin a new one) and short numbers between separators; a number may end a word.
_NAME = re.compile(rf"(?:{_WORD}\d{{0,4}}|\d{{1,4}})(?:[_\-/](?:{_WORD}\d{{0,4}}|\d{{1,4}}))*")
_LETTERS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
_PATH = re.compile(r"(?:https?:|www\.|@|\\|~/|\./)\S*$")


def is_name(s: str, encode, max_ratio: float = MAX_RATIO) -> bool:
    """Whether ``s`` is joined from words and numbers and the words, one by one, need few tokens."""
    if not _NAME.fullmatch(s):
        return False
    words = _LETTERS.findall(s)
    return not words or sum(map(len, words)) > max_ratio * sum(len(encode(w)) for w in words)


def find_secrets(text: str, encode, known: frozenset[str] = frozenset(), max_ratio: float = MAX_RATIO) -> list[tuple[int, int, int, bool]]:
    """(first character, characters, tokens, whether a key-like name is assigned) of each secret."""
    out = []
    for m in _RUN.finditer(text):
        s, at = m.group(), m.start()
        lead = len(s) - len(s.lstrip("=-+/"))
        s, at = s[lead:].rstrip("="), at + lead
        if "=" in s:  # name=value in one run
            cut = s.rindex("=") + 1
            s, at = s[cut:], at + cut
        if len(s) < MIN_LENGTH or s.isdigit() or s.isalpha() or not any(c.isdigit() for c in s) or s.lower() in known:
            continue
        before = text[max(0, at - 60) : at]
        named = bool(_ASSIGNED.search(before))
        if not named:
            if _PATH.search(before.rsplit(None, 1)[-1] if before and not before[-1].isspace() else ""):
                continue
            if _DIGEST_NAME.search(before) or _UUID.fullmatch(s) or (_HEX.fullmatch(s) and len(s) in (32, 40, 56, 64, 96, 128)) or is_name(s, encode, max_ratio):
                continue
        n = len(encode(s))
        if len(s) / n <= max_ratio:
            out.append((at, len(s), n, named))
    return out


def _candidates(text: F.Column) -> F.Column:
    return text.rlike(JVM_RUN)


def secret_scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", known: frozenset[str] = frozenset(), max_ratio: float = MAX_RATIO, vocabulary: str = tokenizer_path("byte_bpe_50k.tiktoken")) -> DataFrame:
    """(id, at, length, tokens, ratio, named): every secret with its place in characters; never its text.

    Null and empty texts have no rows; a null id stays null; repeated rows give repeated rows. ``known`` holds
    lower-case digests that aren't secrets.
    """
    df = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).where(_candidates(F.col("text")))
    kind = df.schema["id"].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoding(vocabulary).encode_ordinary
        for part, texts in pieces(batches):
            rows = [(i, a, n, t, round(n / t, 6), c) for i, text in zip(part.column(0).to_pylist(), texts, strict=True) for a, n, t, c in find_secrets(text, encode, known, max_ratio)]
            if rows:
                types = [part.column(0).type, pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.bool_()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=["id", "at", "length", "tokens", "ratio", "named"])

    return map_batches(df, kernel, f"id {kind}, at int, length int, tokens int, ratio double, named boolean").withColumnRenamed("id", id_col)


def mask_secrets(docs: DataFrame, text_col: str = "text", length_col: str | None = "n_chars", known: frozenset[str] = frozenset(), max_ratio: float = MAX_RATIO, vocabulary: str = tokenizer_path("byte_bpe_50k.tiktoken")) -> DataFrame:
    """``docs`` with every secret of the text replaced by a mark and, if there is one, the length column renewed.

    No row goes. Rows without candidates, null and empty texts are passed on untouched and stay in the JVM.
    """
    names = docs.columns
    at = names.index(text_col)
    count = names.index(length_col) if length_col in names else None

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoding(vocabulary).encode_ordinary
        for part, texts in pieces(batches, at):
            new = []
            for text in texts:
                for a, n, _, _ in reversed(find_secrets(text, encode, known, max_ratio)):
                    text = text[:a] + MASK + text[a + n :]
                new.append(text)
            cols = list(part.columns)
            cols[at] = pa.array(new, part.column(at).type)
            if count is not None:
                cols[count] = pa.array([len(t) for t in new], part.column(count).type)
            yield pa.RecordBatch.from_arrays(cols, schema=part.schema)

    hit = F.coalesce(_candidates(F.col(text_col)), F.lit(False))
    changed = map_batches(docs.where(hit), kernel, docs.schema)
    return docs.where(~hit).unionByName(changed)
