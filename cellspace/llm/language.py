"""Language of each word in code-switched text by a linear-chain conditional random field.

A word's features are its prefixes and suffixes of one to three bytes, its byte pairs and triples, its length, and its
standing in a lexicon (the language that has most of its uses in the training sample, by how clear a margin). Features
are hashed; states are the languages, with learned transitions between neighbouring words. Training sequences switch
between languages; the gradient is the difference of observed and expected features, by forward-backward. Labels are
the states of greatest marginal probability, by forward-backward over all words of a document.

The fit uses at most ``TRAIN_PER_LANG`` documents of each language, chosen by hash (its only bound). Scoring runs over
every whole text, keeps a row of state scores for each distinct word of a task, and moves no data.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cellspace.llm.common import WordIds, folded_words, map_batches, maybe_broadcast, mix, pieces, staged, word_hashes

DIMS = 1 << 16
TRAIN_PER_LANG = 250
STEPS, LANES, LENGTH = 150, 64, 32


def byte_table(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    n = np.fromiter(map(len, words), np.int64, len(words))
    width = int(n.max()) if len(n) else 1
    data = np.frombuffer(b"".join([w.ljust(width, b"\0") for w in words]), np.uint8).reshape(len(words), width)
    return data.astype(np.uint64), n


def feature_columns(words: list[bytes], lexicon: dict[bytes, int]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(rows, hashed feature of each): one kind of feature after the other, of words of like length together."""
    width = np.fromiter((max(5, len(w).bit_length()) for w in words), np.int64, len(words))
    for k in np.unique(width):
        at = np.flatnonzero(width == k)
        for rows, feature in _features([words[i] for i in at], lexicon):
            yield at[rows], feature


def _features(words: list[bytes], lexicon: dict[bytes, int]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    data, n = byte_table(words)
    every = np.arange(len(words))

    def hashed(x: np.ndarray, kind: int) -> np.ndarray:
        return (mix(x + np.uint64(kind << 56)) & np.uint64(DIMS - 1)).astype(np.int64)

    yield every, hashed(np.minimum(n, 20).astype(np.uint64), 1)
    pre, suf = np.zeros(len(words), np.uint64), np.zeros(len(words), np.uint64)
    for k in range(3):
        rows = every[n > k]
        if len(rows):
            pre[rows] = (pre[rows] << np.uint64(8)) | data[rows, k]
            suf[rows] |= data[rows, n[rows] - 1 - k] << np.uint64(8 * k)
            yield rows, hashed(pre[rows], 2 + k)
            yield rows, hashed(suf[rows], 5 + k)
    for k in range(data.shape[1] - 1):
        rows = every[n > k + 1]
        two = (data[rows, k] << np.uint64(8)) | data[rows, k + 1]
        yield rows, hashed(two, 8)
        rows = every[n > k + 2]
        if len(rows):
            yield rows, hashed((data[rows, k] << np.uint64(16)) | (data[rows, k + 1] << np.uint64(8)) | data[rows, k + 2], 9)
    yield every, hashed(np.fromiter((lexicon.get(w, 0) for w in words), np.uint64, len(words)), 10)


def forward_backward(emit: np.ndarray, move: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Marginals [time, lane, state], expected transitions [state, state] and the log partition sum.

    ``emit`` are scores [time, lane, state]; lanes are in order of falling length, so those still running at a time are
    the first ones.
    """
    T, _, K = emit.shape
    top = emit.max(2, keepdims=True)
    e, m = np.exp(emit - top), np.exp(move)
    alpha, scale = np.empty_like(e), np.ones(emit.shape[:2], e.dtype)
    running = [int(np.searchsorted(-lengths, -t, "left")) for t in range(T)]  # lanes with length > t
    for t in range(T):
        b = running[t]
        a = e[t, :b] if t == 0 else (alpha[t - 1, :b] @ m) * e[t, :b]
        s = a.sum(1)
        alpha[t, :b], scale[t, :b] = a / s[:, None], s
    marginal, pairs = np.zeros_like(e), np.zeros((K, K))
    beta = np.ones((emit.shape[1], K), e.dtype)
    for t in range(T - 1, -1, -1):
        b = running[t]
        if t + 1 < T and (c := running[t + 1]):
            right = e[t + 1, :c] * beta[:c] / scale[t + 1, :c, None]
            pairs += (alpha[t, :c].T @ right) * m
            beta[:c] = right @ m.T
        marginal[t, :b] = alpha[t, :b] * beta[:b]
    log_z = float(sum(np.log(scale[t, : running[t]]).sum() + top[t, : running[t], 0].sum() for t in range(T)))
    return marginal, pairs, log_z


@dataclass
class LanguageModel:
    languages: list[str]
    weights: np.ndarray
    move: np.ndarray
    lexicon: dict[bytes, int]

    def word_scores(self, words: list[bytes]) -> list[np.ndarray]:
        out = np.zeros((len(words), len(self.languages)), np.float32)
        for rows, feature in feature_columns(words, self.lexicon):
            out[rows] += self.weights[feature]
        return [out]

    def marginals(self, docs: list[list[bytes]], ids: WordIds) -> list[np.ndarray]:
        """[words, languages] for each document."""
        flat, lengths = ids(docs)
        scores = ids.rows[0]
        starts, order = np.cumsum(lengths) - lengths, np.argsort(-lengths, kind="stable")
        out: list[np.ndarray] = [np.zeros((0, len(self.languages)), np.float32)] * len(docs)
        at = 0
        while at < len(order) and lengths[order[at]]:  # lanes of alike length share a table
            T = int(lengths[order[at]])
            to = at + 1
            while to < len(order) and lengths[order[to]] and (lengths[order[to]] * 2 > T or T < 64) and (to - at) * T < 400_000:
                to += 1
            lanes = order[at:to]
            where = np.minimum(starts[lanes] + np.arange(T)[:, None], len(flat) - 1)
            marginal, _, _ = forward_backward(scores[flat[where]], self.move, lengths[lanes])
            for k, d in enumerate(lanes):
                out[d] = marginal[: lengths[d], k]
            at = to
        return out


def make_lexicon(words: dict[str, Counter], languages: list[str]) -> dict[bytes, int]:
    """1 + language * 3 + margin (0 half to 2 all of the uses) for words used more than once in the sample."""
    total = Counter()
    for c in words.values():
        total.update(c)
    size = {g: max(1, sum(words[g].values())) for g in languages}
    out = {}
    for w, n in total.items():
        if n > 1:
            rates = [words[g][w] / size[g] for g in languages]
            best = int(np.argmax(rates))
            share = rates[best] / sum(rates)
            out[w] = 1 + best * 3 + (share > 0.7) + (share > 0.95) if share > 0.5 else 1 + 3 * len(languages)
    return out


def switched_sequences(docs: dict[str, list[list[bytes]]], languages: list[str], lanes: int, length: int, rng: np.random.Generator) -> tuple[list[list[bytes]], np.ndarray]:
    """Lanes of ``length`` words that switch language after runs of 1 to 24 words, with their states [length, lane]."""
    words, states = [], np.zeros((length, lanes), np.int64)
    for lane in range(lanes):
        row: list[bytes] = []
        while len(row) < length:
            g = int(rng.integers(len(languages)))
            pool = docs[languages[g]]
            doc = pool[int(rng.integers(len(pool)))]
            run = int(np.exp(rng.uniform(0, np.log(24))))
            at = int(rng.integers(max(1, len(doc) - run)))
            part = doc[at : at + min(run, length - len(row))]
            states[len(row) : len(row) + len(part), lane] = g
            row += part
        words.append(row)
    return words, states


def train(docs: dict[str, list[list[bytes]]], steps: int = STEPS, seed: int = 0) -> LanguageModel:
    """Fits by stochastic gradients with step sizes by coordinate. ``docs``: word lists by language."""
    languages = sorted(g for g, d in docs.items() if any(d))
    docs = {g: [d for d in docs[g] if d] for g in languages}
    K = len(languages)
    counts = {g: Counter(w for d in docs[g] for w in d) for g in languages}
    lexicon = make_lexicon(counts, languages)
    # words seen once have no entry, as unknown words will; some of the known ones are hidden while training
    weights, move = np.zeros((DIMS, K)), np.zeros((K, K))
    g2w, g2m = np.full((DIMS, K), 1e-6), np.full((K, K), 1e-6)
    rng = np.random.default_rng(seed)
    for _ in range(steps):
        seqs, states = switched_sequences(docs, languages, LANES, LENGTH, rng)
        flat = [w for t in range(LENGTH) for w in (s[t] for s in seqs)]
        kinds = list(dict.fromkeys(flat))
        hidden = {w: v for w, v in lexicon.items() if rng.random() > 0.3} if _ % 10 == 0 else hidden  # noqa: F821
        place = {w: k for k, w in enumerate(kinds)}
        at = np.fromiter(map(place.__getitem__, flat), np.int64, len(flat))
        cols = list(feature_columns(kinds, hidden))
        score = np.zeros((len(kinds), K))
        for rows, f in cols:
            score[rows] += weights[f]
        emit = score[at].reshape(LENGTH, LANES, K)
        marginal, pairs, _z = forward_backward(emit, move, np.full(LANES, LENGTH))
        seen = np.eye(K)[states]
        grad = np.zeros((len(kinds), K))
        np.add.at(grad, at, (seen - marginal).reshape(-1, K))
        gw = np.zeros((DIMS, K))
        for rows, f in cols:
            for k in range(K):
                gw[:, k] += np.bincount(f, grad[rows, k], DIMS)
        real = np.zeros((K, K))
        np.add.at(real, (states[:-1].ravel(), states[1:].ravel()), 1)
        gw, gm = gw / LANES - 1e-5 * weights, (real - pairs) / LANES - 1e-4 * move
        g2w += gw**2
        g2m += gm**2
        weights += 0.3 * gw / np.sqrt(g2w)
        move += 0.1 * gm / np.sqrt(g2m)
    return LanguageModel(languages, weights.astype(np.float32), move.astype(np.float32), lexicon)


def fit_languages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_lang: int = TRAIN_PER_LANG, steps: int = STEPS) -> LanguageModel:
    """Fits to ``per_lang`` documents of each language, in the order of a hash of their ids; null ids, texts and
    languages are left out, of rows with one id and language the least text counts. Without any the model knows one
    language, "und"."""
    ids = docs.select(F.col(id_col).alias("id"), F.col(lang_col).alias("lang")).where(F.col("id").isNotNull() & F.col("lang").isNotNull() & F.col(text_col).isNotNull())
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("id"), "id"))
    chosen = staged(ids.withColumn("place", place).where(F.col("place") <= per_lang).select("id", "lang").distinct(), "chosen")
    sample: dict[str, dict] = defaultdict(dict)
    text = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).where("text is not null")
    found = text.join(maybe_broadcast(chosen, chosen.count(), 32), "id").groupBy("lang", "id").agg(F.min("text").alias("text"))
    for r in found.toLocalIterator():
        sample[r["lang"]][r["id"]] = folded_words(r["text"])
    pools = {g: [d[i] for i in sorted(d)] for g, d in sample.items()}
    if not any(any(p) for p in pools.values()):
        return LanguageModel(["und"], np.zeros((DIMS, 1), np.float32), np.zeros((1, 1), np.float32), {})
    return train(pools, steps)


def language_labels(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, language, confidence, words, switches, segments) of each document.

    ``language`` has most words (ties: first by name); ``confidence`` is its mean marginal over its words; segments
    are runs (language, first word, words) in order and cover every word. A null text gives nulls and no segments;
    one without words gives a null language, 0 words and no segments. Null ids stay null; repeated rows repeat.
    """
    df = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = df.schema["id"].dataType.simpleString()
    sent = df.sparkSession.sparkContext.broadcast(model)
    runs = pa.struct([("language", pa.string()), ("first_word", pa.int32()), ("words", pa.int32())])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        ids, names, K = WordIds(m.word_scores, 250_000), m.languages, len(m.languages)
        for part, texts in pieces(batches, 1, 3_000_000):
            rows = []
            for t, p in zip(texts, m.marginals([folded_words(t or "") for t in texts], ids), strict=True):
                if not len(p):
                    rows.append((None, None, None if t is None else 0, None if t is None else 0, []))
                    continue
                label = p.argmax(1)
                best = int(np.bincount(label, minlength=K).argmax())
                change = np.concatenate([[0], np.flatnonzero(label[1:] != label[:-1]) + 1, [len(label)]])
                segments = [(names[label[a]], int(a), int(b - a)) for a, b in zip(change[:-1], change[1:], strict=True)]
                rows.append((names[best], round(float(p[label == best, best].mean()), 6), len(label), len(change) - 2, segments))
            cols = list(zip(*rows, strict=True))
            kinds = [pa.string(), pa.float64(), pa.int32(), pa.int32(), pa.list_(runs)]
            made = [pa.array(c, k) for c, k in zip(cols[:4], kinds, strict=False)]
            flat = [s for c in cols[4] for s in c]
            ends = np.concatenate([[0], np.cumsum([len(c) for c in cols[4]])]).astype(np.int32)
            inner = pa.StructArray.from_arrays([pa.array([s[0] for s in flat], pa.string()), pa.array([s[1] for s in flat], pa.int32()), pa.array([s[2] for s in flat], pa.int32())], fields=list(runs))
            yield pa.RecordBatch.from_arrays([part.column(0), *made, pa.ListArray.from_arrays(pa.array(ends), inner)], names=["id", "language", "confidence", "words", "switches", "segments"])

    out = map_batches(df, kernel, f"id {kind}, language string, confidence double, words int, switches int, segments array<struct<language:string,first_word:int,words:int>>")
    return out.withColumnRenamed("id", id_col)
