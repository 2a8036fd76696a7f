"""Whole operators against plain loops, and the odd cases: id types, repeated rows, empty tables, clashing columns."""

import itertools
import math
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellspace.llm import bpe, exact_dedup, language, licenses, lm, packing, quality, secrets, simhash, topk
from cellspace.llm.bpe import encoding
from cellspace.llm.common import WordIds, folded_words, mix, tokenizer_path, word_hashes

SF = "/root/testdata/sf0.001"
VOCAB = tokenizer_path("byte_bpe_50k.tiktoken")
CLASH = "text string, lang string, source string, n_chars long, score double, keep_id long, row long, node long, at int, size int, n int, tokens string, `__x` string"


def frame(spark, rows, kind="long"):
    cast = {"long": lambda i: i, "string": lambda i: None if i is None else f"d{i:04d}", "smallint": lambda i: i}[kind]
    return spark.createDataFrame([(cast(i), t, "en", "s", len(t or ""), 0.5, 9, 3, 4, 5, 1, 7, "x", "y") for i, t in rows], f"doc_id {kind}, {CLASH}")


def words(n, seed=0):
    rng = np.random.default_rng(seed)
    return " ".join(f"w{k}" for k in rng.integers(0, 400, n))


# --- near duplicates --------------------------------------------------------------------------------------------
def plain_prints(text):
    """The prints of one text by loops over words, triples and bits."""
    flat = folded_words(text or "")
    if not flat:
        return None
    bit = lambda h, salt: np.unpackbits(np.array([mix(np.array([h + salt * 0x9E3779B97F4A7C15 & 2**64 - 1], np.uint64))[0]]).view(np.uint8))
    h = {w: int(word_hashes([w])[0]) for w in flat}
    total, check = np.zeros((3, 64)), np.zeros((2, 64))
    for w, n in Counter(flat).items():
        weight = round(8 * (1 + math.log(n)))
        for s in range(3):
            total[s] += weight * (2.0 * bit(h[w], 1 + s) - 1)
    grams = [h[a] + 3 * h[b] + 7 * h[c] & 2**64 - 1 for a, b, c in zip(flat, flat[1:], flat[2:])] if len(flat) >= 3 else [h[w] for w in flat]
    for g in grams:
        for s in range(2):
            check[s] += 2.0 * bit(g, 100 + s) - 1
    return total > 0, check > 0


def plain_groups(rows):
    """Least id and size of the group of each row, by comparing all pairs, and a name of each row's group."""
    prints = [plain_prints(t) for _, t in rows]
    up = list(range(len(rows)))

    def root(k):
        while up[k] != k:
            k = up[k]
        return k

    for i, j in itertools.combinations(range(len(rows)), 2):
        if prints[i] is not None and prints[j] is not None:
            (fa, ca), (fb, cb) = prints[i], prints[j]
            if min((fa != fb).sum(1)) <= simhash.DISTANCE and (ca != cb).sum() <= simhash.CHECK_DISTANCE:
                up[root(j)] = root(i)
    members = {}
    for k in range(len(rows)):
        members.setdefault(root(k), []).append(k)
    out = []
    for k in range(len(rows)):
        own = members[root(k)]
        ids = [rows[m][0] for m in own if rows[m][0] is not None]
        out.append((rows[k][0], min(ids) if ids else None, len(own)))
    return out, [root(k) for k in range(len(rows))]


def chain(n, seed):
    """Texts each of which is a near copy of the one before, the last far from the first."""
    rng = np.random.default_rng(seed)
    now, out = words(120, seed).split(), []
    for _ in range(n):
        out.append(" ".join(now))
        for at in rng.choice(120, 3, replace=False):
            now[at] = f"n{rng.integers(10**6)}"
    return out


NEAR = [*[(k, t) for k, t in enumerate(chain(12, 1), 10)], (1, "alpha beta"), (2, "alpha beta"), (5, words(90, 7)), (5, words(90, 8)), (5, words(90, 8)), (6, words(90, 7).replace("w1 ", "x1 ")), (3, None), (4, ""), (7, "?!"), (None, words(90, 7)), (None, words(90, 9)), (8, "tail " * 5_000)]


@pytest.mark.parametrize("kind", ["long", "string"])
def test_near_groups_equal_all_pairs(spark, kind):
    df = frame(spark, NEAR, kind)
    want, roots = plain_groups(NEAR)
    groups = len(set(roots))
    got = simhash.near_groups(df).collect()
    number = (lambda x: x and int(x[1:])) if kind == "string" else lambda x: x
    assert Counter((number(r.doc_id), number(r.group_id), r.group_size) for r in got) == Counter(want)
    assert sum(not r.is_near_copy for r in got) == groups
    kept = simhash.drop_near_copies(df)
    assert kept.columns == df.columns and kept.count() == groups
    assert {number(r.doc_id) for r in kept.collect()} >= {1, 3, 4, 7, 8}


def test_rows_with_one_id_and_different_texts_stay(spark):
    a, b = words(80, 1), words(80, 2)
    rows = [(1, a), (5, a + " more"), (5, b)]
    assert sorted((r.doc_id, r.text) for r in simhash.drop_near_copies(frame(spark, rows)).collect()) == sorted([(1, a), (5, b)])
    twice = simhash.near_groups(frame(spark, [(1, a), (1, a)])).collect()
    assert sorted(r.is_near_copy for r in twice) == [False, True] and simhash.drop_near_copies(frame(spark, [(1, a), (1, a)])).count() == 1
    assert simhash.drop_near_copies(frame(spark, [])).count() == 0


# --- exact duplicates -------------------------------------------------------------------------------------------
@pytest.mark.parametrize("kind", ["long", "string", "smallint"])
def test_exact_groups_equal_a_loop(spark, kind):
    rng = np.random.default_rng(3)
    rows = [(int(i), f"t{rng.integers(60)}") for i in range(300)] + [(900, None), (901, ""), (901, ""), (None, "t1")]
    number = (lambda x: x and int(x[1:])) if kind == "string" else lambda x: x
    seen = {}
    for i, t in rows:
        seen.setdefault(t, []).append(i)
    want = Counter((i, i if t is None else min(x for x in seen[t] if x is not None), 1 if t is None else len(seen[t])) for i, t in rows)
    index = exact_dedup.build_index(frame(spark, rows, kind), capacity=2)
    assert index.directory.global_depth >= 3 and len(index.directory.first) > 8
    entries = index.entries.withColumn("part", F.input_file_name()).collect()
    for owner in {r["__cs_owner"] for r in entries}:
        mine = [r for r in entries if r["__cs_owner"] == owner]
        keys = [r["__cs_key"] % 2**64 for r in mine]
        assert len({r.part for r in mine}) == 1
        others = [r["__cs_key"] % 2**64 for r in entries if r["__cs_owner"] != owner]
        assert not any(min(keys) < k < max(keys) for k in others)  # an owner holds a range of keys
    for capacity in (2, None):
        got = exact_dedup.exact_groups(frame(spark, rows, kind), capacity=capacity).collect()
        assert Counter((number(r.doc_id), number(r.keep_id), r.copies) for r in got) == want
        assert sum(not r.is_copy for r in got) == len(seen)


# --- secrets ----------------------------------------------------------------------------------------------------
def test_secret_scan_equals_a_loop(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    encode = encoding(VOCAB).encode_ordinary
    want = Counter((r.doc_id, a, n, t) for r in docs.collect() if r.text for a, n, t, _ in secrets.find_secrets(r.text, encode))
    got = secrets.secret_scan(docs).collect()
    assert Counter((r.doc_id, r["at"], r.length, r.tokens) for r in got) == want and want
    by = {r.doc_id: r.text for r in docs.collect()}
    for r in got:  # each is a maximal run with few characters a token
        s = by[r.doc_id][r["at"] : r["at"] + r.length]
        assert len(s) == r.length and len(encode(s)) == r.tokens and len(s) / r.tokens <= secrets.MAX_RATIO and re.search(r"\d", s)
    assert secrets.secret_scan(frame(spark, [])).count() == 0 and secrets.mask_secrets(frame(spark, [])).count() == 0
    odd = frame(spark, [(None, "token = 'q8Zx7Lw2Tn5Rv9Kc3Bm6'"), (1, None), (2, "")])
    assert [r.doc_id for r in secrets.secret_scan(odd).collect()] == [None]
    assert {r.text for r in secrets.mask_secrets(odd).collect()} == {"token = '[SECRET]'", None, ""}


# --- quality ----------------------------------------------------------------------------------------------------
def plain_indicators(text):
    """The set of hashed words, pairs, shapes and shape pairs, one by one."""
    flat = text.encode().split()
    h, shape = ([int(x) for x in r] for r in quality.word_rows(flat)) if flat else ([], [])
    M, G = 2**64 - 1, 0x9E3779B97F4A7C15
    raw = [x + G & M for x in h] + [x + 3 * G & M for x in shape]
    for k in range(len(flat) - 1):
        raw.append(3 * h[k] + h[k + 1] + 2 * G & M)
        raw.append((shape[k] << 20) + (shape[k + 1] << 1) + (flat[k] == flat[k + 1]) + 4 * G & M)
    return {int(x) for x in mix(np.array(raw, np.uint64)) & np.uint64(quality.DIMS - 1)} if raw else set()


def test_quality_scores_equal_plain_sums(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    m = quality.fit_quality(docs, labels)
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in quality.quality_scores(docs, m).collect():
        t = texts[r.doc_id] or ""
        s = sum(m.weights[f] for f in plain_indicators(t)) + m.bias
        assert abs(s - r.score) < 1e-4 and r.keep == (s >= m.threshold and bool(t.strip()))
    rows = [plain_indicators(t) for t in ("a b", "a c", "d")]
    ratio = quality.log_count_ratios([np.array(sorted(r)) for r in rows], np.array([1, 1, -1]))
    up, down = Counter(f for r in rows[:2] for f in r), Counter(rows[2])
    for f in set().union(*rows):
        want = math.log((up[f] + 1) / (sum(up.values()) + quality.DIMS)) - math.log((down[f] + 1) / (sum(down.values()) + quality.DIMS))
        assert abs(ratio[f] - want) < 1e-9
    odd = frame(spark, [(None, "a b c"), (1, "a b c"), (1, "a b c"), (2, None)])
    assert sorted(str(r.doc_id) for r in quality.quality_scores(odd, m).collect()) == ["1", "1", "2", "None"]
    assert quality.keep_quality(frame(spark, []), m).count() == 0
    nothing = quality.fit_quality(frame(spark, []), labels)
    assert nothing.threshold == 0 and all(r["keep"] for r in quality.quality_scores(odd.where("text is not null"), nothing).collect())


# --- language ---------------------------------------------------------------------------------------------------
def test_language_equals_enumeration(spark):
    docs = spark.createDataFrame([(i, words(30, i) if g == "en" else "".join(chr(97 + (i * k) % 7) + " " for k in range(40)), g) for i, g in enumerate(["en", "fr"] * 12)], "doc_id long, text string, lang string")
    m = language.fit_languages(docs, steps=20)
    K = len(m.languages)
    rows = [(1, "a b w3"), (2, "w1 w2 w3 d e"), (3, "x" * 5000 + " w4"), (4, "b"), (4, "b"), (None, "a w9"), (5, None), (6, "")]
    got = language.language_labels(frame(spark, rows), m).collect()
    assert len(got) == len(rows)
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
    for i, t in rows:
        flat = folded_words(t or "")
        for r in by[i]:
            if not flat:
                assert r.language is None and r.words == (None if t is None else 0)
                continue
            emit = m.word_scores(flat)[0].astype(float)
            marginal = np.zeros((len(flat), K))
            for path in itertools.product(range(K), repeat=len(flat)):
                p = math.exp(sum(emit[k, s] for k, s in enumerate(path)) + sum(m.move[a, b] for a, b in itertools.pairwise(path)) - emit.max(1).sum())
                for k, s in enumerate(path):
                    marginal[k, s] += p
            marginal /= marginal.sum(1, keepdims=True)
            label = marginal.argmax(1)
            best = int(np.bincount(label, minlength=K).argmax())
            assert r.language == m.languages[best] and r.words == len(flat) and abs(r.confidence - marginal[label == best, best].mean()) < 1e-3
            assert [m.languages[s] for s in label] == [s.language for s in r.segments for _ in range(s.words)]
    assert language.language_labels(frame(spark, []), m).count() == 0
    assert language.fit_languages(frame(spark, []), steps=1).languages == ["und"]


def test_every_byte_of_a_long_word_counts():
    m = language.LanguageModel(["a", "b"], np.random.default_rng(0).standard_normal((language.DIMS, 2)), np.zeros((2, 2)), {})
    long = b"q" * 100 + b"z" + b"q" * 100
    assert not np.allclose(m.word_scores([long])[0], m.word_scores([b"q" * 201])[0])
    one = np.concatenate([m.word_scores([w])[0] for w in (long, b"ab", b"c", b"qq" * 40)])
    assert np.allclose(one, m.word_scores([long, b"ab", b"c", b"qq" * 40])[0], atol=1e-3)


# --- licences ---------------------------------------------------------------------------------------------------
def test_fillings_are_bounded_by_their_pattern(spark):
    automata = {n: licenses.compile_template(t) for n, t in licenses.TEMPLATES.items()}
    need = licenses.anchors(automata)
    plain = re.sub(r"<<(?:beginOptional|endOptional)>>", "", licenses.TEMPLATES["mit-text"])
    fill = lambda what, rest="THE AUTHORS": re.sub(r"<<var;name=\"what\"[^>]*>>", what, re.sub(r"<<var;name=\"holders\"[^>]*>>", rest, plain))
    scan = lambda t: {m[0] for m in licenses.scan_text(t, automata, need)}
    assert "mit-text" in scan(fill("this software")) and "mit-text" in scan(fill(" ".join("abcdefghijklmnopqrstuvwxyzabcdefghijklmnop")))
    assert "mit-text" not in scan(fill("x" * 130)) and "mit-text" not in scan(fill("this software").replace("NONINFRINGEMENT", "INFRINGEMENT"))
    for name, markup in licenses.TEMPLATES.items():  # each template accepts its own original wording
        own = re.sub(r"<<var;[^>]*original=\"([^\"]*)\"[^>]*>>", lambda m: m.group(1), re.sub(r"<<(?:beginOptional|endOptional)>>", "", markup))
        assert name in scan(f"before. {own} after"), name
    df = frame(spark, [(None, "Released under the MIT License."), (3, "Released under the MIT License."), (3, "Released under the MIT License.")])
    assert [r.doc_id for r in licenses.license_scan(df).orderBy("doc_id").collect()] == [None, 3, 3]


# --- tokens -----------------------------------------------------------------------------------------------------
def test_shared_chunks_are_encoded_once_and_joined(spark):
    passage = words(900, 5)
    rows = [(i, words(200, i) + " " + passage + " " + words(100, 50 + i)) for i in range(6)] + [(7, passage), (7, passage), (8, None), (9, "")]
    df = frame(spark, rows).select(F.xxhash64("text").alias("text_hash"), "text").where("text is not null")
    table, lists = bpe.shared_chunks(df, VOCAB)
    count = Counter(bpe.chunk_hash(c) for _, t in rows if t for c in bpe.chunks_of(t))
    assert sorted(r.h for r in table.collect()) == sorted(h for h, n in count.items() if n > 1) and lists.count() >= 6
    plain, got = encoding(VOCAB), bpe.bpe_encode(frame(spark, rows)).collect()
    assert sorted(map(str, ((r.doc_id, r.tokens) for r in got))) == sorted(map(str, ((i, None if t is None else plain.encode_ordinary(t)) for i, t in rows)))
    coder = bpe.ChunkEncoder(VOCAB)
    wrong = np.array(plain.encode_ordinary("something else"), np.int32).tobytes()
    assert coder.text(rows[0][1], {0: wrong}).tolist() == plain.encode_ordinary(rows[0][1])
    assert bpe.bpe_encode(frame(spark, [])).count() == 0 and bpe.bpe_decode(bpe.bpe_encode(frame(spark, []))).count() == 0


# --- packing ----------------------------------------------------------------------------------------------------
@pytest.mark.parametrize("kind", ["string", "smallint"])
def test_packing_ids(spark, kind):
    rows = [(i, words(7, i)) for i in range(30)] + [(None, words(5)), (3, words(7, 3)), (40, None), (41, "")]
    out = packing.best_fit_pack(frame(spark, rows, kind), capacity=40, home_items=8).collect()
    assert len(out) >= len(rows) and sum(r.bin_id is None for r in out) == 2
    used = {}
    for r in out:
        if r.bin_id is not None:
            used.setdefault(r.bin_id, []).append((r.start, r.start + r.length))
    for spans in used.values():
        spans.sort()
        assert all(b <= c for (_, b), (c, _) in itertools.pairwise(spans)) and spans[-1][1] <= 40


# --- vectors ----------------------------------------------------------------------------------------------------
@pytest.mark.parametrize("kind", ["string", "smallint"])
def test_top_k_ids_and_odd_vectors(spark, kind):
    rng = np.random.default_rng(4)
    x = rng.standard_normal((120, 8)).round(2)
    x[5] = x[6] = x[7]
    cast = (lambda i: f"v{i:03d}") if kind == "string" else lambda i: i
    bad = [[float("nan")] * 8, [float("inf")] + [0.0] * 7, [], [None] * 8]
    rows = [(cast(i), v.tolist(), 1, 2) for i, v in enumerate(x)] + [(cast(200 + i), b, 1, 2) for i, b in enumerate(bad)]
    df = spark.createDataFrame(rows, f"vec_id {kind}, embedding array<float>, id int, no int")
    got = {}
    for r in topk.exact_top_k(df, 4, block=16, group_blocks=2).collect():
        got.setdefault(r.vec_id, []).append((r.rank, r.neighbour))
    x = x.astype(np.float32).astype(float)
    d = ((x[:, None] - x[None]) ** 2).sum(2)
    np.fill_diagonal(d, np.inf)
    assert len(got) == 120
    for i in range(120):
        assert [n for _, n in sorted(got[cast(i)])] == [cast(j) for j in sorted(range(120), key=lambda j: (d[i, j], j))[:4]]


def test_top_k_of_repeated_rows(spark):
    df = spark.createDataFrame([(1, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [3.0, 0.0])], "vec_id long, embedding array<double>")
    got = sorted((r.vec_id, r.rank, r.neighbour, r.distance) for r in topk.exact_top_k(df, 5).collect())
    assert got == [(1, 1, 1, 0.0), (1, 1, 1, 0.0), (1, 2, 2, 2.0), (1, 2, 2, 2.0), (2, 1, 1, 2.0), (2, 2, 1, 2.0)]


# --- language model ---------------------------------------------------------------------------------------------
def test_every_word_is_trained_on_once():
    v = lm.Vocabulary([b"a", b"b", b"c", b"d"], np.array([3, 4, 5, 2, 2, 1]), np.full(257, 5.0))
    for n in (1, 7, 100, 1003, 5000):
        m, seen = lm.RecurrentModel(v, 4), []
        plain = m.window_parts
        m.window_parts = lambda x, y, h, plain=plain, seen=seen: (seen.append(y.size), plain(x, y, h))[1]
        m.train_stream(np.random.default_rng(n).integers(0, 6, n + 1).astype(np.int32), lanes=16, window=5)
        assert sum(seen) == n


def test_classes_and_groups_sum_to_one():
    rng = np.random.default_rng(0)
    counts = np.concatenate([[50, 400], np.sort(rng.zipf(1.5, 3000) % 10_000 + 1)[::-1]])
    v = lm.Vocabulary([b"w%d" % k for k in range(3000)], counts, np.full(257, 5.0))
    m = lm.RecurrentModel(v, 6)
    h = rng.standard_normal((1, 6)).astype(np.float32).repeat(3002, 0)
    assert abs(np.exp(-m.output(h, np.arange(3002))).sum() - 1) < 1e-3
    assert len(v.group_starts) > 5 and v.group_starts[-1] == len(v.starts) - 1


# --- pipeline ---------------------------------------------------------------------------------------------------
def test_pipeline_equals_plain_stages(spark, tmp_path):
    import corpus_pipeline as cp

    rows = [(int(i), words(120, i)) for i in range(40)] + [(100, words(120, 3)), (101, words(120, 4) + " end"), (102, None), (103, ""), (104, "  "), (None, words(120, 77)), (5, words(120, 99)), (7, words(120, 7)), (8, words(60, 8) + " token = 'q8Zx7Lw2Tn5Rv9Kc3Bm6'")]
    frame(spark, rows).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(20)] + [(103, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs, d = spark.read.parquet(f"{tmp_path}/documents.parquet"), str(tmp_path)
    m = quality.fit_quality(docs, spark.read.parquet(f"{d}/labels.parquet"))
    ids = WordIds(quality.word_rows)
    now = [(i, t) for i, t in rows if t and t.strip() and m.score([t], ids)[0] >= m.threshold]
    first = {}
    for i, t in sorted(now, key=lambda r: (r[0] is None, r[0] or 0)):
        first.setdefault(t, i)
    now = [(i, t) for t, i in first.items()]
    groups = {}
    for (i, g, _), root, (_, t) in zip(*plain_groups(now), now, strict=True):
        if i == g:
            groups.setdefault(root, (i, t))
    encode = encoding(VOCAB).encode_ordinary
    want = {}
    for i, t in groups.values():
        for a, n, _, _ in reversed(secrets.find_secrets(t, encode)):
            t = t[:a] + secrets.MASK + t[a + n :]
        want[i] = want.get(i, 0) + len(encode(t))
    got = {}
    for r in cp.run(spark, d).collect():
        got[r.doc_id] = got.get(r.doc_id, 0) + r.length
    assert got == want and len(want) > 30
    (tmp_path / "none").mkdir()
    frame(spark, []).write.parquet(f"{tmp_path}/none/documents.parquet")
    spark.read.parquet(f"{d}/labels.parquet").limit(0).write.parquet(f"{tmp_path}/none/labels.parquet")
    assert cp.run(spark, f"{d}/none").count() == 0
