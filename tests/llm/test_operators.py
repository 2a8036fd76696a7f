"""Each operator against brute force, with nulls, empty and long texts, repeated rows, empty tables, clashing columns."""

import itertools

import numpy as np
import pyarrow as pa
import pytest

from cellspace.llm import exact_dedup, language, licenses, lm, packing, quality, secrets, simhash, topk
from cellspace.llm.bpe import ChunkEncoder, bpe_decode, bpe_encode, encoding
from cellspace.llm.common import WordIds, folded_words, tokenizer_path

VOCAB = tokenizer_path("byte_bpe_50k.tiktoken")
CLASH = "doc_id long, text string, lang string, source string, n_chars long, score double, keep_id long, `__x` string, size int"


def frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), 0.5, 9, "x", 1) for i, t in rows], CLASH)


def words(n, seed=0):
    rng = np.random.default_rng(seed)
    return " ".join(f"w{k}" for k in rng.integers(0, 400, n))


ODD = [(1, "a b c"), (2, "a b c"), (2, "a b c"), (3, None), (4, None), (5, ""), (6, ""), (None, "a b c"), (7, "long " * 30_000), (8, "  ")]


def test_directory_splits_and_doubles():
    counts = np.array([9, 1, 0, 1, 1, 1, 1, 1])
    d = exact_dedup.ExtendibleDirectory(counts, 3, 3)
    assert d.global_depth == 3 and all(d.size(b) <= 3 or d.local_depth[b] == 3 for b in range(len(d.first)))
    keys = (np.arange(8, dtype=np.uint64) << np.uint64(61)) + np.uint64(5)
    assert len({int(b) for b in d.lookup(keys)}) == len(d.first)
    assert sum(d.size(b) for b in range(len(d.first))) == counts.sum()


@pytest.mark.parametrize("capacity", [1, 65536])
def test_exact_groups(spark, capacity):
    got = exact_dedup.exact_groups(frame(spark, ODD), capacity=capacity).collect()
    assert len(got) == len(ODD)
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
    assert {(r.keep_id, r.copies) for i in (1, 2, None) for r in by[i]} == {(1, 4)}
    assert sum(not r.is_copy for i in (1, 2, None) for r in by[i]) == 1
    assert by[3][0].copies == 1 and not by[3][0].is_copy and by[6][0].keep_id == 5 and by[6][0].is_copy
    assert exact_dedup.exact_groups(frame(spark, [])).count() == 0


def test_drop_copies(spark):
    kept = exact_dedup.drop_copies(frame(spark, ODD))
    assert kept.columns == frame(spark, []).columns
    assert sorted((r.doc_id for r in kept.collect()), key=str) == [1, 3, 4, 5, 7, 8]


def test_equal_hashes_of_different_texts():
    import pyarrow as pa

    b = pa.RecordBatch.from_pydict({"b": [0, 0, 0], "k": [5, 5, 5], "t": ["x", "y", "x"], "i": [[3], [4], [1]]})
    out = [r for x in exact_dedup._chain_groups(pa.int64())([b]) for r in x.to_pylist()]
    assert sorted((r["id"], r["keep_id"], r["copies"]) for r in out) == [(1, 1, 2), (3, 1, 2), (4, 4, 1)]


def test_licenses():
    a = {n: licenses.compile_template(t) for n, t in licenses.TEMPLATES.items()}
    need = licenses.anchors(a)
    scan = lambda t: {m[0] for m in licenses.scan_text(t, a, need)}
    assert scan("x. Released under the MIT License. y") == {"mit-notice"}
    assert scan("This work is licensed under the GNU General Public License, version 3.") == {"gpl-notice"}
    assert scan("Licensed under CC BY-NC 4.0.") == {"cc-notice"}
    assert scan("LICENCED under the Apache licence, version 2.0") == {"apache-2.0-notice"}
    assert scan("Licensed under the Apache Software Licence") == set() and scan("the MIT License was released") == set() and scan("") == set()


def test_automaton_against_expansion():
    markup = 'a <<beginOptional>>b <<beginOptional>>c <<endOptional>><<endOptional>><<var;name="n";original="x";match="x( x)?">> d'
    auto = licenses.compile_template(markup)
    accepted = {(*p, *v, "d") for p in (("a",), ("a", "b"), ("a", "b", "c")) for v in (("x",), ("x", "x"))}
    for n in range(1, 7):
        for t in itertools.product("abcxd", repeat=n):
            assert (auto.match(list(t), 0) == n) == (t in accepted)
    with pytest.raises(ValueError):
        licenses.compile_template("a <<beginOptional>> b")


def test_license_scan_table(spark):
    df = frame(spark, [*ODD, (9, words(5000) + " Released under the MIT License.")])
    assert [(r.doc_id, r.license_id) for r in licenses.license_scan(df).collect()] == [(9, "mit-notice")]
    assert licenses.license_scan(frame(spark, [])).count() == 0


def test_secrets(spark):
    encode = encoding(VOCAB).encode_ordinary
    hexed = "254ca002228af484f240146ffd26ba4415598ee8"
    found = lambda t, **k: [t[a : a + n] for a, n, _, _ in secrets.find_secrets(t, encode, **k)]
    assert found(f'x token = "{hexed}" y') == [hexed] and found(f"commit {hexed}") == [] and found(f"sha1: {hexed}") == []
    assert found("id 123e4567-e89b-12d3-a456-426614174000") == [] and found("mail aa.bb@mail4.example.com") == []
    assert found("key AKq7Zx09PmV2sLd8Wq3R rest") == ["AKq7Zx09PmV2sLd8Wq3R"] and found("the version2_configuration_file") == []
    assert found(f"token = {hexed}", known=frozenset([hexed])) == []
    df = frame(spark, [*ODD, (9, f'a token = "{hexed}" b'), (9, f'a token = "{hexed}" b')])
    assert [r.doc_id for r in secrets.secret_scan(df).collect()] == [9, 9]
    masked = {r.text for r in secrets.mask_secrets(df).where("doc_id = 9").collect()}
    assert masked == {'a token = "[SECRET]" b'} and secrets.mask_secrets(df).count() == 12


def test_secrets_that_look_like_names():
    encode = encoding(VOCAB).encode_ordinary
    found = lambda t: [t[a : a + n] for a, n, _, _ in secrets.find_secrets(t, encode)]
    rng = np.random.default_rng(6)
    for alphabet, n, head in (("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", 16, "AKIA"), ("abcdefghijklmnopqrstuvwxyz0123456789", 20, ""), ("abcdefghijklmnopqrstuvwxyz0123456789", 32, "")):
        keys = [head + "".join(rng.choice(list(alphabet), n)) for _ in range(300)]
        keys = [k for k in keys if any(c.isdigit() for c in k)]
        assert np.mean([found(f"see {k} there") == [k] for k in keys]) > 0.95
    key = "q8Zx7Lw2Tn5Rv9Kc3Bm6"
    assert found(f"get https://host.example.com/x?api_key={key} now") == [key]
    assert found(f"get https://host.example.com/x/{key} now") == [] and found("on 2023-01-15-0042 at") == []
    assert found("the version2-configuration-file-17 and myServerName2_backupFolder") == []


def test_top_k(spark):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((300, 24)).round(3)
    x[10] = x[11]
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    df = spark.createDataFrame([*rows, (None, x[0].tolist()), (900, None), (901, [1.0, 2.0])], "vec_id long, embedding array<double>")
    got = {}
    for r in topk.exact_top_k(df, 7, block=40).collect():
        got.setdefault(r.vec_id, []).append((r.rank, r.neighbour))
    d = ((x[:, None] - x[None]) ** 2).sum(2)
    np.fill_diagonal(d, np.inf)
    for i in range(300):
        want = sorted(range(300), key=lambda j: (d[i, j], j))[:7]
        assert [n for _, n in sorted(got[i])] == want
    assert 901 not in got and topk.exact_top_k(df.limit(0)).count() == 0


def test_top_k_of_chosen_rows(spark):
    """Only chosen rows are queries, all rows are neighbours."""
    from pyspark.sql import functions as F

    rng = np.random.default_rng(8)
    x = rng.standard_normal((600, 20)).round(3)
    x[50] = x[51] = x[100]
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    df = spark.createDataFrame([*rows, (None, x[0].tolist()), (950, None), (1000, [1.0, 2.0]), (1003, [1.0, 3.0])], "vec_id long, embedding array<double>")
    d = ((x[:, None] - x[None]) ** 2).sum(2)
    np.fill_diagonal(d, np.inf)
    for every, block in ((50, 40), (50, 2048), (7, 30)):
        got = sorted((r.vec_id, r.rank, r.neighbour) for r in topk.exact_top_k(df, 7, block=block, group_blocks=2, queries=F.col("vec_id") % every == 0).collect())
        want = [(i, k + 1, n) for i in range(0, 600, every) for k, n in enumerate(sorted(range(600), key=lambda j: (d[i, j], j))[:7])]
        assert [g for g in got if g[0] < 900] == want
        assert [g for g in got if g[0] >= 900] == ([(1000, 1, 1003)] if every == 50 else [])


@pytest.mark.parametrize("shift,scale", [(30.0, 1.0), (1e5, 1.0), (0.0, 100.0), (0.0, 1e25)])
def test_top_k_far_from_the_origin(shift, scale):
    rng = np.random.default_rng(8)
    x = rng.standard_normal((400, 64)) * scale / 8 + shift
    d = ((x[:, None] - x[None]) ** 2).sum(2)
    np.fill_diagonal(d, np.inf)
    a, b = topk.Prepared(np.arange(200), x[:200]), topk.Prepared(np.arange(200, 400), x[200:], x[:200].mean(0))
    la, lb = topk.own_limits(a, 10), topk.own_limits(topk.Prepared(b.ids, b.x), 10)
    own = np.sort(d[:200, :200], 1)[:, 9]
    assert (la >= own).all()
    kept = np.zeros((200, 200), bool)
    for i, j in topk.survivors(a, b, la, lb, False):
        kept[i, j] = True
    assert kept[(d[:200, 200:] <= np.maximum(own[:, None], np.sort(d[200:, 200:], 1)[:, 9][None]))].all()


def test_lower_bounds_hold():
    rng = np.random.default_rng(1)
    x = rng.standard_normal((60, 30))
    d = ((x[:, None] - x[None]) ** 2).sum(2)
    for n in topk.levels_of(30):
        s = topk.statistics(x, n)
        assert (((s[:, None] - s[None]) ** 2).sum(2) <= d + 1e-9).all()


def test_quality(spark):
    good = [(300 + i, words(60, i)) for i in range(120)]
    bad = [(500 + i, " ".join(w + "###" for w in words(40, 500 + i).split())) for i in range(60)]
    docs = frame(spark, [*good, *bad, *ODD])
    labels = spark.createDataFrame([(i, 1, 0) for i, _ in good[:80]] + [(i, 0, 0) for i, _ in bad[:40]] + [(None, 1, 0), (5, None, 0)], "doc_id long, quality int, toxic int")
    m = quality.fit_quality(docs, labels)
    out = {r.doc_id: r.keep for r in quality.quality_scores(docs, m).collect()}
    assert all(out[i] for i, _ in good) and not any(out[i] for i, _ in bad) and not out[5] and not out[3]
    kept = quality.keep_quality(docs, m)
    assert kept.columns == docs.columns and {i for i, _ in good} <= {r.doc_id for r in kept.collect()}
    assert quality.quality_scores(frame(spark, []), m).count() == 0


def test_dual_coordinate_descent_meets_its_conditions():
    rng = np.random.default_rng(0)
    rows = [np.flatnonzero(rng.random(30) < 0.3) for _ in range(40)]
    y = np.where(rng.random(40) < 0.5, 1, -1)
    scale = np.ones(30)
    w, b = quality.dual_coordinate_descent(rows, scale, y, epochs=3000)
    share = {s: 40 / (2 * (y == s).sum()) for s in (1, -1)}
    alpha = [max(0, 1 - t * (w[r].sum() + b)) * 2 * quality.COST * share[t] for r, t in zip(rows, y, strict=True)]
    again = np.zeros(30)
    for a, r, t in zip(alpha, rows, y, strict=True):
        again[r] += a * t
    assert np.abs(again - w).max() < 1e-2


def test_simhash_pairs_equal_brute_force(spark):
    rng = np.random.default_rng(2)
    base = [rng.integers(-(2**62), 2**62, 5) for _ in range(60)]
    rows = []
    for i, b in enumerate(base):
        rows.append((i * 10, *map(int, b)))
        for j in range(1, 4):
            v = b.copy()
            v[j % 3] ^= sum(1 << int(k) for k in rng.choice(62, rng.integers(1, 8), replace=False))
            v[(j + 1) % 3] = rng.integers(-(2**62), 2**62)
            rows.append((i * 10 + j, *map(int, v)))
    df = spark.createDataFrame(rows, "id long, f0 long, f1 long, f2 long, c0 long, c1 long")
    got = {(r.a, r.b) for r in simhash.near_pairs(df, len(rows)).collect()}
    pop = lambda a, b: bin((a ^ b) & (2**64 - 1)).count("1")
    want = set()
    for r, s in itertools.combinations(sorted(rows), 2):
        if min(pop(r[1 + k], s[1 + k]) for k in range(3)) <= simhash.DISTANCE and pop(r[4], s[4]) + pop(r[5], s[5]) <= simhash.CHECK_DISTANCE:
            want.add((r[0], s[0]))
    assert got == want and len(want) > 60


def test_simhash_keys_of_millions():
    """Few keys a node however many nodes, so that the shuffle stays in proportion; plans cover any 7 bits."""
    for nodes in (10**5, 3 * 10**6, 10**8):
        assert len(simhash.block_plan(nodes)) * simhash.SEEDS <= 24
    rng = np.random.default_rng(4)
    for plan in (simhash.block_plan(10**6), simhash.block_plan(10**9), simhash.block_plan(10**11)):
        for _ in range(200):
            x = np.bitwise_or.reduce(np.uint64(1) << rng.choice(64, simhash.DISTANCE, replace=False).astype(np.uint64))
            assert any(not x & simhash._mask(spans) for spans in plan)
        for spans in plan:
            both = sorted([*spans, *simhash._others(spans)])
            assert sum(n for _, n in both) == 64 and all(a + n == b for (a, n), (b, _) in zip(both, both[1:], strict=False))


@pytest.mark.parametrize("most", [10**6, 60])
def test_simhash_crowded_keys(spark, most):
    """Fingerprints that agree in most pieces: runs of all rows, cut further, and keys dealt to cells."""
    rng = np.random.default_rng(5)
    prints = np.zeros((700, 5), np.int64)
    prints[:, 0] = rng.integers(0, 2**12, 700) << 30
    prints[:, 1] = rng.integers(-(2**62), 2**62, 700)
    prints[:, 2] = rng.integers(0, 2**62, 700) & ~np.int64(0xFF)
    prints[:, 3] = rng.integers(0, 2**25, 700)
    prints[::3, 4] = -1
    rows = [(i, *map(int, r)) for i, r in enumerate(prints)]
    df = spark.createDataFrame(rows, "id long, f0 long, f1 long, f2 long, c0 long, c1 long")
    keys = simhash.key_rows(df, len(rows), most=most)
    if most < len(rows):
        assert max(r["count"] for r in keys.groupBy("k", "cell").count().collect()) <= 1.6 * most
    ordered = keys.repartition(5, "k", "cell").sortWithinPartitions("k", "cell")
    check = 20
    found = ordered.mapInArrow(simhash._verify(simhash.block_plan(len(rows)), simhash.DISTANCE, check), "a long, b long").distinct().collect()
    i, j = np.triu_indices(700, 1)
    bits = simhash.differing(prints[i], prints[j]).astype(int)
    hit = (bits[:, :3].min(1) <= simhash.DISTANCE) & (bits[:, 3:].sum(1) <= check)
    assert {(r.a, r.b) for r in found} == set(zip(i[hit].tolist(), j[hit].tolist(), strict=True)) and hit.sum() > 10_000


@pytest.mark.parametrize("run_rows", [1, 50, 10**6])
def test_simhash_runs_over_batches(monkeypatch, run_rows):
    import pyarrow as pa

    monkeypatch.setattr(simhash, "RUN_ROWS", run_rows)
    monkeypatch.setattr(simhash, "SORT_COST", 1)
    rng = np.random.default_rng(6)
    plan = simhash.block_plan(1000)
    f = rng.integers(0, 2**20, 900)
    rows = np.stack([np.sort(rng.integers(0, 5, 900)), np.zeros(900, np.int64), np.arange(900), f, f & 3, f & 5])
    rows[0] = rows[0] // 4 << 48
    batches = [pa.RecordBatch.from_arrays([pa.array(c[at : at + 70]) for c in rows], names=list("kvifcd")) for at in range(0, 900, 70)]
    got = {p for b in simhash._verify(plan, 7, 40)(iter(batches)) for p in zip(*(c.to_pylist() for c in b.columns), strict=True)}
    i, j = np.triu_indices(900, 1)
    hit = (simhash.differing(f[i], f[j]) <= 7) & (rows[0][i] == rows[0][j])
    assert got == set(zip(i[hit].tolist(), j[hit].tolist(), strict=True)) and hit.sum() > 1000


@pytest.mark.parametrize("nodes,keys", [(3 * 10**6, 24), (10**9, 108)])
def test_simhash_plans_of_large_tables(spark, nodes, keys):
    """The plans of tables far larger than this one find the same pairs, with few rows to shuffle."""
    rng = np.random.default_rng(9)
    prints = rng.integers(-(2**62), 2**62, (300, 5))
    prints[100:] = prints[rng.integers(0, 100, 200)]
    for row in prints[100:]:
        for k in range(5):
            row[k] ^= sum(1 << int(b) for b in rng.choice(62, rng.integers(0, 12), replace=False))
    df = spark.createDataFrame([(i, *map(int, r)) for i, r in enumerate(prints)], "id long, f0 long, f1 long, f2 long, c0 long, c1 long")
    rows = simhash.key_rows(df, nodes)
    assert rows.count() == keys * 300
    ordered = rows.repartition(4, "k", "cell").sortWithinPartitions("k", "cell")
    found = ordered.mapInArrow(simhash._verify(simhash.block_plan(nodes), simhash.DISTANCE, simhash.CHECK_DISTANCE), "a long, b long").distinct().collect()
    i, j = np.triu_indices(300, 1)
    bits = simhash.differing(prints[i], prints[j]).astype(int)
    hit = (bits[:, :3].min(1) <= simhash.DISTANCE) & (bits[:, 3:].sum(1) <= simhash.CHECK_DISTANCE)
    assert {(r.a, r.b) for r in found} == set(zip(i[hit].tolist(), j[hit].tolist(), strict=True)) and hit.sum() > 100


def test_large_groups_are_linked_not_paired(spark, monkeypatch):
    """A group of n alike texts gives some n links to write, not its square; groups are those of all pairs."""
    rng = np.random.default_rng(11)
    prints = np.concatenate([np.repeat(rng.integers(-(2**62), 2**62, (1, 5)), 600, 0), rng.integers(-(2**62), 2**62, (200, 5))])
    prints[700:800] = prints[600:700]
    at = np.r_[0:600, 700:800]
    for k in range(5):
        for _ in range(3):
            prints[at, k] ^= np.int64(1) << rng.integers(0, 62, len(at))
    i, j = np.triu_indices(len(prints), 1)
    bits = simhash.differing(prints[i], prints[j]).astype(int)
    hit = (bits[:, :3].min(1) <= simhash.DISTANCE) & (bits[:, 3:].sum(1) <= simhash.CHECK_DISTANCE)
    least = np.arange(len(prints))
    while (least[i[hit]] != least[j[hit]]).any():
        np.minimum.at(least, j[hit], least[i[hit]])
        np.minimum.at(least, i[hit], least[j[hit]])
    written, spread = [], simhash.least_labels
    monkeypatch.setattr(simhash, "least_labels", lambda edges: written.append(edges.count()) or spread(edges))
    df = spark.createDataFrame([(n, n, 9, *map(int, r)) for n, r in enumerate(prints)], "row long, id long, words long, f0 long, f1 long, f2 long, c0 long, c1 long")
    _, groups, count = simhash._groups(df, simhash.DISTANCE, simhash.CHECK_DISTANCE)
    want = {k: n for k, n in zip(*map(np.ndarray.tolist, np.unique(least, return_counts=True)), strict=True) if n > 1}
    assert {r.id: r.group_size for r in groups.collect()} == want and count == sum(want.values())
    assert hit.sum() > 100_000 and written[0] <= 24 * len(prints)  # at most one a key and node


def test_near_copies_of_six_tenths():
    """Pairs of about 100 words that share 0.6 to 0.8 of their word triples."""
    rng = np.random.default_rng(12)
    docs, pairs = [], []
    for _ in range(400):
        a = [f"w{int(k)}" for k in rng.zipf(1.3, int(rng.integers(60, 200))) % 5000]
        b = list(a)
        for at in rng.choice(len(a), max(1, len(a) // 20), replace=False):
            b[at] = f"n{rng.integers(10**6)}"
        ta, tb = ({tuple(x[i : i + 3]) for i in range(len(x) - 2)} for x in (a, b))
        if 0.6 <= len(ta & tb) / len(ta | tb) < 0.8:
            pairs.append((len(docs), len(docs) + 1))
            docs += [[w.encode() for w in a], [w.encode() for w in b]]
    prints = simhash.fingerprints(docs, WordIds(simhash.word_rows, 150_000))
    i, j = np.array(pairs).T
    bits = simhash.differing(prints[i], prints[j]).astype(int)
    hit = (bits[:, :3].min(1) <= simhash.DISTANCE) & (bits[:, 3:].sum(1) <= simhash.CHECK_DISTANCE)
    assert len(pairs) > 200 and hit.mean() >= 0.9


def test_near_groups(spark):
    text = words(300)
    near = text.split()
    near[50], near[200] = "other", "thing"
    df = frame(spark, [(1, text), (2, " ".join(near)), (3, words(300, 9)), (4, text.upper()), *[(i + 10, t) for i, t in ODD if i]])
    got = {r.doc_id: r for r in simhash.near_groups(df).collect()}
    assert got[1].group_id == got[2].group_id == got[4].group_id == 1 and got[2].is_near_copy and got[3].group_size == 1
    assert got[13].group_id == 13 and got[15].group_id == 15
    kept = {r.doc_id for r in simhash.drop_near_copies(df).collect()}
    assert {1, 3, 13, 14, 15, 16} <= kept and not {2, 4} & kept
    assert simhash.near_groups(frame(spark, [])).count() == 0


def test_bpe_equals_whole_encoding(spark):
    plain = encoding(VOCAB)
    rng = np.random.default_rng(5)
    coder = ChunkEncoder(VOCAB)
    alphabet = list("ab é\n  \t'sll1234..,，日本  ")
    for k in range(60):
        t = "".join(rng.choice(alphabet, rng.integers(0, 5000)))
        assert coder.text(t).tolist() == plain.encode_ordinary(t), k
    shared = words(800)
    rows = [(20, shared + words(300, 1)), (21, words(200, 2) + shared), *ODD]
    out = bpe_encode(frame(spark, rows))
    for r in out.collect():
        t = dict(rows)[r.doc_id] if r.doc_id not in (None,) else "a b c"
        assert (r.tokens is None and t is None) or (list(r.tokens) == plain.encode_ordinary(t) and r.decodes)
    back = {r.doc_id: r.text for r in bpe_decode(out).collect()}
    assert back[20] == rows[0][1] and back[3] is None and back[5] == ""


def _tiny_vocabulary():
    return lm.Vocabulary([b"a", b"b", b"c", b"d"], np.array([3, 4, 5, 2, 2, 1]), np.full(257, 5.0))


def test_lm_scores_equal_a_plain_loop():
    m = lm.RecurrentModel(_tiny_vocabulary(), 5)
    docs = [np.array(d, np.int64) for d in ([2, 3, 1, 4], [], [5] * 150, [2])]
    want = []
    for d in docs:
        h, total = np.zeros((1, 5), np.float32), 0.0
        for x, y in zip([0, *d], [*d, 0], strict=True):
            out, _ = m.steps(np.array([[x]]), h)
            h = out[0]
            total -= m.output(h, np.array([y]))[0]
        want.append(total)
    assert np.allclose(m.log_likelihoods(docs, window=7), want, atol=1e-3)
    p = [np.exp(-m.output(np.zeros((1, 5), np.float32), np.array([t]))[0]) for t in range(6)]
    assert abs(sum(p) - 1) < 1e-5


def test_lm_counts_and_codes_equal_plain_loops(spark):
    """Bytes counted by way of the words, and pieces encoded at once, row by row as a plain loop has them."""
    texts = ["b b  c\u00e9 b", None, "", "  ", "x" * 70 + " b", "c\u00e9 new b\tnew", "b"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    v = lm.count_words(df, size=4)
    split = [None if t is None else t.encode().split() for t in texts]
    octets = np.full(257, 0.1)
    for w in (w for d in split if d for w in d):
        octets[-1] += 1
        for k in w:
            octets[k] += 1
    assert v.words == [b"b", "c\u00e9".encode()] and np.allclose(v.byte_cost, -np.log(octets / octets.sum()))
    for r in lm.encoded_docs(df, v, "doc_id", "text").collect():
        d = split[r.id]
        if d is None:
            assert r.ids is r.words is r.unknown is r.spelled is r.bytes is None
            continue
        strange = [w for w in d if w not in v.words]
        assert np.frombuffer(r.ids, np.uint16).tolist() == [v.ids.get(w, 1) for w in d]
        assert (r.words, r.unknown, r.bytes) == (len(d), len(strange), sum(len(w) + 1 for w in d))
        assert np.isclose(r.spelled, sum(v.spelling([w])[0] for w in strange))


@pytest.mark.parametrize("limit", [0, 5, 10**6])
def test_lm_codes_look_each_word_up_once(limit):
    """Ids and costs of words as one by one, over calls, with unknown words forgotten in between; none is spelled twice."""
    grams = [(k, np.ones(len(k))) for k in map(np.unique, lm.byte_grams([b"seen", b"sea"])[0][1:])]
    v = lm.Vocabulary([b"a", b"b"], np.array([3, 4, 5, 2]), np.full(257, 5.0), grams)
    spelled, plain = [], v.spelling
    v.spelling = lambda new: spelled.extend(new) or plain(new)
    codes, rng = lm.WordCodes(v, limit), np.random.default_rng(3)
    for n in (30, 0, 1, 50, 40):
        flat = [[b"a", b"b", b"seen", b"\xc3\xa9", b"x" * 70, *(b"w%d" % k for k in range(9))][k] for k in rng.integers(0, 14, n)]
        ids, unknown, cost = codes(flat)
        assert ids.tolist() == [v.ids.get(w, lm.UNKNOWN) for w in flat] and unknown.tolist() == [w not in v.ids for w in flat]
        assert np.allclose(cost, [plain([w])[0] for w in flat if w not in v.ids])
    assert limit < 10**6 or len(spelled) == len(set(spelled)) == 12


def test_lm_words_equal_split():
    """Words cut in Arrow, with and without blanks at the ends, nulls and slices, as ``bytes.split`` has them."""
    texts = ["b b  c\u00e9 b", None, "", "  ", "x" * 70 + " b\n", " b\x0b a\x0cz\r\n q\x1cw\x85  r\u2003s\x1f ", "\x00 a\x00b", "\t\n"]
    split = [t.encode().split() if t else [] for t in texts]
    for column in (pa.array(texts), pa.array(["zz zz", *texts, "k"]).slice(1, len(texts)), pa.array([], pa.string()), pa.array([None], pa.string())):
        want = split[: len(column)] if len(column) != 1 else [[]]
        found, counts = lm.split_words(column)
        assert found.to_pylist() == [w for d in want for w in d] and counts.tolist() == [len(d) for d in want]


def test_lm_gradients_come_in_one_piece():
    """Where a window uses most rows their changes are one array, and an update by it equals one by single rows."""
    v = lm.Vocabulary([b"w%d" % k for k in range(300)], np.arange(1, 303)[::-1].copy(), np.full(257, 5.0))
    whole, single = lm.RecurrentModel(v, 5), lm.RecurrentModel(v, 5)
    rng = np.random.default_rng(0)
    for n, pieces in ((400, 1), (1, 2)):
        x, y, h = rng.integers(0, 302, (6, n)), rng.integers(0, 302, (6, n)), np.zeros((n, 5), np.float32)
        parts, (_, _, grads) = whole.window_parts(x, y, h)[2], single.window(x, y, h)
        assert len(parts["to_word"]) >= pieces and (n == 1 or len(parts["to_word"]) == 1)
        whole.update(parts, 0.5)
        single.update({k: [(np.array([r]), g[r : r + 1]) for r in range(len(g)) if g[r].any()] for k, g in grads.items()}, 0.5)
        assert all(np.allclose(whole.p[k], single.p[k], atol=1e-6) for k in whole.p)


def test_lm_scores_by_lanes():
    m, rng = lm.RecurrentModel(_tiny_vocabulary(), 5), np.random.default_rng(1)
    docs = [rng.integers(0, 6, n) for n in rng.integers(0, 90, 50)]
    assert np.allclose(m.log_likelihoods(docs, lanes=7), m.log_likelihoods(docs), atol=1e-3) and len(m.log_likelihoods([])) == 0


def test_lm_gradients():
    m = lm.RecurrentModel(_tiny_vocabulary(), 4)
    m.p = {k: x.astype(np.float64) for k, x in m.p.items()}
    x, y, h = np.array([[0, 2], [3, 0], [4, 5]]), np.array([[3, 0], [4, 5], [0, 1]]), np.zeros((2, 4))
    _, _, g = m.window(x, y, h)
    for k, p in m.p.items():
        for at in list(np.ndindex(p.shape))[:8]:
            p[at] += 1e-3
            up = m.window(x, y, h)[0]
            p[at] -= 2e-3
            down = m.window(x, y, h)[0]
            p[at] += 1e-3
            assert abs((up - down) / 2e-3 - g[k][at]) < 2e-3


def test_lm_table(spark):
    docs = frame(spark, [(i, "the cat sat on the mat " * 20) for i in range(50, 70)] + ODD)
    got = {r.doc_id: r for r in lm.lm_log_likelihood(docs, vocab=50, rounds=2).collect()}
    assert got[3].log_likelihood is None and got[5].words == 0 and got[5].bits_per_byte is None and got[5].log_likelihood < 0
    assert got[52].bits_per_byte < 8 and len(got) == 29
    assert lm.lm_log_likelihood(frame(spark, [])).count() == 0


def test_lm_gathers_more_from_more(spark):
    many = [f"word{k}" for k in range(3000)]
    few = lm.count_words(frame(spark, [(i, " ".join(many[:100] + ["rare", "rarer"][: i + 1])) for i in range(2)]), size=50)
    assert len(few.words) == 48
    count = lm.count_words(frame(spark, [(i, " ".join(many)) for i in range(lm.MIN_COUNT)] + [(99, "once")]), size=50)
    assert set(count.words) == {w.encode() for w in many} and count.counts[lm.UNKNOWN] == 2
    assert len(count.starts) - 1 > lm.CLASSES and [k for k, _ in count.grams][0].size == 5
    assert lm.rounds_of(10**6) == lm.ROUNDS and lm.rounds_of(10**10) == 36
    odd = lm.Vocabulary([], np.array([1, 1]), np.full(257, np.log(257)), [(k, np.ones(len(k))) for k in map(np.unique, lm.byte_grams([b"seen", b"sea"])[0][1:])])
    after = [b"se" + bytes([k]) for k in range(256)]
    keys, lengths = lm.byte_grams(after)
    third = np.cumsum(lengths) - 2
    keys = [np.append(k[third], (k[third[0]] >> 9 << 9) + lm.END) for k in keys]
    assert abs(odd.bytes.probability(keys).sum() - 1) < 1e-9
    assert odd.spelling([b"seen"])[0] < odd.spelling([b"nese"])[0]


def test_forward_backward_against_enumeration():
    rng = np.random.default_rng(0)
    emit, move = rng.standard_normal((4, 1, 3)), rng.standard_normal((3, 3))
    marginal, pairs, log_z = language.forward_backward(emit, move, np.array([4]))
    total, m, e = 0.0, np.zeros((4, 3)), np.zeros((3, 3))
    for path in itertools.product(range(3), repeat=4):
        p = np.exp(sum(emit[t, 0, s] for t, s in enumerate(path)) + sum(move[a, b] for a, b in itertools.pairwise(path)))
        total += p
        for t, s in enumerate(path):
            m[t, s] += p
        for a, b in itertools.pairwise(path):
            e[a, b] += p
    assert np.allclose(marginal[:, 0], m / total) and np.allclose(pairs, e / total) and np.isclose(log_z, np.log(total))


def test_language(spark):
    rng = np.random.default_rng(4)
    parts = {"en": ["th", "ing", "er", "an"], "fr": ["eau", "oi", "ux", "que"]}
    make = lambda g, n: " ".join("".join(rng.choice(parts[g], rng.integers(1, 4))) for _ in range(n))
    rows = [(i, make(g, 60), g) for i, g in enumerate(["en", "fr"] * 30)]
    docs = spark.createDataFrame([*rows, (100, None, "en"), (101, "", "fr"), (102, make("en", 40) + " " + make("fr", 40), None)], "doc_id long, text string, lang string")
    m = language.fit_languages(docs, steps=40)
    got = {r.doc_id: r for r in language.language_labels(docs, m).collect()}
    assert np.mean([got[i].language == g for i, _, g in rows]) > 0.95
    assert got[100].language is None and got[100].words is None and got[101].words == 0
    assert sum(s.words for s in got[102].segments) == 80 and {s.language for s in got[102].segments} == {"en", "fr"}
    assert sum(len(p) for p in m.marginals([folded_words("a b"), []], WordIds(m.word_scores))) == 2


def _check_packing(out, sizes, capacity):
    bins, total = {}, {}
    for r in out:
        total[r.doc_id] = total.get(r.doc_id, 0) + r.length
        if r.bin_id is not None:
            bins.setdefault(r.bin_id, []).append((r.start, r.length))
    for spans in bins.values():
        spans.sort()
        assert all(a + n <= b for (a, n), (b, _) in itertools.pairwise(spans)) and spans[-1][0] + spans[-1][1] <= capacity
    assert total == sizes
    return len(bins)


@pytest.mark.parametrize("home", [50_000, 40])
def test_packing(spark, home):
    rng = np.random.default_rng(7)
    rows = [(i, words(int(n), i)) for i, n in enumerate(rng.integers(0, 90, 400))] + [(400, None), (401, "é" * 500)]
    df = frame(spark, rows)
    out = packing.best_fit_pack(df, capacity=100, home_items=home).collect()
    encode = encoding(VOCAB).encode_ordinary
    sizes = {i: len(encode(t or "")) for i, t in rows}
    n = _check_packing(out, sizes, 100)
    rest = sorted((s % 100 for s in sizes.values() if s % 100), reverse=True)
    best = sum(s // 100 for s in sizes.values()) + _best_fit_decreasing(rest, 100)
    assert n <= best * 1.05 and max(sizes.values()) > 200
    assert packing.best_fit_pack(frame(spark, [])).count() == 0


def _best_fit_decreasing(sizes, capacity):
    """The number of bins of the plain method: each size into the fullest bin that takes it."""
    left = []
    for s in sorted(sizes, reverse=True):
        fits = [k for k, g in enumerate(left) if g >= s]
        if fits:
            left[min(fits, key=lambda k: left[k])] -= s
        else:
            left.append(capacity - s)
    return len(left)


def test_packed_sequences_hold_all_tokens(spark):
    rows = [(1, words(130)), (1, words(20, 3)), (None, words(33, 4)), (5, ""), (6, None), (7, "日本 " * 90), (8, words(20, 3))]
    encode = encoding(VOCAB).encode_ordinary
    got = {}
    for r in packing.packed_sequences(frame(spark, rows), capacity=64).collect():
        assert len(r.tokens) == sum(r.lengths) <= 64
        at = 0
        for i, n in zip(r.ids, r.lengths, strict=True):
            got.setdefault(i, []).append(tuple(r.tokens[at : at + n]))
            at += n
    for i in {i for i, _ in rows}:
        want = [tuple(e[k : k + 64]) for j, t in rows if j == i for e in [encode(t or "")] for k in range(0, len(e), 64)]
        assert sorted(got.get(i, [])) == sorted(want)


def test_sweep_takes_the_smallest_gap():
    where, left = packing.sweep([5, 3], [9, 6, 3], 10, True)
    assert where == [(1, 4), (2, 7)] and left == [9, 1, 0]
    assert packing.sweep([4], [3], 10, False)[0] == [(-1, 0)]


def test_pipeline_stages(spark):
    import corpus_pipeline as cp

    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    kept = cp.STAGES[0][1](spark, docs, d)
    after = cp.STAGES[1][1](spark, kept, d)
    texts = [r.text for r in kept.collect()]
    assert after.columns == docs.columns and after.count() == len(set(texts))
    near = cp.STAGES[2][1](spark, after, d)
    clean = cp.STAGES[3][1](spark, near, d)
    assert clean.columns == docs.columns and clean.count() == near.count()
    assert secrets.secret_scan(clean).count() == 0
    ids = {r.doc_id for r in clean.collect()}
    out = cp.run(spark, d)
    assert {r.doc_id for r in out.collect()} == ids
