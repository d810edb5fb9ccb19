"""Operators on small fixtures: nulls, empty and long texts, ties, repeated rows, empty tables, clashing names."""

from __future__ import annotations

import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from incstate.llm import (
    collision_links,
    cube_mix,
    hilbert_pack,
    kd_shards,
    knn_quality,
    license_scan,
    lsh_forest,
    rank_bpe,
    rlz_dedup,
    tree_rules,
)

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, source string, lang string, n_words string, score double, __seq int, seq string"


def prose(seed: int, n: int) -> str:
    draw = np.random.default_rng(seed)
    return " ".join("".join(chr(97 + x) for x in draw.integers(0, 26, draw.integers(2, 8))) for _ in range(n))


@pytest.fixture(scope="module")
def odd_rows():
    long = prose(1, 20_000)
    shared = prose(2, 60)
    texts = [
        (1, None), (2, ""), (3, "  \n\t "), (4, "one"), (5, "one"), (6, "a b c d e"), (7, long), (8, long + " end"), (None, "no id here at all"),
        (9, prose(3, 80)), (9, prose(3, 80)), (10, prose(4, 50) + " " + shared), (11, shared + " " + prose(5, 50)), (12, "Ünï çödé 日本 \x85 x\xa0y <|endoftext|> 'll!"),
        (13, "w " * 300), (14, prose(6, 90)), (15, prose(6, 90).replace("a", "A")), (16, "\n".join(["same line here"] * 5 + ["other"])), (17, "Released under the MIT License."),
    ]
    return [(i, t, None if k % 5 == 0 else f"s{k % 3}", "en", "clash", 0.5, 1, "clash") for k, (i, t) in enumerate(texts)]


@pytest.fixture(scope="module")
def odd(spark, odd_rows):
    return spark.createDataFrame(odd_rows, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(7, 1, 0), (8, 1, 0), (13, 0, 0), (99, 0, 0), (None, 1, 0), (9, None, 1), (14, 1, 0)], "doc_id long, quality int, toxic int")


def words(text):
    return WORD.findall(text or "")


def test_mix(odd, odd_rows, none):
    out = cube_mix.decisions(odd).toPandas()
    assert len(out) == len(odd_rows) and sorted(out["size"]) == sorted(len(words(r[1])) for r in odd_rows)
    assert (out.taken <= 3 * out["size"]).all()
    again = cube_mix.decisions(odd.orderBy(F.rand(1)).repartition(5)).toPandas()
    key = ["doc_id", "size", "taken"]
    assert out[key].sort_values(key).reset_index(drop=True).equals(again[key].sort_values(key).reset_index(drop=True))
    assert cube_mix.decisions(none).count() == 0 and cube_mix.apply_mix(none).count() == 0
    mixed = cube_mix.apply_mix(odd)
    assert mixed.columns == odd.columns and mixed.count() == int(out.copies.sum())


def test_mix_targets_and_balance(spark):
    draw = np.random.default_rng(0)
    rows = [(k, f"s{int(s)}", int(z)) for k, (s, z) in enumerate(zip(np.minimum(draw.zipf(1.7, 6000), 6), draw.lognormal(5, 1.2, 6000)))]
    docs = spark.createDataFrame(rows, "doc_id long, source string, z long")
    out = cube_mix.decisions(docs, size="z", chunk=256).toPandas().merge(docs.toPandas())
    by = out.groupby("source").agg(size=("z", "sum"), target=("target", "first"), taken=("taken", "sum"))
    weight = dict(zip(by.index, [5, 2, 1] * 3))
    target, total = {s: 0.0 for s in by.index}, float(by["size"].sum())
    open_, left = set(by.index), total
    while open_:
        share = left / sum(weight[s] for s in open_)
        full = {s for s in open_ if share * weight[s] > 3 * by["size"][s]}
        for s in full or open_:
            target[s] = 3.0 * by["size"][s] if full else share * weight[s]
        left -= sum(target[s] for s in full)
        open_ = open_ - full if full else set()
    for s in by.index:
        assert by.target[s] == pytest.approx(target[s]) and by.taken[s] == pytest.approx(target[s], rel=0.01)


def test_flight_keeps_totals():
    draw = np.random.default_rng(1)
    p, size = draw.random(200), draw.integers(1, 900, 200).astype(float)
    keep = np.column_stack([size, np.ones(200)])
    q = p.copy()
    cube_mix.flight(q, keep, draw)
    assert np.allclose(q @ keep, p @ keep) and ((q > 0) & (q < 1)).sum() <= 2
    hits = np.zeros(6)
    for seed in range(4000):
        r = np.array([0.2, 0.4, 0.6, 0.8, 0.5, 0.5])
        cube_mix.flight(r, np.ones((6, 1)), np.random.default_rng(seed))
        hits += r
    assert np.allclose(hits / 4000, [0.2, 0.4, 0.6, 0.8, 0.5, 0.5], atol=0.03)


def test_collision_links(spark):
    draw = np.random.default_rng(2)
    base = draw.standard_normal((400, 32))
    near = base[:60] + 0.25 * draw.standard_normal((60, 32))
    x = np.vstack([base, near, base[:5]]).astype(np.float32)
    rows = [(k, [float(v) for v in r], 0) for k, r in enumerate(x)]
    n = len(rows)
    rows += [(n, None, 0), (n + 1, [0.0] * 32, 0), (n + 2, [1.0, None] + [0.0] * 30, 0), (n + 3, [float("nan")] * 32, 0), (n + 4, [float("inf")] + [0.0] * 31, 0), (n + 5, [1.0, 2.0], 0), (n + 6, [2.0, 4.0], 0), (n + 7, [], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    out = collision_links.collision_links(df).toPandas().sort_values("vec_id").set_index("vec_id")
    u = x.astype(float) / np.linalg.norm(x.astype(float), axis=1)[:, None]
    true = u @ u.T >= 0.9
    np.fill_diagonal(true, False)
    got = out.n_links.to_numpy()[:n]
    assert (got <= true.sum(1)).all() and got.sum() >= 0.9 * true.sum()
    assert (out.n_links[n : n + 5] == 0).all() and out.n_links[n + 5] == 1 and out.component_id[n + 6] == n + 5 and not out.kept[n + 6]
    assert collision_links.collision_links(df.where("false")).count() == 0


def test_collision_links_of_a_crowd_is_split(spark, monkeypatch):
    monkeypatch.setattr(collision_links, "BLOCK_ROWS", 40)
    draw = np.random.default_rng(3)
    x = draw.standard_normal(16) + 0.05 * draw.standard_normal((150, 16))
    df = spark.createDataFrame([(k, [float(v) for v in r]) for k, r in enumerate(x)], "vec_id long, embedding array<double>")
    out = collision_links.collision_links(df).toPandas()
    assert out.n_links.sum() >= 0.9 * 150 * 149 and out.component_id.max() == 0


def test_kd_shards(odd, odd_rows, none, spark):
    out = kd_shards.kd_shards(odd, 4).toPandas()
    assert len(out) == len(odd_rows) and set(out.law) == {"bytes"} and out.grown_shard.isna().all()
    assert sorted(out["size"]) == sorted(len((r[1] or "").encode()) + 8 for r in odd_rows)
    assert sorted(out.text_crc32) == sorted(zlib.crc32((r[1] or "").encode()) for r in odd_rows)
    for _, g in out.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))
    assert kd_shards.kd_shards(none).count() == 0
    even = spark.range(3000).select(F.col("id").alias("doc_id"), F.concat_ws(" ", F.array_repeat(F.hex(F.xxhash64("id")), 5)).alias("text"))
    sizes = kd_shards.kd_shards(even, 24).groupBy("shard").agg(F.sum("size").alias("s")).toPandas().s
    assert len(sizes) == 24 and sizes.max() / sizes.min() < 1.1
    copies = even.withColumn("text", F.when(F.col("doc_id") < 1000, "the same text in a third of all rows").otherwise(F.col("text")))
    sizes = kd_shards.kd_shards(copies, 6).groupBy("shard").agg(F.sum("size").alias("s")).toPandas().s
    assert sizes.max() / sizes.min() < 1.1


def test_hilbert_curve_is_a_walk():
    axis = np.arange(8)
    cells = np.stack(np.meshgrid(axis, axis, axis, indexing="ij"), axis=-1).reshape(-1, 3)
    key = hilbert_pack.hilbert_key(cells, 3)
    assert sorted(key) == list(range(512))
    walk = cells[np.argsort(key)]
    assert (np.abs(np.diff(walk, axis=0)).sum(axis=1) == 1).all()


def test_packing(odd, odd_rows, none):
    path = public_tokenizers.path(hilbert_pack.VOCABULARY)
    out = hilbert_pack.packed_pieces(odd, path, sequence=64).toPandas()
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(path)
    want = Counter(tuple([r[0]] + lib.encode(r[1] or "", add_special_tokens=False).ids + [2]) for r in odd_rows)
    got = Counter()
    seq = out.groupby("sequence_id")
    assert (seq.length.sum().sort_index()[:-1] == 64).all()
    for _, g in seq:
        g = g.sort_values("offset")
        assert (g.offset.to_numpy() == np.cumsum(g.length) - g.length).all()
    assert (out.ids_crc32 == out.ids.map(zlib.crc32)).all()
    out["at"] = out.sequence_id * 64 + out.offset
    cur: list[int] = []
    for r in out.sort_values("at").itertuples():
        cur += np.frombuffer(r.ids, "<u4").tolist()
        if len(cur) == r.doc_tokens:
            got[tuple([None if r.doc_id != r.doc_id else int(r.doc_id)] + cur)] += 1
            cur = []
    assert got == want
    assert hilbert_pack.packing(none, path).count() == 0


def test_word_ids_equal_the_library():
    path = public_tokenizers.path(hilbert_pack.VOCABULARY)
    reader = hilbert_pack.WordIds(path)
    draw = np.random.default_rng(4)
    signs = [*"aAbB'stréÉß  \n\t\x1c\x85\xa0中1²|<>!,.İ×÷", "<|endoftext|>", "'ll", "<|STARTOFTEXT|>"]
    texts = ["".join(draw.choice(signs, draw.integers(0, 25))) for _ in range(3000)]
    ids, counts = reader.ids(pa.array(texts))
    ends = np.cumsum(counts)
    for n, e, code in zip(counts, ends, reader.tokenizer.encode_batch(texts, add_special_tokens=False)):
        assert ids[e - n : e].tolist() == code.ids


def jaccard_components(rows):
    sets = []
    for i, t, *_ in rows:
        w = words("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        sets.append({tuple(w[k : k + 4]) for k in range(len(w) - 3)} if len(w) >= 4 else {tuple(w)} if w else set())
    root = list(range(len(rows)))

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * both >= 80 * len(sets[a] | sets[b]):
                root[find(a)] = find(b)
    groups = {}
    for k in range(len(rows)):
        groups.setdefault(find(k), []).append(rows[k][0])
    low = {r: min((x for x in g if x is not None), default=None) for r, g in groups.items()}
    return Counter((rows[k][0], len(sets[k]), low[find(k)]) for k in range(len(rows)))


def test_near_duplicates(odd, odd_rows, none):
    out = lsh_forest.near_duplicates(odd).toPandas().astype(object)
    got = Counter(tuple(None if v != v else int(v) for v in r) for r in out[["doc_id", "n_shingles", "component_id"]].itertuples(index=False))
    assert got == jaccard_components(odd_rows)
    assert lsh_forest.near_duplicates(none).count() == 0
    kept = lsh_forest.keep_one(odd)
    assert kept.columns == odd.columns


def test_crowded_regions_keep_their_pairs(spark):
    """Pairs at similarity 0.8: 0.8% of them fall out if crowded regions get deeper keys but no more trees."""
    draw, rows = np.random.default_rng(6), []
    for k in range(3000):
        w = [f"{x:x}" for x in draw.integers(1 << 40, size=103)]
        rows += [(2 * k, " ".join(w[:93])), (2 * k + 1, " ".join(w[:83] + w[93:]))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    classes, labels = lsh_forest.forest_links(df, crowd=1)
    assert classes.count() == 6000 and labels.count() >= 2 * (3000 - 6)


def test_near_copies_with_many_edits(spark):
    draw = np.random.default_rng(5)
    base = prose(7, 150).split()
    rows = []
    for k in range(160):
        w = list(base)
        for at in draw.choice(150, draw.integers(0, 14), replace=False):
            w[at] = f"x{draw.integers(1 << 30)}"
        rows.append((k, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    out = lsh_forest.near_duplicates(df).toPandas()
    assert Counter(zip(out.doc_id, out.n_shingles, out.component_id)) == jaccard_components(rows)
    small = lsh_forest.forest_links(df, block=20, crowd=30)[1].toPandas()
    largest = out.component_id.value_counts().index[0]
    assert small.groupby("component").size().max() == len({rows[k][1] for k in out[out.component_id == largest].doc_id})


def repeats(rows):
    places = Counter()
    for _, t, *_ in rows:
        w = words(t)
        places.update(tuple(w[k : k + 35]) for k in range(len(w) - 34))
    out = Counter()
    for i, t, *_ in rows:
        w = words(t)
        gone = set()
        for k in range(len(w) - 34):
            if places[tuple(w[k : k + 35])] > 1:
                gone.update(range(k, k + 35))
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        out[i, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()] += 1
    return out


@pytest.mark.parametrize("hot", [2, 1000])
def test_substring_dedup(odd, odd_rows, none, hot):
    out = rlz_dedup.digest(odd, hot).toPandas().astype(object)
    assert Counter((None if r[0] != r[0] else int(r[0]), int(r[1]), int(r[2]), r[3]) for r in out.itertuples(index=False)) == repeats(odd_rows)
    assert rlz_dedup.digest(none).count() == 0
    assert rlz_dedup.drop_repeats(odd).columns == odd.columns


def test_factors_copy_from_their_sources(odd, odd_rows):
    rows, found = rlz_dedup.factors(odd)
    by_seq = {r.seq: words(next(x[1] for x in odd_rows if x[0] == r.doc_id and len(words(x[1])) == r.n)) for r in rows.collect()}
    some = found.collect()
    assert some
    for f in some:
        assert f.length >= 35
        assert by_seq[f.seq][f.start : f.start + f.length] == by_seq[f.source_seq][f.source_start : f.source_start + f.length]


def test_token_counts(odd, odd_rows, none):
    from tokenizers import Tokenizer

    path = public_tokenizers.path(rank_bpe.VOCABULARY)
    lib = Tokenizer.from_file(path)
    out = rank_bpe.token_counts(odd, path).toPandas()
    assert sorted(out.n_tokens) == sorted(len(lib.encode(r[1] or "", add_special_tokens=False).ids) for r in odd_rows)
    assert (out.over_limit == (out.n_tokens > 1024)).all()
    assert rank_bpe.token_counts(none, path).count() == 0
    bpe = rank_bpe.RankMerger(path)
    draw = np.random.default_rng(6)
    signs = [*"aab'stre   \n\t\r\x1c\x85\xa0é中1²|<>!,.", "<|endoftext|>", "'ll", "aaaa"]
    texts = ["".join(draw.choice(signs, draw.integers(0, 30))) for _ in range(3000)]
    assert bpe.counts(texts) == [len(e.ids) for e in lib.encode_batch(texts, add_special_tokens=False)]
    ids, n = bpe.tokens([b" hello", b"aaaaaaa"])
    assert ids.tolist() == lib.encode(" hello").ids + lib.encode("aaaaaaa").ids and n.sum() == len(ids)


def test_quality_rules(odd, odd_rows, none, labels):
    out = tree_rules.quality_rules(odd, labels).toPandas()
    assert len(out) == len(odd_rows) and not out.kept[out.base_failed].any()
    assert sorted(out.n_words) == sorted(len(words(r[1])) for r in odd_rows)
    lines = [[x for x in (r[1] or "").split("\n") if words(x)] for r in odd_rows]
    assert sorted(out.n_dup_lines) == sorted(len(x) - len(set(x)) for x in lines)
    assert out[out.doc_id == 13].n_repeat_words.item() == 300
    assert tree_rules.quality_rules(none, labels).count() == 0
    assert tree_rules.quality_rules(odd, labels.where("false")).count() == len(odd_rows)


def test_trees_are_monotonic():
    draw = np.random.default_rng(7)
    x = draw.random((2000, 3))
    y = ((1 - x[:, 0]) + 0.3 * np.sin(9 * x[:, 1]) + 0.2 * draw.standard_normal(2000) > 0.5).astype(float)
    forest = tree_rules.fit(x, y, np.array([-1, 0, 0]))
    assert ((forest.score(x) > 0.5) == y).mean() > 0.85
    for row in x[:40]:
        line = np.repeat(row[None], 60, axis=0)
        line[:, 0] = np.linspace(0, 1, 60)
        assert (np.diff(forest.score(line)) <= 1e-12).all()


def test_quality_scores(odd, odd_rows, none, labels):
    out = knn_quality.quality_scores(odd, labels).toPandas()
    assert len(out) == len(odd_rows) and out.score.between(0, 1).all()
    held = {r[0]: zlib.crc32(str(r[0]).encode()) % 4 == 2 for r in odd_rows if r[0] is not None}
    assert all(held.get(r.doc_id, False) == r.held_out for r in out.itertuples())
    assert knn_quality.quality_scores(none, labels).count() == 0
    assert (knn_quality.quality_scores(odd, labels.where("false")).toPandas().score == 0.5).all()


def test_quality_on_held_out_rows(spark, data):
    t = lambda n: spark.read.parquet(f"{data.replace('0.001', '0.01')}/{n}.parquet")
    out = knn_quality.quality_scores(t("documents"), t("labels")).join(t("labels"), "doc_id").where("held_out and quality is not null").toPandas()
    assert ((out.predicted == out.quality).mean()) > 0.93
    rules = tree_rules.quality_rules(t("documents"), t("labels")).where("not base_failed").join(t("labels"), "doc_id").toPandas()
    assert rules[rules.quality == 1].kept.mean() > 0.97 and rules[rules.quality == 0].kept.mean() < 0.1


def test_quality_scores_equal_brute_force(spark, data):
    """From bytes to votes, text by text: terms, their weights, the voters, cosines and the vote."""
    docs, marks = (spark.read.parquet(f"{data}/{n}.parquet") for n in ("documents", "labels"))
    space = knn_quality.learn(docs, marks)
    got = {r.doc_id: r for r in knn_quality.quality_scores(docs, marks).collect()}
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    label = {r.doc_id: r.quality for r in marks.collect() if r.quality in (0, 1) and zlib.crc32(str(r.doc_id).encode()) % 4 != 2}
    label = {k: label[k] for k in sorted(label) if k in texts}

    def terms(text):
        raw, out = text.encode(), np.zeros(knn_quality.TERMS)
        for a, b, c in zip(raw, raw[1:], raw[2:]):
            out[((a * 0x9E3779B1 + b * 0x85EBCA77 + c * 0xC2B2AE3D) & 0xFFFFFFFF) >> 21] += 1
        out = np.log1p(out)
        shares, at = dict(zip(knn_quality.SHARES, knn_quality.stats(pa.array([text]))[1][0])), knn_quality.TRIGRAM_TERMS
        for name, ends in knn_quality.BIN_ENDS.items():
            out[at + sum(shares[name] > e for e in ends)] = 1
            at += len(ends) + 1
        return out

    made = {k: terms(x) for k, x in texts.items()}
    sample = np.array([made[k] for k in label])
    weight = np.log((1 + len(label)) / (1 + (sample > 0).sum(axis=0))) + 1
    weight[knn_quality.TRIGRAM_TERMS :] = 1
    assert np.allclose(space.weight, weight, atol=1e-5) and space.label.tolist() == list(label.values())

    def vector(x):
        x, cut = x * weight, knn_quality.TRIGRAM_TERMS
        x[:cut] /= max(np.linalg.norm(x[:cut]), 1e-12)
        x[cut:] *= knn_quality.STATISTIC_WEIGHT / np.sqrt(len(knn_quality.BIN_ENDS))
        return x

    rows = np.array([vector(made[k]) for k in label])
    best = (np.linalg.svd(rows, compute_uv=False)[: knn_quality.LATENT] ** 2).sum()
    assert ((rows @ space.axes) ** 2).sum() > 0.99 * best
    unit = lambda z: z / max(np.linalg.norm(z), 1e-12)
    voters = np.array([unit(x @ space.axes) for x in rows])
    rate = np.mean(list(label.values()))
    vote = np.array([space.prior / rate if y else (1 - space.prior) / (1 - rate) for y in label.values()])
    for k, x in made.items():
        cosine = voters @ unit(vector(x) @ space.axes)
        near = np.argsort(-cosine)[: knn_quality.NEIGHBOURS]
        w = np.exp(knn_quality.SHARPNESS * (cosine[near] - cosine.max())) * vote[near]
        score = (w * np.array(list(label.values()))[near]).sum() / w.sum()
        assert got[k].score == pytest.approx(score, abs=2e-3)
        assert got[k].held_out == (zlib.crc32(str(k).encode()) % 4 == 2) and got[k].predicted == (got[k].score >= knn_quality.THRESHOLD)


def test_neighbours_are_exact():
    draw = np.random.default_rng(8)
    space = knn_quality.Space(None, None, knn_quality._unit(draw.standard_normal((300, 8))), np.ones(300), (draw.random(300) < 0.5).astype(float), 0.5)
    z = knn_quality._unit(draw.standard_normal((20, 8)))

    class Fixed(knn_quality.Space):
        def latent(self, counts):
            return z

    got = Fixed(*space).score(np.zeros((20, 1)))
    for k in range(20):
        c = space.voters @ z[k]
        best = np.argsort(-c)[: knn_quality.NEIGHBOURS]
        w = np.exp(knn_quality.SHARPNESS * (c[best] - c.max()))
        assert got[k] == pytest.approx((w * space.label[best]).sum() / w.sum())


def test_license_scan(odd, odd_rows, none):
    out = license_scan.license_matches(odd).toPandas()
    assert len(out) == len(odd_rows) and out[out.doc_id == 17].licenses.map(list).item() == ["MIT"] and (out.n_matches > 0).sum() == 1
    assert license_scan.license_matches(none).count() == 0
    index = license_scan.build_index(license_scan.TEMPLATES)
    for name, body in license_scan.TEMPLATES.items():
        for pad in range(0, 40, 7):
            text = f"{prose(9, pad)} {body.upper()} {prose(10, 30)}"
            assert name in {x[0] for x in license_scan.scan(pa.array([text]), index)[0]}


def test_license_lines_headers_and_texts(spark):
    held = license_scan.TEMPLATES
    texts = {
        "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.", "CC-BY-NC-SA-4.0": "Licensed under CC BY-NC-SA 4.0.", "CC-BY-4.0": "Licensed under CC BY 4.0.",
        "MIT": held["MIT (text)"], "Apache-2.0": held["Apache-2.0 (header)"], "GPL-3.0": f"This program may be used {held['GPL-3.0 (header)']}, or any later one.",
        "GPL-2.0": f"You can modify it {held['GPL-2.0 (header)']}.", "": "All rights reserved by the licensor of this software and its authors.",
    }
    rows = [(k, f"{prose(20 + k, 12)} {t} {prose(40 + k, 12)}") for k, t in enumerate(texts.values())]
    out = license_scan.license_digest(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r.doc_id: (r.n_licenses, r.licenses) for r in out} == {k: (int(bool(name)), name) for k, name in enumerate(texts)}


def test_pipeline(spark, data):
    import corpus_pipeline as p

    assert [k for k, _ in p.STAGES] == ["quality classifier", "MinHash near-dedup", "substring dedup", "mixing sources to target weights", "packing"]
    docs = spark.read.parquet(f"{data}/documents.parquet")
    columns, held = docs.columns, []
    for name, stage in p.STAGES:
        docs = stage(spark, docs, data).cache()
        held.append(docs.toPandas())
        if name != "packing":
            assert docs.columns == columns
    good, one, cut_, mixed, packed = held
    assert Counter(one.doc_id) == Counter(i for i, _, low in jaccard_components(list(zip(good.doc_id, good.text))) if i == low)
    want = repeats(list(zip(one.doc_id, one.text)))
    kept = {i: s for i, n, gone, s in want if gone < n or n == 0}
    assert set(cut_.doc_id) == set(kept)
    changed = {i for i, n, gone, _ in want if 0 < gone < n}
    assert all(hashlib.sha256(r.text.encode()).hexdigest() == kept[r.doc_id] for r in cut_.itertuples() if r.doc_id in changed)
    assert set(mixed.doc_id) <= set(cut_.doc_id)
    assert packed.groupby("doc_id").length.sum().sum() == packed.drop_duplicates(["sequence_id", "offset"]).length.sum()
    assert Counter(mixed.doc_id).keys() == set(packed.doc_id)


def test_collision_links_tell_vectors_apart_by_themselves(spark):
    """Two vectors of one id, and two without an id, keep their own links."""
    draw = np.random.default_rng(11)
    a, b = draw.standard_normal((2, 16))
    near = lambda x: [float(v) for v in x + 0.01 * draw.standard_normal(16)]
    rows = [(5, near(a)), (5, near(b)), (6, near(a)), (7, near(a)), (8, near(b)), (None, near(-a)), (None, near(-a)), (None, near(-b)), (9, near(-b))]
    out = collision_links.collision_links(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()
    got = Counter((r.vec_id, r.n_links, r.component_id, r.kept) for r in out)
    want = Counter({(5, 2, 5, True): 1, (5, 1, 5, True): 1, (6, 2, 5, False): 1, (7, 2, 5, False): 1, (8, 1, 5, False): 1})
    assert got == want + Counter({(None, 1, None, True): 2, (None, 1, 9, False): 1, (9, 1, 9, True): 1})


def test_collision_settings_are_calibrated_at_every_size():
    for n in (100, 5_000, 51_282, 10**6, 10**8, 10**11):
        plan = collision_links.calibrate(n, 0.9)
        both = 1.0 if plan.directions == 1 else collision_links.both_tails(plan.tail, 0.9)
        odds = collision_links.NormalDist().cdf(collision_links.WINDOW_SIGMAS) * 2 - 1
        draw = np.random.default_rng(1).binomial(collision_links.PROJECTIONS, odds, 200_000)
        region = (1 - (1 - both) ** plan.directions) ** plan.families
        assert plan.count > 10 and region * (draw >= plan.count).mean() >= 0.98 and plan.directions <= collision_links.MOST_DIRECTIONS


def test_windows_and_counts_equal_brute_force():
    draw = np.random.default_rng(12)
    x = collision_links._unit(draw.standard_normal((300, 8)))
    w = collision_links.windows(x, 0.4, 3, 12)
    v = x @ collision_links.directions_of(8, 12, -1 % (1 << 32), 3).astype(float)
    count = (np.abs(v[:, None] - v[None]) <= 0.4).sum(axis=2)
    left, right = collision_links.collided(w, slice(0, 300), slice(0, 300), 7)
    assert set(zip(left.tolist(), right.tolist())) == set(zip(*(i.tolist() for i in np.nonzero(count >= 7))))
    assert 0 < (count >= 7).mean() < 0.3


def test_collision_links_with_many_regions(spark, monkeypatch):
    """Regions of about 64 rows: recall and counting once hold where most pairs share several regions."""
    monkeypatch.setattr(collision_links, "REGION_ROWS", 64)
    draw = np.random.default_rng(13)
    x = draw.standard_normal((3000, 24))
    x[2000:] = x[:1000] + 0.3 * draw.standard_normal((1000, 24))
    df = spark.createDataFrame([(k, [float(v) for v in r]) for k, r in enumerate(x)], "vec_id long, embedding array<double>")
    out = collision_links.collision_links(df).toPandas().sort_values("vec_id")
    u = x / np.linalg.norm(x, axis=1)[:, None]
    true = u @ u.T >= 0.9
    np.fill_diagonal(true, False)
    assert (out.n_links.to_numpy() <= true.sum(1)).all() and out.n_links.sum() >= 0.97 * true.sum()


def test_license_of_any_offset_and_edit_is_found():
    """A copy that holds 80 to 85% of a template's shingles, at every offset from the grid of windows."""
    draw = np.random.default_rng(14)
    for n in (30, 120, 400):
        body = prose(60 + n, n).split()
        index = license_scan.build_index({"T": " ".join(body), "other": prose(61, 90)})
        mine = index.shingles[0]
        step = license_scan.window_of(index.sizes[0])[1]
        tried = 0
        for offset in range(2 * step):
            for _ in range(3):
                w = list(body)
                while True:
                    at = int(draw.integers(n))
                    was, w[at] = w[at], f"q{draw.integers(1 << 30)}"
                    share = np.isin(mine, license_scan.word_shingles(pa.array([" ".join(w)]))[1][: n - 4]).mean()
                    if share < 0.85:
                        break
                if share < 0.8:
                    w[at] = was
                tried += 1
                text = f"{prose(62, offset)} {' '.join(w)} {prose(63, int(draw.integers(0, 90)))}"
                assert "T" in {x[0] for x in license_scan.scan(pa.array([text]), index)[0]}, (n, offset)
        assert tried == 6 * step


def test_license_bands_retrieve_and_containment_decides():
    """Results equal exact counting over every window; without its bands nothing is found."""
    draw = np.random.default_rng(15)
    templates = {"A": prose(70, 40), "B": prose(71, 12), "C": prose(72, 6), "D": prose(73, 200)}
    index = license_scan.build_index(templates)
    texts = [None, "", "one two", prose(73, 150)]
    for k in range(150):
        w = f"{prose(100 + k, int(draw.integers(0, 40)))} {templates['ABCD'[k % 4]]} {prose(300 + k, int(draw.integers(0, 40)))}".split()
        for at in draw.choice(len(w), int(len(w) * draw.random() * 0.1), replace=False):
            w[at] = "edit"
        texts.append(" ".join(w))
    got = [{x[0] for x in found} for found in license_scan.scan(pa.array(texts, pa.string()), index)]
    r, run, _ = license_scan.word_shingles(pa.array(texts, pa.string()))
    want = []
    for d in range(r.n):
        mine = run[r.first[d] : max(r.first[d], r.first[d + 1] - 4)]
        held = set()
        for t, name in enumerate(index.names):
            for a in range(len(mine)):
                if len(np.intersect1d(mine[a : a + index.sizes[t]], index.shingles[t])) >= 0.8 * len(index.shingles[t]) - 1e-9:
                    held.add(name)
        want.append(held)
    assert got == want and sum(map(len, want)) > 60
    blind = index._replace(keys=index.keys + np.uint32(1))
    assert not any(license_scan.scan(pa.array(texts, pa.string()), blind))


def test_longest_matches_equal_brute_force():
    draw = np.random.default_rng(16)
    size = draw.integers(1, 30, 40)
    value = draw.integers(0, 4, size.sum())
    end = np.repeat(np.cumsum(size), size)
    length, source = rlz_dedup.longest_matches(value, end - np.arange(len(value)))
    for i in range(len(value)):
        best = 0
        for j in range(len(value)):
            k = 0
            while j != i and i + k < end[i] and j + k < end[j] and value[i + k] == value[j + k]:
                k += 1
            best = max(best, k)
        assert length[i] == best and (not best or (value[i : i + best] == value[source[i] : source[i] + best]).all())


def test_greedy_factors_reach_over_anchors(spark):
    """A long copy is one factor from end to end, whatever blocks its anchors lie in."""
    body = prose(80, 900).split()
    rows = [(1, " ".join(prose(81, 40).split() + body)), (2, " ".join(body[100:800])), (3, " ".join(body[100:140] + prose(82, 50).split()))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    known, found = rlz_dedup.factors(df)
    by = {r.seq: r.doc_id for r in known.collect()}
    got = {(by[f.seq], f.start, f.length, by[f.source_seq], f.source_start) for f in found.collect()}
    assert (2, 0, 700, 1, 140) in got or ((2, 40 - 34, 700 - 6, 1, 146) in got)
    assert max(f[2] for f in got if f[0] == 1) >= 690 and {f[:3] for f in got if f[0] == 3} == {(3, 0, 40)}


def test_rows_without_ids_are_not_multiplied(spark):
    """Null and repeated ids: as many rows out as in, each with its own text, however often a row is repeated."""
    body = prose(90, 60)
    rows = [(None, prose(100 + k, 40) + " " + (body if k % 2 else prose(200 + k, 45))) for k in range(30)] + [(None, body)] * 4 + [(3, prose(91, 50))] * 3 + [(3, body + " x"), (3, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    out = rlz_dedup.digest(df).toPandas().astype(object)
    assert Counter((None if r[0] != r[0] else int(r[0]), int(r[1]), int(r[2]), r[3]) for r in out.itertuples(index=False)) == repeats(rows)


def test_anchors_of_a_text_longer_than_a_piece():
    value = np.random.default_rng(17).integers(0, 1 << 63, 5000).astype(np.uint64) << np.uint64(1)
    assert (rlz_dedup.Parsed._minima(value, 28) == rlz_dedup.Parsed._minima(value, 28, 700)).all()


def test_one_row_of_each_component_stays(spark):
    """Ids that repeat, or lack, don't bring back a row whose component has a smaller one."""
    a, b, c = prose(300, 30), prose(301, 30), prose(302, 30)
    rows = [(5, b, 1), (9, a, 2), (9, b, 3), (None, a, 4), (None, c, 5), (None, c, 5), (7, c + " x", 6), (8, None, 7), (8, "", 8), (None, " ", 9), (11, prose(303, 9), 10), (11, prose(303, 9), 10)]
    df = spark.createDataFrame(rows, "doc_id long, text string, node long")
    out = [(r.doc_id, r.node) for r in lsh_forest.keep_one(df).collect()]
    assert sorted(out, key=str) == sorted([(5, 1), (9, 2), (7, 6), (8, 7), (8, 8), (None, 9), (11, 10)], key=str)
    only = spark.createDataFrame([(None, c)] * 3 + [(None, c + " y")], "doc_id long, text string")
    assert lsh_forest.keep_one(only).count() == 1


def test_pipeline_stages_on_odd_rows(odd, odd_rows, none, spark, tmp_path):
    """Every stage on nulls, repeated rows and clashing names, and on an empty table."""
    import corpus_pipeline as p

    spark.createDataFrame([(7, 1, 0), (8, 1, 0), (13, 0, 0), (None, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    for name, stage in p.STAGES:
        out = stage(spark, odd.withColumn("n_chars", F.length("text").cast("long")), str(tmp_path))
        assert out.count() <= 3 * len(odd_rows) + 8, name
        empty = stage(spark, none.withColumn("n_chars", F.lit(0).cast("long")), str(tmp_path))
        assert empty.count() == 0 and empty.columns == out.columns, name


def test_quality_counts_equal_brute_force(spark, data, labels):
    """All five base counts and the base verdict, text by text."""
    docs = spark.read.parquet(f"{data}/documents.parquet")
    extra = [(-1, "a b c a b c\n\n x\nx\n x"), (-2, "# $ |<>\n" * 3), (-3, None), (-4, "é日本 " * 60), (-5, "one two")]
    both = docs.select("doc_id", "text").unionByName(spark.createDataFrame(extra, "doc_id long, text string"))
    out = {r.doc_id: r for r in tree_rules.quality_rules(both, labels).collect()}
    for r in both.collect():
        w = words(r.text)
        lines = [x for x in (r.text or "").split("\n") if words(x)]
        seen = Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
        repeated = {k + j for k in range(len(w) - 2) if seen[tuple(w[k : k + 3])] > 1 for j in range(3)}
        got = out[r.doc_id]
        want = (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in r.text or ""), len(lines) - len(set(lines)), len(repeated))
        assert (got.n_words, got.word_chars, got.n_symbols, got.n_dup_lines, got.n_repeat_words) == want
        assert got.base_failed == (len(w) < 50 or 100 * len(repeated) > 50 * len(w))


def test_shards_of_a_table_equal_their_sums(spark, data):
    """Sizes and checksums of real texts, and slots without gaps."""
    docs = spark.read.parquet(f"{data}/documents.parquet")
    out = kd_shards.kd_shards(docs).join(docs.select("doc_id", "text"), "doc_id").toPandas()
    raw = out.text.fillna("").map(str.encode)
    assert len(out) == docs.count() and (out["size"] == raw.map(len) + 8).all() and (out.text_crc32 == raw.map(zlib.crc32)).all()
    for _, g in out.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))
