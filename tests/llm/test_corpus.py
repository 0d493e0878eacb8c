"""Corpus operators against brute force on small tables, with nulls, ties, repeats and odd columns."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict
from random import Random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from abilityrank.llm import cotraining, encode, fingerprint_index, kernels, kmeans_tree, licences, merge_dropout, packing, quality_rules, suffix_dedup, token_store, weighted_minhash
from abilityrank.llm.components import components
from abilityrank.llm.shared import shared_dir

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, gram long, score double"
WORDS = "the of and to in an on is it by thea onth erin shin tion ould nder esti".split()


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empties, white space only, repeats, a long text, near and exact copies, clashing columns."""
    rng = Random(7)
    base = " ".join(rng.choice(WORDS) + str(rng.randint(0, 300)) for _ in range(160))
    passage = " ".join(rng.choice(WORDS) + str(rng.randint(0, 999)) for _ in range(70))
    near = base.split()
    near[80] = "changed"
    texts = [None, "", "  \n\t ", "one", base, base, " ".join(near), "start " + passage + " end", "other\n" + passage.replace(" ", "\n") + "\nrest é ü 漢字", passage, " ".join(rng.choice(WORDS) for _ in range(4000)), "a a a a a a a a a a a a", "x" * 900, "x" * 900 + "y"]
    rows = [(i, t, "en" if i % 2 else None, f"src{i % 3}", None if t is None else len(t), 5, 0.5) for i, t in enumerate(texts)]
    rows += [(4, base, "en", "src0", 3, 1, 1.0), (None, base, "en", "src0", 3, 1, 1.0), (9, "another text of the same doc", None, None, None, 1, 1.0)]
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def as_rows(df):
    return [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]


def test_kernels_by_hand():
    block = next(kernels.text_blocks(pa.array(["ab  cd e", None, "cd", " ", "e f g h i j"])))
    words = kernels.words_of(block)
    assert [block.data[a:b].tobytes() for a, b in zip(words.start, words.end)] == [b"ab", b"cd", b"e", b"cd", b"e", b"f", b"g", b"h", b"i", b"j"]
    assert words.first.tolist() == [0, 3, 3, 4, 4, 10]
    h = words.hashes(block)
    assert h[1] == h[3] and h[2] == h[4] and len(set(h.tolist())) == 8
    values = np.random.default_rng(0).integers(0, 9, 200).astype(np.uint64)
    assert kernels.sliding_argmin(values, 13).tolist() == [i + int(values[i : i + 13].argmin()) for i in range(188)]


@pytest.mark.parametrize("name,byte_level", [("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)])
def test_piecewise_ids_equal_whole_ids(spark, name, byte_level):
    encoder = encode.PieceEncoder(encode.vocabulary(name), byte_level)
    texts = [t or "" for _, t in as_rows(spark.read.parquet(f"{SF}/documents.parquet"))]
    texts += ["a  b \n c\n\nd  ", " x", "x ", "", "\n", "a\tb", "a\x85b c", "a\xa0b c<|endoftext|> d", "don't  he's 12 3", "é ́x", " ́a", "A　b", "a \x1c b", "I'll 've", "a. b, é, 1. x%, %. . , A, B.\nC.", "a\x00b c"]
    for lo in range(0, len(texts), 50):
        want = [np.array(e.ids, encoder.dtype).tobytes() for e in encoder.tok.encode_batch(texts[lo : lo + 50], add_special_tokens=False)]
        assert encoder.payloads(texts[lo : lo + 50]) == want


def test_perfect_hash_and_strangers():
    keys = np.random.default_rng(1).choice(1 << 40, 5000, replace=False).astype(np.int64)
    part = token_store.IndexPart.build(np.concatenate([keys, keys[:10]]), np.zeros(5010, np.int64), np.arange(5010), np.ones(5010, np.int64))
    part = token_store.IndexPart.from_bytes(part.to_bytes())
    assert sorted(part.hash.slots(keys.view(np.uint64)).tolist()) == list(range(5000))
    who, row = part.lookup(keys[:10])
    assert Counter(who.tolist()) == dict.fromkeys(range(10), 2) and {(w, part.places[r, 1]) for w, r in zip(who.tolist(), row.tolist())} == {(i, x) for i in range(10) for x in (i, 5000 + i)}
    assert len(part.lookup(keys + (1 << 41))[0]) <= 1  # refused by fingerprints


def test_token_store_round_trip(spark, odd):
    store = token_store.TokenStore.write(odd, shared_dir(spark, "t"), shards=4, parts=3)
    store = token_store.TokenStore.open(spark, store.folder)
    got = store.read(store.lookup(odd), digest=True).collect()
    tok = encode.PieceEncoder.get(encode.vocabulary("byte_bpe_50k.json"), True).tok
    want = Counter((d, zlib.crc32(np.array([*tok.encode(t or "", add_special_tokens=False).ids, 2], "<u4").tobytes())) for d, t in as_rows(odd))
    assert Counter((r["doc_id"], r["ids_crc32"]) for r in got) == want
    got.sort(key=lambda r: r["start"])
    at = 0
    for r in got:
        assert r["start"] == at
        at += r["n_tokens"]
    known = [r["doc_id"] for r in got]
    assert known == sorted(known, key=lambda x: -1 if x is None else x)
    assert store.lookup(spark.createDataFrame([(77777,)], "doc_id long")).count() == 0
    nothing = token_store.TokenStore.write(empty(spark), shared_dir(spark, "t"), shards=2, parts=2)
    assert nothing.read(nothing.lookup(empty(spark)), digest=True).count() == 0


def test_neighbours_against_brute_force(spark):
    rng = np.random.default_rng(5)
    v = rng.standard_normal((600, 8)).astype(np.float32)
    v[50] = v[100] = v[101] = v[102] = v[7]
    rows = [(i, [float(x) for x in r]) for i, r in enumerate(v)] + [(600, None), (650, [0.0] * 8), (601, [float("nan")] * 8), (602, [1.0]), (None, [1.0] * 8)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("score", F.lit(1)).repartition(3)
    got = defaultdict(list)
    for r in kmeans_tree.neighbours(df, rows_a_leaf=40, recall=0.95, tile=64).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    unit = v.astype(float) / np.linalg.norm(v.astype(float), axis=1, keepdims=True)
    hits = 0
    for q in range(0, 600, 50):
        s = unit @ unit[q]
        s[q] = -2
        want = np.lexsort((np.arange(600), -np.round(s, 12)))[:5]
        assert len(got[q]) == 5
        hits += len({i for i, _ in got[q]} & set(want.tolist()))
        assert all(abs(x - s[i]) < 1e-9 for i, x in got[q])
    assert set(got) == set(range(0, 600, 50)) and hits >= 54
    assert [i for i, _ in got[50]][:4] == [7, 100, 101, 102]
    assert kmeans_tree.neighbours(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0
    assert kmeans_tree.neighbours(spark.createDataFrame([(0, [1.0, 2.0]), (3, [2.0, 1.0])], "vec_id long, embedding array<float>")).count() == 1


def test_neighbours_with_ties_and_mixed_widths(spark):
    """Copies scaled by powers of two score alike and come by vec_id; other widths take no part."""
    rng = np.random.default_rng(8)
    v = rng.standard_normal((300, 6))
    for i, scale in ((40, 2.0), (120, 0.5), (201, 4.0), (7, 1.0), (250, 8.0), (33, 16.0)):
        v[i] = v[100] * scale
    rows = [(i, r.tolist()) for i, r in enumerate(v)] + [(1000 + i, [1.0] * (2 + i % 3)) for i in range(30)] + [(2000, [1e300] * 6), (2050, [float("inf")] + [0.0] * 5)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = defaultdict(list)
    for r in kmeans_tree.neighbours(df, rows_a_leaf=50, recall=0.99).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    assert [i for i, _ in got[100]] == [7, 33, 40, 120, 201] and all(abs(x - 1) < 1e-12 for _, x in got[100])
    assert [i for i, _ in got[250]] == [7, 33, 40, 100, 120]
    assert not {x for own in got.values() for x, _ in own} & {*range(1000, 1030), 2050} and 1000 not in got and 2050 not in got
    assert all(np.isfinite(x) for own in got.values() for _, x in own)


def test_walks_hold_one_row_a_query(spark, monkeypatch):
    """However many leaves a query visits; pairs found in small pieces are those of brute force."""
    v = np.random.default_rng(9).standard_normal((900, 6))
    df = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(v)], "vec_id long, embedding array<double>")
    rows, keep, further = {}, kmeans_tree.materialise, kmeans_tree._further

    def counted(df, name):
        out = keep(df, name)
        rows[name] = out.count()
        return out

    monkeypatch.setattr(kmeans_tree, "materialise", counted)
    monkeypatch.setattr(kmeans_tree, "_further", lambda *a: further(*a, chunk=100, block=7, piece=30, most=40))
    got = defaultdict(list)
    for r in kmeans_tree.neighbours(df, every=30, rows_a_leaf=10, recall=1.0).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append(r["vec_id"])
    unit = v / np.linalg.norm(v, axis=1, keepdims=True)
    want = {q: [i for i in np.argsort(-(unit @ unit[q])).tolist() if i != q][:5] for q in range(0, 900, 30)}
    assert rows["walks"] == 30 and got == want


def test_very_long_texts_are_whole(spark):
    """A text far beyond any block: every operator over texts sees its end."""
    rng = Random(12)
    tail = " ".join(f"tail{rng.randint(0, 10**6)}" for _ in range(80))
    long = " ".join(rng.choice(WORDS) + str(rng.randint(0, 10**5)) for _ in range(60_000)) + " all rights reserved " + tail
    docs = spark.createDataFrame([(1, tail), (2, long), (3, long)], "doc_id long, text string")
    cut = {r["doc_id"]: r for r in fingerprint_index.dedup_substrings(docs).collect()}
    assert cut[2]["n_words"] == 60_083 and cut[2]["n_removed"] == 80 and cut[3]["n_removed"] == 60_083
    removed = {r["doc_id"]: r for r in suffix_dedup.dedup_bytes(docs).collect()}
    assert removed[1]["n_removed"] == len(tail) and removed[2]["n_removed"] == removed[3]["n_removed"] == len(long)
    spans = {r["doc_id"]: r for r in licences.scan_licences(docs).collect()}
    assert spans[2]["first_word"] == 60_000 and spans[2]["n_words"] == 60_083
    encoded = {r["doc_id"]: r for r in merge_dropout.encode_documents(docs).collect()}
    assert all(r["restored"] for r in encoded.values()) and encoded[2]["ids_crc32"] != encoded[3]["ids_crc32"]  # other documents, other skips
    assert {r["doc_id"]: r["class_id"] for r in weighted_minhash.near_duplicates(docs).collect()} == {1: 1, 2: 2, 3: 2}
    report = {r["doc_id"]: r for r in quality_rules.quality_rules_report(docs).collect()}
    assert report[2]["n_words"] == 60_083


def test_classifier_on_held_out_labels(spark, odd):
    docs, labels = spark.read.parquet("/root/testdata/sf0.1/documents.parquet"), spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    half = labels.where("doc_id % 2 = 0")
    scored = cotraining.score_documents(docs, half).join(labels.where("doc_id % 2 = 1"), "doc_id").collect()
    assert sum(r["kept"] == bool(r["quality"]) for r in scored) / len(scored) > 0.97
    model = cotraining.train(docs, half)
    assert sum(model.added) > 0  # views did exchange labels
    assert cotraining.score_documents(odd, half).count() == odd.count()
    assert cotraining.score_documents(odd, half.where("1 = 0")).where("not kept or score <> 0.5").count() == 0
    assert cotraining.score_documents(empty(spark), half).count() == 0
    kept = cotraining.keep_good(docs, labels)
    assert kept.columns == docs.columns and 0 < kept.count() < docs.count()


def test_views_exchange_labels_on_the_whole_table(spark):
    docs, labels = spark.read.parquet("/root/testdata/sf0.1/documents.parquet"), spark.read.parquet("/root/testdata/sf0.1/labels.parquet").where("doc_id % 2 = 0")
    n = docs.count()
    many = docs.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(1)))).withColumn("doc_id", F.col("doc_id") + F.col("k") * 10_000_000)
    one, two = (cotraining.train(x, labels, labelled=500, rounds=1).added for x in (docs, many))
    # more than any fixed pool or quota, also of labelled rows beyond the bound; each copy is exchanged again
    assert one[1] > 0.5 * (n - 500) and two[1] >= one[1] + 0.5 * n


def test_views_are_calibrated_one_by_one():
    rng = np.random.default_rng(4)
    y = (rng.random(4000) < 0.5).astype(float)
    x = np.stack([y * 2 - 1 + rng.standard_normal(4000)], 1).astype(np.float32)
    m = np.stack([y * 2 - 1 + 3 * rng.standard_normal(4000)], 1).astype(np.float32)
    model = cotraining.CoTrained(np.array([9.0, 2.0]), np.array([7.0, -3.0]), np.array([[1.0, 0.0]] * 2), np.array([0.5, 0.5, 0.0]), (0, 0))
    model.calibrate(x, m, y)
    for s in model.score(x, m):  # among documents of about one score, that share is good
        for lo in (0.1, 0.4, 0.7):
            own = (s >= lo) & (s < lo + 0.2)
            assert own.sum() < 100 or abs(y[own].mean() - s[own].mean()) < 0.08
    both, a, b = model.score(x, m)
    loss = lambda p: -np.mean(np.log(np.where(y == 1, p, 1 - p)))
    assert loss(both) < loss(a) < loss(b)


def test_conflicting_labels_are_settled(spark):
    docs = spark.createDataFrame([(i, ("fine words here. " if i % 2 else "### $$$ ") * 9, None, None, None) for i in range(80)], "doc_id long, text string, lang string, source string, n_chars long")
    labels = spark.createDataFrame([(i, i % 2) for i in range(80)] + [(0, 1), (2, 1), (3, 0), (3, 1)] + [(None, 1), (5, None), (7, 9)], "doc_id long, quality int")
    scored = {r["doc_id"]: r["kept"] for r in cotraining.score_documents(docs, labels).collect()}
    assert all(scored[i] == bool(i % 2) for i in scored)  # also those without a label of their own


def test_consistent_sampling_estimates_weighted_jaccard():
    rng = np.random.default_rng(2)
    h = rng.integers(0, 1 << 62, 400).astype(np.uint64)
    h.sort()
    wa, wb = rng.random(300) + 0.2, rng.random(300) + 0.2
    wb[:200] = wa[100:300]
    s = weighted_minhash.consistent_samples(np.concatenate([h[:300], h[100:]]), np.concatenate([wa, wb]), np.array([0, 300, 600]), samples=2048)
    want = wa[100:300].sum() / (wa.sum() + wb.sum() - wa[100:300].sum())
    assert abs((s[0] == s[1]).mean() - want) < 0.05
    small = lambda x: (x >> np.uint64(32)).astype(np.uint32)
    assert weighted_minhash.weighted_jaccard(small(h[:300]), wa, small(h[100:]), wb) == pytest.approx(want)


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(1, 40)] + [(100, x) for x in range(101, 160)] + [(200, 201), (201, 200), (5, 5)]
    got = {r["node"]: r["root"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 1 for i in range(1, 41)} | {x: 100 for x in range(100, 160)} | {200: 200, 201: 200}


def test_near_duplicates_against_all_pairs(spark, odd):
    got = {(r["doc_id"]): r["class_id"] for r in weighted_minhash.near_duplicates(odd).collect()}
    assert got[4] == got[5] == got[6] == 4
    assert got[7] == got[8] == 7  # the passage with a few words more
    assert all(got[i] == i for i in (0, 1, 2, 3, 10, 11))
    rows = weighted_minhash.near_duplicates(odd).collect()
    assert len(rows) == odd.count() and [(r["class_id"], r["class_size"]) for r in rows if r["doc_id"] is None] == [(None, 1)]
    assert weighted_minhash.near_duplicates(empty(spark)).count() == 0
    docs = spark.read.parquet(f"{SF}/documents.parquet").union(odd.where("doc_id in (4, 5, 6, 7, 9, 12, 13) and n_chars > 3").select(F.col("doc_id") + 1_000_000, "text", "lang", "source", "n_chars"))
    found = {r["doc_id"]: r["class_id"] for r in weighted_minhash.near_duplicates(docs).collect()}
    bags = {d: Counter(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4)) if w) for d, t in as_rows(docs) for w in [t.split()]}
    df = Counter(x for bag in bags.values() for x in bag)
    weigh = lambda bag: {x: n * np.log1p(len(bags) / max(df[x], 0.002 * len(bags))) for x, n in bag.items()}
    weights = {d: weigh(bag) for d, bag in bags.items()}
    parent = {d: d for d in bags}

    def top(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in weights:
        for b in weights:
            if a < b and (weights[a].keys() & weights[b].keys()):
                low = sum(min(v, weights[b].get(x, 0.0)) for x, v in weights[a].items())
                if low / (sum(weights[a].values()) + sum(weights[b].values()) - low) >= 0.8:
                    u, v = top(a), top(b)
                    parent[max(u, v)] = min(u, v)
    assert found == {d: top(d) for d in bags}


def test_rare_shingles_are_weighted_by_their_own_frequency(spark):
    """Shingles in one, two or four of 2,000 documents weigh differently, and that decides two classes."""
    run = lambda name, n: [f"{name}{i}" for i in range(n)]
    apart = [run("s", 169) + run("a", 20), run("s", 169) + run("b", 20)]  # 165 shared, 40 not: 0.805 unweighted
    both = [run("t", 162) + run("c", 21), run("t", 162) + run("d", 21)]  # 158 shared, 42 not: 0.79 unweighted
    echoes = [["t158", "t159", "t160", "t161"] + run(x, 21) for x in "cd" for _ in range(3)]
    texts = apart + both + [x + [f"e{i}"] for i, x in enumerate(echoes)] + [run(f"x{i}y", 3) for i in range(1990)]
    docs = spark.createDataFrame([(i, " ".join(x)) for i, x in enumerate(texts)], "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: r["class_id"] for r in weighted_minhash.near_duplicates(docs).where("doc_id < 4").collect()}
    assert got == {0: 0, 1: 1, 2: 2, 3: 2}

    docs = weighted_minhash._settled(docs)
    folder = weighted_minhash.document_frequencies(docs, 10_000)
    found = weighted_minhash.signatures(docs, folder, len(texts), 16, 4, 5).select("weights").collect()
    bags = [Counter(tuple(x[k : k + 5]) for k in range(max(1, len(x) - 4))) for x in texts]
    df = Counter(x for bag in bags for x in bag)
    want = [sum(n * np.log1p(len(texts) / df[x]) for x, n in bag.items()) for bag in bags]
    assert sorted(float(np.frombuffer(r["weights"], np.float32).astype(float).sum()) for r in found) == pytest.approx(sorted(want), rel=1e-6)


def brute_windows(rows, n):
    first = {}
    for d, t in rows:
        w = (t or "").encode().split()
        for k in range(len(w) - n + 1):
            if d is not None:
                key = tuple(w[k : k + n])
                first[key] = min(first.get(key, d), d)
    out = Counter()
    for d, t in rows:
        w = (t or "").encode().split()
        gone = {x for k in range(len(w) - n + 1) if d is not None and first[tuple(w[k : k + n])] < d for x in range(k, k + n)}
        out[d, len(w), len(gone), hashlib.sha256(b" ".join(x for i, x in enumerate(w) if i not in gone)).hexdigest()] += 1
    return out


@pytest.mark.parametrize("window,batches,hot", [(50, 2, 2000), (12, 3, 2000), (12, 1, 1)])
def test_fingerprint_index_against_brute_force(spark, odd, window, batches, hot, monkeypatch):
    docs = odd.select("doc_id", "text").union(spark.read.parquet(f"{SF}/documents.parquet").select(F.col("doc_id") + 100, "text"))
    init = fingerprint_index.FingerprintIndex.__init__
    monkeypatch.setattr(fingerprint_index.FingerprintIndex, "__init__", lambda self, s, **k: init(self, s, hot=hot, **k))
    got = Counter(map(tuple, fingerprint_index.dedup_substrings(docs, batches, window, min(20, window // 2)).collect()))
    assert got == brute_windows(as_rows(docs), window)


def test_fingerprint_index_compacts(spark, odd):
    assert fingerprint_index.dedup_substrings(empty(spark)).count() == 0
    index = fingerprint_index.FingerprintIndex(spark)
    docs = odd.where("doc_id is not null")
    index.ingest(docs.where("doc_id <= 4"))
    index.ingest(docs.where("doc_id between 5 and 8"))
    index.compact()
    assert len(index.runs) == 1
    again = fingerprint_index.FingerprintIndex.open(spark.newSession(), index.folder)  # what is listed is all it needs
    assert (again.runs, len(again.texts)) == (index.runs, 2)
    last = docs.where("doc_id > 8")
    cuts = sorted(map(tuple, index.ingest(last).collect()))
    assert any(c[0] == 9 for c in cuts) and cuts == sorted(map(tuple, again.ingest(last).collect()))
    small = fingerprint_index.FingerprintIndex(spark, most_runs=1)
    for low, high in ((0, 4), (5, 8), (9, 99)):
        found = small.ingest(docs.where(F.col("doc_id").between(low, high)))
    assert len(small.runs) == 2 and sorted(map(tuple, found.collect())) == cuts


def test_fingerprint_indexes_of_one_folder_take_turns(spark):
    docs = lambda i, letter: spark.createDataFrame([(i, " ".join(letter + str(k) for k in range(60)))], "doc_id long, text string")
    one = fingerprint_index.FingerprintIndex(spark)
    one.ingest(docs(1, "a"))
    two = fingerprint_index.FingerprintIndex.open(spark.newSession(), one.folder)
    one.ingest(docs(2, "b"))
    two.ingest(docs(3, "c"))
    one.compact()
    two.compact()  # its first run is merged already
    last = fingerprint_index.FingerprintIndex.open(spark, one.folder)
    assert len(last.runs) == 2 and len(last.texts) == 3
    for i, letter in enumerate("abc"):
        assert {x for r in last.ingest(docs(10 + i, letter)).collect() for x in range(r["start"], r["end"])} == set(range(60))


@pytest.mark.parametrize("memory", [8000, 12])
def test_induced_suffixes_against_brute_force(spark, odd, memory):
    docs = odd.select("doc_id", "text").union(spark.read.parquet(f"{SF}/documents.parquet").select(F.col("doc_id") + 100, "text"))
    rows = as_rows(docs)
    n, seen = 60, Counter()
    for _, t in rows:
        b = (t or "").encode()
        seen.update(b[k : k + n] for k in range(len(b) - n + 1))
    want = Counter()
    for d, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b) + 1, bool)
        for k in range(len(b) - n + 1):
            if seen[b[k : k + n]] > 1:
                gone[k : k + n] = True
        spans = int((gone[1:] & ~gone[:-1]).sum() + gone[0])
        want[d, len(b), int(gone.sum()), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone) if not g)).hexdigest()] += 1
    got = Counter(map(tuple, suffix_dedup.dedup_bytes(docs, n, 20, memory).collect()))
    assert got == want
    assert suffix_dedup.dedup_bytes(empty(spark)).count() == 0


def test_external_induction_equals_the_vectorised_one():
    rng = Random(3)
    for length, n in ((10, 5), (12, 80), (16, 300)):
        seen, cases = set(), []
        while len(cases) < n:
            place = rng.randint(0, length - 4)
            count = place - rng.randint(0, place) + 1
            text = bytes(rng.choice(b"ab") for _ in range(place)) + b"@ANC" + bytes(rng.choice(b"ab") for _ in range(length))
            text = text[: count + length - 1]
            if text not in seen:
                seen.add(text)
                cases.append((text, place, count))
        hit = suffix_dedup.induce(np.zeros(n, np.int64), [c[0] for c in cases], np.array([c[1] for c in cases]), np.array([c[2] for c in cases]), length)
        external = suffix_dedup.ExternalInduction(length, most=40, run=16)
        for c in cases:
            external.add(*c)
        found = {(int(i), back) for items, back in external.finish() for i in items}
        assert found == {(int(a), int(b)) for a, b in zip(*np.nonzero(hit))}
        where = defaultdict(set)
        for i, (text, place, count) in enumerate(cases):
            for t in range(count):
                where[place - t, text[t : t + length]].add(i)
        assert found == {(i, back) for (back, _), own in where.items() if len(own) > 1 for i in own}


def test_induced_suffixes_with_zero_bytes(spark):
    """Zero bytes at the end of a context are text, not padding; the smallest doc_id is not null."""
    rng, n, missed = Random(1), 12, 0
    for _ in range(300):
        cases = {}
        for _ in range(rng.randint(3, 12)):
            place = rng.randint(0, n - 4)
            count = place - rng.randint(0, place) + 1
            text = bytes(rng.choice(b"ab") for _ in range(place)) + b"@ANC" + bytes(rng.choice(b"\0\0\0a") for _ in range(n))
            cases[text[: count + n - 1]] = place, count
        place, count = (np.array(x) for x in zip(*cases.values()))
        hit = suffix_dedup.induce(np.zeros(len(cases), np.int64), list(cases), place, count, n)
        where = defaultdict(set)
        for i, (text, (p, c)) in enumerate(cases.items()):
            for t in range(c):
                where[p - t, text[t : t + n]].add(i)
        missed += {(i, back) for (back, _), own in where.items() if len(own) > 1 for i in own} != {(int(a), int(b)) for a, b in zip(*np.nonzero(hit))}
    assert not missed
    rows = [(-(1 << 63), "x" * 900), (None, "x" * 900), (1, "\0" * 900)]
    got = suffix_dedup.dedup_bytes(spark.createDataFrame(rows, "doc_id long, text string")).select("doc_id", "n_bytes", "n_removed").collect()
    assert Counter(map(tuple, got)) == Counter((d, 900, 900) for d, _ in rows)


def test_packing_places_everything(spark, odd):
    tok = encode.PieceEncoder.get(encode.vocabulary("word_bpe_49k.json"), False).tok
    docs = odd.select("doc_id", "text").union(spark.read.parquet(f"{SF}/documents.parquet").select(F.col("doc_id") + 100, "text"))
    rows = packing.pack(docs).collect()
    want = Counter()
    for d, t in as_rows(docs):
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 0]
        for k, s in enumerate(range(0, len(ids), 2048)):
            part = ids[s : s + 2048]
            want[d, k, s, len(part), zlib.crc32(np.array(part, "<u4").tobytes())] += 1
    assert Counter(tuple(r[c] for c in ("doc_id", "piece", "start", "length", "ids_crc32")) for r in rows) == want
    bins = defaultdict(list)
    for r in rows:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    for own in bins.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= 2048
    total = sum(r["length"] for r in rows)
    assert len(bins) <= -(-total // 2048) * 1.02 + 2
    assert packing.pack(empty(spark)).count() == 0


def test_leading_tokens_give_the_norm_over_all_sequences(monkeypatch):
    """Comparing only the fewest residual tokens with room gives what comparing all gives."""
    rng = Random(4)
    histogram = Counter(rng.choice([rng.randint(1, 100), rng.randint(1, 30)]) for _ in range(800))
    caps = packing.Capacities(100, 5, 6000)
    histogram = {k: v for k, v in histogram.items() if k <= 77}
    assert packing.leads(packing.Capacities(), packing.WEIGHTS) and packing.leads(caps, packing.WEIGHTS)
    quick = packing.plan(histogram, caps)
    monkeypatch.setattr(packing, "leads", lambda *a: False)
    assert packing.plan(histogram, caps) == quick


@pytest.mark.parametrize("rule,weights", [("norm", (1.0, 0.0, 0.0)), ("norm", (1.0, 0.5, 0.2)), ("dot", (1.0, 1.0, 1.0))])
def test_plans_keep_every_capacity(rule, weights):
    rng = Random(9)
    histogram = Counter(rng.choice([rng.randint(1, 100), rng.randint(1, 20)]) for _ in range(3000))
    caps = packing.Capacities(100, 6, 8000)
    used, placed = defaultdict(lambda: [0, 0, 0]), Counter()
    for length, number, count, start, offset in packing.plan({k: v for k, v in histogram.items() if k <= 89}, caps, rule, weights):
        for k in range(count):
            b = used[start + k]
            assert offset == b[0]
            b[0], b[1], b[2] = b[0] + length, b[1] + 1, b[2] + length * length
            placed[length, number + k] += 1
    assert all(b[0] <= 100 and b[1] <= 6 and b[2] <= 8000 for b in used.values())
    assert placed == {(length, k): 1 for length, n in histogram.items() if length <= 89 for k in range(n)}


def test_rules_on_odd_rows(spark, odd):
    got = quality_rules.quality_rules_report(odd).collect()
    assert len(got) == odd.count()
    by = {r["doc_id"]: r for r in got}
    assert by[0]["n_words"] == by[1]["n_words"] == by[2]["n_words"] == 0 and by[0]["base_failed"] and not by[0]["kept"]
    assert by[11]["n_words"] == 12 and by[11]["n_repeat_words"] == 12 and by[11]["base_failed"]
    assert quality_rules.quality_rules_report(empty(spark)).count() == 0
    assert set(odd.columns) - {"score"} <= set(quality_rules.apply_rules(odd).columns)


def test_dropout_encoding(spark, odd):
    import sentencepiece

    path = encode.vocabulary("piece_bpe_32k.model")
    library, plain, loose = sentencepiece.SentencePieceProcessor(model_file=path), merge_dropout.DropoutEncoder(path, 0.0), merge_dropout.DropoutEncoder(path, 0.3)
    texts = [t or "" for _, t in as_rows(odd)] + ["", "a", " a", "  a  b   ", " ", "a▁b", "▁", " ▁", "\U0001F600x\x00\n\n\ty", "12 345", "a \nb", "\n", "x.\ny, z"]
    for t in texts:
        assert plain.decode(plain.encode(t, 1)) == loose.decode(loose.encode(t, 1)) == t
        assert "▁" in t or plain.encode(t, 1) == library.encode(t)
        assert loose.encode(t, 1) == merge_dropout.DropoutEncoder(path, 0.3).encode(t, 1)
    long = ' '.join(f'{w}tion{i}' for i, w in enumerate(WORDS))
    assert loose.encode(long, 1) != loose.encode(long, 2)
    rows = merge_dropout.encode_documents(odd).collect()
    assert len(rows) == odd.count() and all(r["restored"] for r in rows)
    assert merge_dropout.encode_documents(empty(spark)).count() == 0


def test_dropout_is_drawn_at_every_place():
    encoder = merge_dropout.DropoutEncoder(rate=0.1)
    model = encoder.model
    forms = Counter(encoder.encode("national", doc).__str__() for doc in range(4000))
    rng = Random(1)  # the same with a draw for every candidate
    want = Counter(str([model.pieces[s] for s in model.unit("▁national", tuple(i for i in range(32) if rng.random() < 0.1))]) for _ in range(4000))
    assert len(forms) > 2 and all(abs(forms[x] - want[x]) < 5 * max(want[x], forms[x], 25) ** 0.5 * 2**0.5 for x in {*forms, *want})
    # places of one text differ too, with runs of spaces as well
    for text in (" ".join(["national"] * 300), "  ".join(["national"] * 300)):
        ids = encoder.encode(text, 3)
        assert len({tuple(x) for x in " ".join(map(str, ids)).split(str(ids[0]))}) > 2 and encoder.decode(ids) == text
    assert len(merge_dropout.DropoutEncoder(rate=1.0).encode("national", 1)) == 9


@pytest.mark.parametrize("rate", [0.1, 0.5])
def test_agendas_side_by_side_equal_one_agenda_a_unit(spark, odd, rate, monkeypatch):
    """Each unit's segmentation is that of its own agenda, with the skips of its document and place."""
    encoder = merge_dropout.DropoutEncoder(rate=rate)
    model = encoder.model
    step = np.uint64(0x9E3779B97F4A7C15)

    def brute(text, doc):
        out, base = [], np.uint64(merge_dropout._hash(encoder.seed, doc))
        for place, unit in enumerate(re.findall(r" +[^ \n]*|\n[^ \n]*", " " + text) if text else []):
            key = merge_dropout.mix(np.array([base + np.uint64(place * int(step) & (1 << 64) - 1)], np.uint64))[0]
            for s in model.unit(unit.replace("▁", "\0").replace(" ", "▁"), encoder._skips(key)):
                out += [model.pieces[s]] if s in model.pieces else model.bytes[list(s.replace("\0", "▁").encode())].tolist()
        return out

    assert model.breaks_alone
    texts = [t or "" for _, t in as_rows(odd)] + [t for _, t in as_rows(spark.read.parquet(f"{SF}/documents.parquet").limit(60)) if t]
    texts += ["a▁b  c\n\nd", "national" * 30 + " x" * 9, "\U0001F600 é漢字" * 40]
    want = [brute(t, d) for d, t in enumerate(texts)]
    for block in (1 << 18, 500):  # texts longer than a block are encoded in parts
        monkeypatch.setattr(merge_dropout, "BLOCK", block)
        got = [ids[s:e].tolist() for _, _, ids, begin in encoder.encode_texts(texts, list(range(len(texts)))) for s, e in zip(begin, begin[1:])]
        assert got == want


def brute_licence(text):
    words = licences.scan_words((text or "").encode())
    places = [(i, label) for phrase, label in licences.BASE_PHRASES for p in [phrase.encode().split()] for i in range(len(words) - len(p) + 1) if words[i : i + len(p)] == p]
    return len(words), len(places), min((i for i, _ in places), default=None), max((i for i, _ in places), default=None), ",".join(sorted({x for _, x in places}))


def test_licences(spark, odd):
    docs = odd.select("doc_id", "text").union(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select(F.col("doc_id") + 100, "text"))
    want = Counter((d, *brute_licence(t)) for d, t in as_rows(docs))
    rows = licences.scan_licences(docs).collect()
    assert Counter(tuple(r[c] for c in ("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels")) for r in rows) == want
    assert all(set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(",")) and 0 <= r["score"] <= 1 for r in rows)
    scan = licences.LicenceScanner().scan
    assert scan(b"x Released under the MIT License. y")["labels"] == "mit"
    assert scan(b"Licensed under the Apache License, Version 2.0")["labels"] == "apache"
    assert scan(b"All rights reserved. CC-BY; cc by")["n_base"] == 3
    assert scan(b"the license of the software is here")["labels"] == ""
    # the score is the share of a template that is covered, also for base phrases
    assert scan(b"All rights reserved.")["score"] == 1.0 and scan(b"see cc by")["score"] == 2 / 9
    whole = licences.TEMPLATES["mit"][-1]
    words = whole.split()
    full, cut = scan(whole.encode()), scan(" ".join(words[:60] + ["altered"] + words[62:]).encode())
    assert full["labels"] == cut["labels"] == "mit" and full["score"] == 1.0
    longest = max(cut["spans"], key=lambda x: x["last"] - x["first"])
    assert longest["last"] - longest["first"] == len(words) - 2 and 0.9 < longest["covered"] < 1.0
    assert licences.scan_licences(empty(spark)).count() == 0


def test_matching_statistics_by_brute_force():
    rng = Random(6)
    for _ in range(60):
        templates = [[rng.randint(0, 3) for _ in range(rng.randint(1, 12))] for _ in range(3)]
        automaton = licences.SuffixAutomaton()
        for i, t in enumerate(templates):
            automaton.add(i, t)
        automaton.close()
        text = [rng.choice([0, 1, 2, 3, None]) for _ in range(40)]
        runs = {tuple(t[a:b]) for t in templates for a in range(len(t)) for b in range(a + 1, len(t) + 1)}
        for k, (state, n) in enumerate(automaton.statistics(text)):
            best = max((m for m in range(1, k + 2) if tuple(text[k - m + 1 : k + 1]) in runs), default=0)
            assert n == best
            for template, end in automaton.ends[state] if n else ():
                assert templates[template][end - n + 1 : end + 1] == text[k - n + 1 : k + 1]
