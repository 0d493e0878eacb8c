"""Near-duplicates by improved consistent weighted sampling over TF-IDF shingles.

A shingle is five consecutive words (a shorter text is one shingle).  Its weight in a document is
its count times ``ln(1 + N / df)`` of N documents.  The document frequency of every shingle is exact:
each unit of some consecutive texts deals its distinct shingles out by hash, the counts come back to the
unit as one file in the shared folder, and a second reading of the texts finds it by the hash of its
texts.  So texts are read twice in equal batches; a plan that might not give them is written out first.

Each text gets ``bands * rows`` samples; the chance that two texts share one is their weighted
Jaccard similarity.  Texts that share all samples of a band are candidates.  In every band's bucket
the texts are compared with two centres; then texts of a bucket that are still in different classes
are compared with each other by their samples, in blocks.  Every candidate that is kept has its
weighted Jaccard similarity computed from all shingles of both texts and must reach ``least``.

Texts with the same words are one text from the start.  Null, empty and wordless texts are classes
of their own; a row without doc_id has a null class of size 1.  Rows that repeat a doc_id are joined by their
texts alone.  Extra columns are ignored; empty tables give no rows.
"""

from __future__ import annotations

import gc
import hashlib
import re
import time
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .components import components
from .shared import materialise, open_fs, shared_dir, small_batches

SLOTS = 1 << 14
UNIT_SHINGLES = 1 << 19
MOST_TURNS = 4
_draws: dict[tuple, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}


def shingles(block: K.Block, width: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hashes, row of each, text key of each row); rows shorter than the width have one shingle."""
    words = K.words_of(block)
    values = words.hashes(block)
    keys = K.signed(K.row_hashes(values, words.first))
    h, inside = K.grams(values, words.first, width)
    at = np.flatnonzero(inside)
    row = np.searchsorted(words.first, at, side="right") - 1
    sizes = np.diff(words.first)
    short = np.flatnonzero((sizes > 0) & (sizes < width))
    if len(short):
        h, row = np.concatenate([h[at], K.mix(keys[short].view(np.uint64))]), np.concatenate([row, short])
        order = np.argsort(row, kind="stable")
        return h[order], row[order], keys
    return h[at], row, keys


def distinct_in_rows(h: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, row, count) of each distinct shingle of each row, by row and hash."""
    order = np.lexsort((h, row))
    h, row = h[order], row[order]
    new = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (row[1:] != row[:-1])])) if len(h) else np.zeros(0, np.int64)
    return h[new], row[new], np.diff(np.concatenate([new, [len(h)]]))


def _texts(docs: DataFrame) -> DataFrame:
    return docs.where("doc_id is not null and text is not null").select(F.col("doc_id").cast("long"), "text")


def _release(spark) -> None:
    """Spark drops the shuffle files of plans that are done when the driver collects garbage: Python's
    hold on them, then Java's, which takes some turns."""
    gc.collect()
    for _ in range(4):
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.25)


def _settled(docs: DataFrame) -> DataFrame:
    """docs, written out unless its plan only reads files: two readings must give equal batches."""
    docs = docs.select("doc_id", "text")
    plan = docs._jdf.queryExecution().executedPlan().toString()
    nodes = {re.sub(r"^[\s:+*()\d-]*", "", line).split(" ")[0].split("(")[0] for line in plan.splitlines() if line.strip()}
    return docs if nodes <= {"FileScan", "Project", "Filter", "ColumnarToRow", "Union"} else materialise(docs, "documents")


def _units(batch: pa.RecordBatch, keep: bool, most: int = UNIT_SHINGLES):
    """Consecutive blocks of texts with about ``most`` shingles: for each such unit (hash, row, count and
    text keys of each block if they are to be kept, the unit's distinct shingles, in how many of its texts, its name)."""
    blocks, held, size, name = [], [], 0, hashlib.blake2b(digest_size=8)

    def unit():
        own, n = np.unique(np.concatenate(held), return_counts=True)
        return blocks, own, n.astype(np.uint32), int.from_bytes(name.digest(), "little", signed=True)

    for block in K.text_blocks(batch.column(0)):
        h, row, keys = shingles(block)
        h, row, counts = distinct_in_rows(h, row)
        name.update(keys.tobytes())
        held.append(h)
        size += len(h)
        if keep:
            blocks.append((h, row, counts, keys))
        if size >= most:
            yield unit()
            blocks, held, size, name = [], [], 0, hashlib.blake2b(digest_size=8)
    if size:
        yield unit()


def document_frequencies(docs: DataFrame, words: int, bucket_rows: int = 1 << 21) -> str:
    """A folder with one file for each unit of texts: the document frequencies of its distinct shingles,
    by hash.  Hashes travel in ``bucket_rows`` or so a group and without their highest byte, which the
    bucket tells."""
    spark = docs.sparkSession
    bits = min(max(8, (words // bucket_rows).bit_length()), 20)
    folder = shared_dir(spark, "frequencies")

    def deal(batches):
        for batch in batches:
            for _, own, n, name in _units(batch, keep=False):
                bucket, start = np.unique((own >> np.uint64(64 - bits)).astype(np.int32), return_index=True)
                parts = [slice(x, y) for x, y in zip(start, [*start[1:], len(own)])]
                raw = own.view(np.uint8).reshape(-1, 8)[:, :7]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(bucket), name)), pa.array(bucket), pa.array([raw[p].tobytes() for p in parts], pa.binary()), pa.array([n[p].tobytes() for p in parts], pa.binary())], ["unit", "bucket", "hashes", "n"])

    def add_up(dealt: pa.Table) -> pa.Table:
        raw = dealt.column("hashes").to_pylist()
        h = np.zeros((sum(map(len, raw)) // 7, 8), np.uint8)
        h[:, :7] = np.frombuffer(b"".join(raw), np.uint8).reshape(-1, 7)
        order = np.argsort(h := h.view("<u8")[:, 0], kind="stable")
        new = np.concatenate([[True], np.diff(h[order]) != 0])
        sums = np.add.reduceat(np.frombuffer(b"".join(dealt.column("n").to_pylist()), np.uint32)[order].astype(np.int64), np.flatnonzero(new))
        df = np.empty(len(h), np.uint32)
        df[order] = sums[np.cumsum(new) - 1]
        ends = np.cumsum([len(x) // 7 for x in raw])
        return pa.table([dealt.column("unit"), dealt.column("bucket"), pa.array([df[x:y].tobytes() for x, y in zip([0, *ends], ends)], pa.binary())], names=["unit", "bucket", "df"])

    def write(counted: pa.Table) -> pa.Table:
        at = dict(zip(counted.column("bucket").to_pylist(), counted.column("df").to_pylist()))  # equal units: one of each
        name, raw = counted.column("unit")[0].as_py(), b"".join(at[x] for x in sorted(at))
        fs, path = open_fs(folder)
        fs.create_dir(path, recursive=True)
        part = f"{path}/part-{uuid.uuid4().hex}"
        with fs.open_output_stream(part) as f:
            f.write(len(raw).to_bytes(8, "little") + pa.compress(raw, "zstd", asbytes=True))
        fs.move(part, f"{path}/{name}")
        return pa.table([pa.array([len(raw) // 4], pa.int64())], names=["n"])

    dealt = _texts(docs).select("text").mapInArrow(deal, "unit long, bucket int, hashes binary, n binary")
    counted = dealt.groupBy("bucket").applyInArrow(add_up, "unit long, bucket int, df binary")
    counted.groupBy("unit").applyInArrow(write, "n long").agg(F.sum("n")).collect()
    return folder


def _frequencies_of(folder: str, name: int) -> np.ndarray:
    fs, path = open_fs(folder)
    try:
        with fs.open_input_stream(f"{path}/{name}") as f:
            raw = f.read()
    except FileNotFoundError:
        raise ValueError("the texts came in another order when they were read again") from None
    return np.frombuffer(pa.decompress(raw[8:], int.from_bytes(raw[:8], "little"), "zstd", asbytes=True), np.uint32)


def _tables(samples: int, seed: int):
    """Gamma(2,1) draws for r and ln c and uniform ones for beta, by slot and sample."""
    if (samples, seed) not in _draws:
        rng = np.random.default_rng(seed)
        r = rng.standard_gamma(2.0, (SLOTS, samples)).astype(np.float32)
        c = np.log(rng.standard_gamma(2.0, (SLOTS, samples))).astype(np.float32)
        _draws[samples, seed] = np.maximum(r, np.float32(1e-6)), c, rng.random((SLOTS, samples), np.float32)
    return _draws[samples, seed]


def consistent_samples(h: np.ndarray, weights: np.ndarray, first: np.ndarray, samples: int = 64, seed: int = 5, chunk: int = 8192) -> np.ndarray:
    """Hashes of the (shingle, level) that each row samples, rows x samples.

    r, c and beta of a shingle are table rows picked by three separate parts of its hash."""
    r_of, c_of, b_of = _tables(samples, seed)
    n_rows = len(first) - 1
    best = np.full((n_rows, samples), np.inf, np.float32)
    shingle = np.zeros((n_rows, samples), np.uint64)
    level = np.zeros((n_rows, samples), np.float32)
    columns = np.arange(samples)
    lnw = np.log(weights).astype(np.float32)
    slot = [((h >> np.uint64(s)) & np.uint64(SLOTS - 1)).astype(np.int64) for s in (0, 16, 32)]
    for lo in range(0, len(h), chunk):
        hi = min(lo + chunk, len(h))
        r, beta = r_of[slot[0][lo:hi]], b_of[slot[2][lo:hi]]
        t = lnw[lo:hi, None] / r
        t += beta
        np.floor(t, out=t)
        a = t - beta
        a += np.float32(1)
        a *= -r
        a += c_of[slot[1][lo:hi]]  # ln c - r (t - beta) - r
        for row in range(int(np.searchsorted(first, lo, side="right")) - 1, int(np.searchsorted(first, hi, side="left"))):
            s, e = max(first[row], lo) - lo, min(first[row + 1], hi) - lo
            if e <= s:
                continue
            at = a[s:e].argmin(0) + s
            value = a[at, columns]
            better = value < best[row]
            best[row, better] = value[better]
            shingle[row, better] = h[lo + at[better]]
            level[row, better] = t[at[better], columns[better]]
    return K.mix(shingle ^ K.mix(level.astype(np.int64).view(np.uint64) + np.uint64(1)))


def signatures(docs: DataFrame, folder: str, total: int, bands: int, rows: int, seed: int) -> DataFrame:
    """Of every text with words: key, samples (two bytes each), bands (one hash each), shingles (four
    bytes each, sorted) and their weights (four bytes each)."""

    def run(batches):
        for batch in batches:
            for blocks, own, _, name in _units(batch, keep=True):
                idf = np.log1p(total / _frequencies_of(folder, name))
                for h, row, counts, keys in blocks:
                    present, start = np.unique(row, return_index=True)
                    _, one = np.unique(keys[present], return_index=True)  # each text once
                    if not len(present):
                        continue
                    first = np.concatenate([start, [len(h)]])
                    if len(one) < len(present):
                        one = np.sort(one)
                        take = K.concat_ranges(first[one], np.diff(first)[one])
                        h, counts = h[take], counts[take]
                        first = np.concatenate([[0], np.cumsum(np.diff(first)[one])])
                        present = present[one]
                    weights = idf[np.searchsorted(own, h)] * counts
                    s = consistent_samples(h, weights, first, bands * rows, seed)
                    mixed = s.reshape(len(present), bands, rows)
                    key = np.full((len(present), bands), 0, np.uint64) + np.arange(bands, dtype=np.uint64)
                    for k in range(rows):
                        key = K.mix(key * np.uint64(K.BASES[0]) + mixed[:, :, k])
                    small, weights = (h >> np.uint64(32)).astype(np.uint32), weights.astype(np.float32)
                    parts = [slice(x, y) for x, y in zip(first[:-1], first[1:])]
                    samples = [x.tobytes() for x in (s >> np.uint64(48)).astype(np.uint16)]
                    yield pa.RecordBatch.from_arrays([pa.array(keys[present]), pa.array(samples, pa.binary()), pa.array(list(K.signed(key)), pa.list_(pa.int64())), pa.array([small[p].tobytes() for p in parts], pa.binary()), pa.array([weights[p].tobytes() for p in parts], pa.binary())], ["key", "samples", "bands", "shingles", "weights"])

    return _texts(docs).select("text").mapInArrow(run, "key long, samples binary, bands array<long>, shingles binary, weights binary")


def text_keys(docs: DataFrame) -> DataFrame:
    """doc_id, the hash of the text's words (null without any) and their number; for all rows with a doc_id."""

    def run(batches):
        for batch in batches:
            keys, sizes = [], []
            for block in K.text_blocks(batch.column(1)):
                words = K.words_of(block)
                keys.append(K.signed(K.row_hashes(words.hashes(block), words.first)))
                sizes.append(np.diff(words.first))
            if keys:
                n = np.concatenate(sizes)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(keys), mask=n == 0), pa.array(n.astype(np.int32))], ["doc_id", "key", "words"])

    return docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, key long, words int")


def weighted_jaccard(a: np.ndarray, wa: np.ndarray, b: np.ndarray, wb: np.ndarray) -> float:
    """Of sorted distinct shingles with weights."""
    if not len(a) or not len(b):
        return 0.0
    at = np.minimum(np.searchsorted(b, a), len(b) - 1)
    hit = b[at] == a
    low = float(np.minimum(wa[hit], wb[at[hit]]).sum())
    return low / (float(wa.sum()) + float(wb.sum()) - low)


def verified(pairs: DataFrame, packed: DataFrame, least: float) -> DataFrame:
    """a, b, similarity of the pairs that reach ``least``."""
    left = pairs.join(packed.select(F.col("key").alias("a"), F.col("shingles").alias("sa"), F.col("weights").alias("wa")), "a")
    both = left.join(packed.select(F.col("key").alias("b"), F.col("shingles").alias("sb"), F.col("weights").alias("wb")), "b").select("a", "b", "sa", "wa", "sb", "wb")

    def run(batches):
        for batch in batches:
            a, b = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            raw = [batch.column(c) for c in range(2, 6)]
            got = np.array([weighted_jaccard(*(np.frombuffer(raw[c][i].as_buffer(), t) for c, t in enumerate((np.uint32, np.float32, np.uint32, np.float32)))) for i in range(len(a))])
            ok = got >= least if len(a) else np.zeros(0, bool)
            yield pa.RecordBatch.from_arrays([pa.array(a[ok]), pa.array(b[ok]), pa.array(got[ok], pa.float64())], ["a", "b", "similarity"])

    return both.mapInArrow(run, "a long, b long, similarity double")


def _rest_links(rows: DataFrame, least: float, bands: int, slack: float = 0.3, block: int = 1024) -> DataFrame:
    """rows (band, at, root, key, samples, shingles, weights), sorted by band: links between texts of
    different classes in a bucket.  Blocks of texts are held against each other by their samples;
    pairs that agree in ``least - slack`` of them are verified on the spot (of pairs at exactly 0.8, two in
    a hundred million have fewer of 64 samples in common; two in ten thousand share no band at all), in the first band that both
    texts share only, so that what leaves a bucket is links and not candidates."""

    def links_of(at, root, key, raw, sets):
        samples = np.frombuffer(b"".join(raw), np.uint16).reshape(len(key), -1)
        width = samples.shape[1]
        parent: dict[int, int] = {}

        def top(x):
            while parent.get(x, x) != x:
                x = parent[x]
            return x

        for i in range(0, len(key), block):
            for j in range(i, len(key), block):
                same = np.zeros((len(key[i : i + block]), len(key[j : j + block])), np.uint8)
                for c in range(width):
                    same += samples[i : i + block, c, None] == samples[None, j : j + block, c]
                x, y = np.nonzero((same >= (least - slack) * width) & (root[i : i + block, None] != root[None, j : j + block]))
                agree = same[x, y]
                x, y = x + i, y + j
                if i == j:
                    once = x < y
                    x, y, agree = x[once], y[once], agree[once]
                if not len(x):
                    continue
                shared = (samples[x] == samples[y]).reshape(len(x), bands, -1).all(2).argmax(1) == at
                x, y, agree = x[shared], y[shared], agree[shared]
                a, b = [], []
                for k in np.argsort(agree)[::-1].tolist():
                    p, q = int(x[k]), int(y[k])
                    u, v = top(int(root[p])), top(int(root[q]))
                    if u != v and weighted_jaccard(*sets(p), *sets(q)) >= least:
                        parent[max(u, v)] = min(u, v)
                        a.append(int(key[p]))
                        b.append(int(key[q]))
                if a:
                    yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    def judged(held):
        if len(held) > 1:
            _, at, root, key, raw, shingle, weight = zip(*held)
            sets = lambda i: (np.frombuffer(shingle[i], np.uint32), np.frombuffer(weight[i], np.float32))
            yield from links_of(at[0], np.array(root), np.array(key), raw, sets)

    def run(batches):
        held: list[tuple] = []
        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in range(7))):
                if held and held[-1][0] != row[0]:
                    yield from judged(held)
                    held = []
                held.append(row)
        yield from judged(held)

    return rows.mapInArrow(run, "a long, b long")


def _joined(roots: DataFrame, links: DataFrame) -> DataFrame:
    """roots (node, root) with the classes that links (a, b) connect made one."""
    if not links.limit(1).count():
        return roots
    at = lambda side: roots.select(F.col("node").alias(side), F.col("root").alias(f"r{side}"))
    edges = links.join(at("a"), "a").join(at("b"), "b").select(F.col("ra").alias("a"), F.col("rb").alias("b"))
    merged = components(edges).select(F.col("node").alias("root"), F.col("root").alias("to"))
    return materialise(roots.join(merged, "root", "left").select("node", F.coalesce("to", "root").alias("root")), "roots")


def _apart(pairs: DataFrame, roots: DataFrame) -> DataFrame:
    """Pairs of texts that are not yet of one class."""
    at = lambda side: roots.select(F.col("node").alias(side), F.col("root").alias(f"r{side}"))
    return pairs.join(at("key"), "key").join(at("centre"), "centre").where("rkey <> rcentre").select("key", "centre", "bands")


def near_duplicates(docs: DataFrame, least: float = 0.8, bands: int = 16, rows: int = 4, seed: int = 5) -> DataFrame:
    """doc_id, class_id (the smallest doc_id of its class), class_size; one row for each row."""
    spark = docs.sparkSession
    small_batches(spark)
    docs = _settled(docs)
    keyed = materialise(text_keys(docs), "keys")
    total, words = keyed.agg(F.count("*"), F.coalesce(F.sum("words"), F.lit(0))).first()
    pinned = spark.conf.get("spark.sql.files.minPartitionNum", None)
    spark.conf.set("spark.sql.files.minPartitionNum", pinned or str(spark.sparkContext.defaultParallelism))  # files are split alike, however many executors are left
    try:
        folder = document_frequencies(docs, words)
        _release(spark)
        sets = materialise(signatures(docs, folder, total, bands, rows, seed), "sets")
    finally:
        spark.conf.unset("spark.sql.files.minPartitionNum") if pinned is None else None
    signed = materialise(sets.groupBy("key").agg(F.first("samples").alias("samples"), F.first("bands").alias("bands")), "signatures")
    member = signed.select("key", F.posexplode("bands").alias("at", "band"))
    buckets = member.groupBy("band").agg(F.min("key").alias("one"), F.min(F.xxhash64("key")).alias("two"), F.count("*").alias("n")).where("n > 1")
    crowded = materialise(member.join(buckets, "band").select("band", "at", "key", "one", (F.xxhash64("key") == F.col("two")).alias("is_two")), "members")
    second = crowded.where("is_two").select("band", F.col("key").alias("two")).dropDuplicates(["band"])
    stars = crowded.select("key", F.col("one").alias("centre")).union(crowded.join(second, "band").select("key", "two"))
    shared = stars.where("key <> centre").groupBy("key", "centre").agg(F.count("*").alias("bands"))
    pairs = materialise(shared, "pairs")
    _release(spark)
    # shingle sets of the texts that are in a crowded bucket
    asked = crowded.select("key").distinct()
    packed = materialise(sets.select("key", "shingles", "weights").join(asked, "key", "left_semi").dropDuplicates(["key"]), "shingles")
    _release(spark)
    # each text is held against the centre it shares most bands with; then, again, against the next one
    # that is not yet of its class: a comparison within a class could not change it
    roots = materialise(signed.select(F.col("key").alias("node"), F.col("key").alias("root")), "roots")
    left, turn = pairs, 0
    while turn < MOST_TURNS and left.limit(1).count():
        turn += 1
        best = left.groupBy("key").agg(F.max(F.struct("bands", -F.col("centre"))).alias("m")).select("key", (-F.col("m.col2")).alias("centre")) if turn < MOST_TURNS else left.select("key", "centre")
        best = materialise(best, "best")
        links = materialise(verified(best.select(F.least("key", "centre").alias("a"), F.greatest("key", "centre").alias("b")).distinct(), packed, least), "links")
        roots = _joined(roots, links)
        left = materialise(_apart(left.join(best, ["key", "centre"], "left_anti"), roots), "pairs")
    # buckets that still hold several classes
    known = crowded.select("band", "at", "key").join(roots.select(F.col("node").alias("key"), "root"), "key").select("band", "at", "key", "root")
    split = known.groupBy("band").agg(F.min("root").alias("x"), F.max("root").alias("y")).where("x <> y").select("band")
    rest = known.join(split, "band", "left_semi").join(signed.select("key", "samples"), "key").join(packed, "key").select("band", "at", "root", "key", "samples", "shingles", "weights")
    roots = _joined(roots, materialise(_rest_links(rest.repartition("band").sortWithinPartitions("band"), least, bands), "links"))
    placed = keyed.join(roots.select(F.col("node").alias("key"), "root"), "key", "left").select("doc_id", F.coalesce("root", "key").alias("root"))
    least_id = placed.where("root is not null").groupBy("root").agg(F.min("doc_id").alias("class_id"), F.count("*").alias("class_size"))
    out = placed.join(least_id, "root", "left").select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("class_size", F.lit(1)).alias("class_size"))
    nameless = docs.where("doc_id is null").select(F.lit(None).cast("long").alias("doc_id"), F.lit(None).cast("long").alias("class_id"), F.lit(1).cast("long").alias("class_size"))
    return out.unionByName(nameless)
