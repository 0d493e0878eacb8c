"""Quality classifier by co-training of a text view and a page-metadata view.

The text view sees what the text is made of (classes of neighbouring characters, hashed words,
repetition); the metadata view sees language, source and length.  Both start from the labelled
sample.  In each round every document outside that sample is scored by both views where it lies, and
those that one view is sure of teach the other, however many there are: the metadata view is fitted
on their counts by language, source and length, which say all it can see of them; the text view is
fitted on blocks of them beside the labelled sample, and the blocks' weights are averaged by their
numbers of documents.  In each class the labelled sample and the documents a view is given have
half of the weight each.  Then each view is calibrated by itself on labelled documents that no round
trained on (a logistic fit of its margin), and the score of every document of the table is the logistic
combination, fitted on the same documents, of the two calibrated views.  Where those have one class only,
the views stay as they are and count alike.

Only the labels that fitting uses are bounded: ``labelled`` rows, the first by a hash of doc_id;
documents whose labels are beyond them are exchanged as unlabelled ones are.  A null or empty text
has the features of no text; null metadata are a value of their own.  Labels that are null or not 0 or 1 are left out;
of several labels of one doc_id the more frequent one counts, and none if they tie.  Without
labels of both classes every document scores 0.5 and is kept.  Rows that repeat a doc_id are scored
apart.  Empty tables give no rows.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K

CLASSES, WORD_BUCKETS, STATISTICS = 10, 1024, 6
TEXT_WIDTH = CLASSES**3 + WORD_BUCKETS + STATISTICS
META_WIDTH = 16 + 64 + 20
_CLASS = np.full(256, 9, np.uint8)  # other ASCII
_CLASS[0x61:0x7B], _CLASS[0x41:0x5B], _CLASS[0x30:0x3A], _CLASS[0x80:] = 0, 1, 2, 3
_CLASS[[0x20, 0x09]], _CLASS[0x0A], _CLASS[[0x2E, 0x2C]], _CLASS[0x21] = 4, 5, 6, 7
_CLASS[[ord(c) for c in "#$%&*|<>"]] = 8


def _per_row(code: np.ndarray, row: np.ndarray, rows: int, width: int) -> np.ndarray:
    return np.bincount(row * width + code, minlength=rows * width).reshape(rows, width).astype(np.float32)


def text_features(block: K.Block) -> np.ndarray:
    """One row of TEXT_WIDTH features for each text."""
    rows = len(block.offsets) - 1
    sizes = np.diff(block.offsets)
    row = np.repeat(np.arange(rows), sizes)
    c = _CLASS[block.data].astype(np.int64)
    if len(c) > 2:
        inside = row[2:] == row[:-2]
        marks = _per_row((c[:-2] * CLASSES + c[1:-1])[inside] * CLASSES + c[2:][inside], row[2:][inside], rows, CLASSES**3)
    else:
        marks = np.zeros((rows, CLASSES**3), np.float32)
    words = K.words_of(block)
    n = np.diff(words.first)
    word_row = np.repeat(np.arange(rows), n)
    h = words.hashes(block)
    bag = _per_row((h >> np.uint64(54)).astype(np.int64), word_row, rows, WORD_BUCKETS)
    some = np.maximum(n, 1)
    again = np.bincount(word_row[1:][(h[1:] == h[:-1]) & (word_row[1:] == word_row[:-1])], minlength=rows) if len(h) > 1 else np.zeros(rows)
    order = np.lexsort((h, word_row))
    same = np.bincount(word_row[order][1:][(h[order][1:] == h[order][:-1]) & (word_row[order][1:] == word_row[order][:-1])], minlength=rows) if len(h) > 1 else np.zeros(rows)
    g, ok = K.grams(h, words.first, 5)
    g, grow = g[ok], word_row[: len(g)][ok]
    order = np.lexsort((g, grow))
    twice = np.bincount(grow[order][1:][(g[order][1:] == g[order][:-1]) & (grow[order][1:] == grow[order][:-1])], minlength=rows) if len(g) > 1 else np.zeros(rows)
    length = np.bincount(word_row, weights=(words.end - words.start), minlength=rows)
    stats = np.stack([np.log1p(n), again / some, same / some, twice / some, length / some / 10, (n == 0).astype(float)], 1)
    marks = np.sqrt(marks / np.maximum(marks.sum(1, keepdims=True), 1))
    return np.concatenate([marks, np.sqrt(bag / some[:, None]), stats], 1).astype(np.float32)


def meta_features(lang: list, source: list, n_chars: list) -> np.ndarray:
    out = np.zeros((len(lang), META_WIDTH), np.float32)
    at = np.arange(len(lang))
    bucket = lambda values, n: [zlib.crc32(str(v).encode()) % n if v is not None else 0 for v in values]
    out[at, bucket(lang, 16)] = 1
    out[at, [16 + b for b in bucket(source, 64)]] = 1
    out[at, [80 + (min(18, max(int(v), 0).bit_length()) if v is not None else 19) for v in n_chars]] = 1
    return out


def fit_logistic(x: np.ndarray, y: np.ndarray, l2: float = 1e-3, rounds: int = 120, rate: float = 0.2, weight: np.ndarray | None = None, start: np.ndarray | None = None) -> np.ndarray:
    """Weights and, last, the intercept; classes count alike."""
    w = np.zeros(x.shape[1] + 1, np.float64) if start is None else start.astype(np.float64)
    m, v = np.zeros_like(w), np.zeros_like(w)
    share = np.ones(len(y)) if weight is None else weight
    share = share * np.where(y == 1, 0.5 / max(share[y == 1].sum(), 1e-9), 0.5 / max(share[y != 1].sum(), 1e-9))
    for t in range(1, rounds + 1):
        p = 1 / (1 + np.exp(-np.clip(x @ w[:-1].astype(x.dtype) + w[-1], -30, 30)))
        e = (p - y) * share
        g = np.concatenate([x.T @ e.astype(x.dtype) + l2 * w[:-1], [e.sum()]])
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        w -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-9)
    return w


def halves(y: np.ndarray, given: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Weights of labelled rows and then of given ones, each half of their class where it has both."""
    weight = np.concatenate([np.ones(len(y)), counts.astype(np.float64)])
    label, own = np.concatenate([y, given]), np.arange(len(weight)) < len(y)
    for c in (0, 1):
        for part in (own, ~own):
            weight[part & (label == c)] /= max(weight[part & (label == c)].sum(), 1e-9)
    return weight


def margin(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return x @ w[:-1].astype(x.dtype) + w[-1]


def sure(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


@dataclass
class CoTrained:
    text: np.ndarray
    meta: np.ndarray
    views: np.ndarray  # of each view's margin, its calibration: slope and intercept
    mixed: np.ndarray  # of the two calibrated margins, and the intercept
    added: tuple[int, int]  # pseudo-labels that the text and metadata views received, of all rounds

    def calibrated(self, text: np.ndarray, meta: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Margins (log-odds) of both views after calibration."""
        return tuple(np.clip(v[0] * np.clip(margin(x, w), -20, 20) + v[1], -20, 20) for x, w, v in ((text, self.text, self.views[0]), (meta, self.meta, self.views[1])))

    def calibrate(self, text: np.ndarray, meta: np.ndarray, y: np.ndarray) -> None:
        """On labelled documents that training has not seen, with both classes."""
        self.views = np.stack([fit_logistic(np.clip(margin(x, w), -20, 20)[:, None], y, l2=1e-2) for x, w in ((text, self.text), (meta, self.meta))])
        self.mixed = fit_logistic(np.stack(self.calibrated(text, meta), 1), y, l2=1e-2)

    def score(self, text: np.ndarray, meta: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        a, b = self.calibrated(text, meta)
        return sure(self.mixed[0] * a + self.mixed[1] * b + self.mixed[2]), sure(a), sure(b)


META = ["lang", "source", "n_chars"]


def _with_meta(docs: DataFrame) -> DataFrame:
    have = set(docs.columns)
    return docs.select("doc_id", "text", *[F.col(c).cast("string" if c != "n_chars" else "long").alias(c) if c in have else F.lit(None).cast("string" if c != "n_chars" else "long").alias(c) for c in META])


def _features(docs: DataFrame) -> DataFrame:
    def run(batches):
        for batch in batches:
            x = [text_features(b) for b in K.text_blocks(batch.column(1))]
            m = meta_features(*(batch.column(c).to_pylist() for c in (2, 3, 4)))
            if x:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r.astype(np.float16).tobytes() for r in np.concatenate(x)], pa.binary()), pa.array([r.tobytes() for r in m], pa.binary())], ["doc_id", "x", "m"])

    return _with_meta(docs).mapInArrow(run, "doc_id long, x binary, m binary")


CELLS = 16 * 64 * 20
BLOCK = 8192  # documents that the text view is fitted on at once, beside the labelled sample


def cells_of(meta: np.ndarray) -> np.ndarray:
    """The number of each row's language, source and length together."""
    return (meta[:, :16].argmax(1) * 64 + meta[:, 16:80].argmax(1)) * 20 + meta[:, 80:].argmax(1)


def cell_features(cell: np.ndarray) -> np.ndarray:
    out, at = np.zeros((len(cell), META_WIDTH), np.float32), np.arange(len(cell))
    out[at, cell // 1280] = out[at, 16 + cell // 20 % 64] = out[at, 80 + cell % 20] = 1
    return out


def exchange(others: DataFrame, x: np.ndarray, y: np.ndarray, text: np.ndarray, meta: np.ndarray, sure: float) -> tuple[np.ndarray, int, np.ndarray]:
    """One round over all rows of ``others``: (text weights, documents the text view was given,
    counts of the documents the metadata view is given by label and cell)."""
    sent = others.sparkSession.sparkContext.broadcast((text, meta, x.astype(np.float16), y))
    row = lambda w, n, counts: pa.RecordBatch.from_arrays([pa.array([w.tobytes()], pa.binary()), pa.array([n], pa.int64()), pa.array([np.flatnonzero(counts).tobytes()], pa.binary()), pa.array([counts[counts > 0].tobytes()], pa.binary())], ["w", "n", "cell", "count"])
    schema = "w binary, n long, cell binary, count binary"

    def run(batches):
        text, meta, own, own_y = sent.value
        summed, n, counts = np.zeros(len(text)), 0, np.zeros(2 * CELLS, np.int64)
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def fitted():
            given = np.concatenate([h[1] for h in held])
            both = np.concatenate([own, *(h[0] for h in held)]).astype(np.float32)
            return len(given) * fit_logistic(both, np.concatenate([own_y, given]), rounds=20, rate=0.05, weight=halves(own_y, given, np.ones(len(given))), start=text), len(given)

        for batch in batches:
            m = meta_features(*(batch.column(c).to_pylist() for c in (2, 3, 4)))
            for block in K.text_blocks(batch.column(1)):
                f, g = text_features(block), m[block.rows]
                a, b = (1 / (1 + np.exp(-np.clip(z, -30, 30))) for z in (margin(f, text), margin(g, meta)))
                told = np.maximum(a, 1 - a) >= sure
                counts += np.bincount(cells_of(g[told]) + CELLS * (a[told] > 0.5), minlength=2 * CELLS)
                told = np.maximum(b, 1 - b) >= sure
                held.append((f[told].astype(np.float16), (b[told] > 0.5).astype(np.float64)))
                if sum(len(h[1]) for h in held) >= BLOCK:
                    w, k = fitted()
                    summed, n, held = summed + w, n + k, []
        if sum(len(h[1]) for h in held):
            w, k = fitted()
            summed, n = summed + w, n + k
        yield row(summed, n, counts)

    def add_up(batches):
        summed, n, counts = np.zeros(len(text)), 0, np.zeros(2 * CELLS, np.int64)
        for batch in batches:
            for w, k, cell, count in zip(*(batch.column(c).to_pylist() for c in range(4))):
                summed, n = summed + np.frombuffer(w), n + k
                counts[np.frombuffer(cell, np.int64)] += np.frombuffer(count, np.int64)
        yield row(summed, n, counts)

    summed, n, counts = np.zeros(len(text)), 0, np.zeros(2 * CELLS, np.int64)
    for r in others.mapInArrow(run, schema).repartition(8).mapInArrow(add_up, schema).collect():  # 8 rows
        summed, n = summed + np.frombuffer(r["w"]), n + r["n"]
        counts[np.frombuffer(r["cell"], np.int64)] += np.frombuffer(r["count"], np.int64)
    return (summed / n if n else text), n, counts


def train(docs: DataFrame, labels: DataFrame, labelled: int = 4_000, label: str = "quality", rounds: int = 4, sure: float = 0.95) -> CoTrained | None:
    each = labels.where(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1)).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y"))
    ids = each.groupBy("doc_id").agg((F.sum("y") * 2 - F.count("*")).alias("lead")).where("lead <> 0").select("doc_id", (F.col("lead") > 0).cast("int").alias("y"))
    docs = docs.withColumn("doc_id", F.col("doc_id").cast("long"))
    known = ids.join(docs.select("doc_id"), "doc_id", "left_semi").orderBy(F.xxhash64("doc_id"), "doc_id", "y").limit(labelled)
    known = docs.sparkSession.createDataFrame(known.collect(), known.schema)  # bounded by ``labelled``
    wanted = F.broadcast(known.select("doc_id").distinct())
    found = _features(docs.join(wanted, "doc_id", "left_semi")).toArrow()
    if not found.num_rows:
        return None
    x = np.frombuffer(b"".join(found.column("x").to_pylist()), np.float16).reshape(-1, TEXT_WIDTH).astype(np.float32)
    m = np.frombuffer(b"".join(found.column("m").to_pylist()), np.float32).reshape(-1, META_WIDTH)
    doc = found.column("doc_id").to_numpy()
    order = np.argsort(doc, kind="stable")
    doc, x, m = doc[order], x[order], m[order]
    y_of = {r["doc_id"]: r["y"] for r in known.collect()}
    y = np.array([y_of[d] for d in doc.tolist()])
    held = K.mix(doc.view(np.uint64)) % np.uint64(4) == 0
    if len(set(y[~held].tolist())) < 2:
        return None
    own_x, own_m, own_y = x[~held], m[~held], y[~held].astype(np.float64)
    text, meta, added = fit_logistic(own_x, own_y), fit_logistic(own_m, own_y), [0, 0]
    others = _with_meta(docs.join(wanted, "doc_id", "left_anti"))
    for _ in range(rounds):
        text, n, counts = exchange(others, own_x, own_y, text, meta, sure)
        at = np.flatnonzero(counts)
        given = (at >= CELLS).astype(np.float64)
        meta = fit_logistic(np.concatenate([own_m, cell_features(at % CELLS)]), np.concatenate([own_y, given]), weight=halves(own_y, given, counts[at]))
        added = [added[0] + n, added[1] + int(counts.sum())]
    model = CoTrained(text, meta, np.array([[1.0, 0.0], [1.0, 0.0]]), np.array([0.5, 0.5, 0.0]), (added[0], added[1]))
    if len(set(y[held].tolist())) == 2:
        model.calibrate(x[held], m[held], y[held].astype(np.float64))
    return model


def _scored(batch: pa.RecordBatch, model: CoTrained | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    text, meta = batch.column(batch.schema.names.index("text")), [batch.column(batch.schema.names.index(c)).to_pylist() for c in META]
    n = batch.num_rows
    out = np.full((3, n), 0.5)
    if model is not None:
        m = meta_features(*meta)
        for block in K.text_blocks(text):
            out[:, block.rows] = model.score(text_features(block), m[block.rows])
    return out[0], out[1], out[2]


def score_documents(docs: DataFrame, labels: DataFrame, keep_from: float = 0.3, **options) -> DataFrame:
    """doc_id, score, text_score, meta_score, kept for every row."""
    model = train(docs, labels, **options)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            score, a, b = _scored(batch, sent.value)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score), pa.array(a), pa.array(b), pa.array(score >= keep_from)], ["doc_id", "score", "text_score", "meta_score", "kept"])

    return _with_meta(docs.withColumn("doc_id", F.col("doc_id").cast("long"))).mapInArrow(run, "doc_id long, score double, text_score double, meta_score double, kept boolean")


def keep_good(docs: DataFrame, labels: DataFrame, keep_from: float = 0.3, **options) -> DataFrame:
    """The rows of docs (with all of its columns) that the classifier does not reject."""
    model = train(docs, labels, **options)
    sent = docs.sparkSession.sparkContext.broadcast(model)
    full = docs
    for c in META:
        if c not in docs.columns:
            full = full.withColumn(c, F.lit(None).cast("string"))
    names = docs.columns

    def run(batches):
        for batch in batches:
            keep = pa.array(_scored(batch, sent.value)[0] >= keep_from)
            yield batch.select(names).filter(keep)

    return full.mapInArrow(run, docs.schema)
