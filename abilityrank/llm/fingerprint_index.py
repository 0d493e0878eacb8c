"""Substring dedup with a log-structured index of window fingerprints.

A window is ``window`` consecutive words.  Of every window only its anchor is kept, the run of
``gram`` words inside it with the smallest hash; neighbouring windows mostly share theirs, and equal
windows always do.  A batch of documents becomes a run: its anchors with the hash of the words that
the anchor's windows span and the smallest document, sorted by anchor, never changed afterwards.  A
new batch's run is merge-joined with the earlier runs:

* the same anchor with the same span: all its windows stand earlier;
* the same anchor with other spans: the windows are verified one by one, from the texts;
* otherwise no window is repeated.

``compact`` merges the runs into one, and happens by itself before the ``most_runs``-th run is joined.
After each batch the folder lists the runs and texts that count, so that ``open`` finds the index in
another session.  Indexes opened on one folder may take turns: each judges by the batches that it found and its own, and the
folder lists those of all.  Words are cut from a document if a window covering them
stands in an earlier batch, or in a document of the same batch with a smaller doc_id.

Null texts have no words.  Rows that share a doc_id never cut each other; rows without a doc_id
neither cut nor are cut.  Extra columns are ignored.  Empty tables give no rows.
"""

from __future__ import annotations

import hashlib
import uuid

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .shared import materialise, shared_dir

ANCHORS = "gram long, span long, doc_id long, row_key long, start int, count int"
WINDOWS = "gram long, doc_id long, row_key long, old boolean, start int, windows binary"
CUTS = "doc_id long, row_key long, start int, end int"
LISTS = "version int, window int, gram int, hot int, most_runs int, runs array<string>, texts array<string>"


def _word_values(block: K.Block):
    words = K.words_of(block)
    return words, words.hashes(block, 0), words.hashes(block, 1)


def anchor_rows(docs: DataFrame, window: int, gram: int) -> DataFrame:
    def run(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for block in K.text_blocks(batch.column(1)):
                words, v0, v1 = _word_values(block)
                found = K.anchors(v0, v1, words.first, gram, window)
                if len(found.row):
                    keys = K.signed(K.row_hashes(v1, words.first))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(K.signed(found.gram)), pa.array(K.signed(found.span)), pa.array(ids[block.rows][found.row]), pa.array(keys[found.row]), pa.array(found.start.astype(np.int32)), pa.array(found.count.astype(np.int32))],
                        ["gram", "span", "doc_id", "row_key", "start", "count"],
                    )

    return docs.where("doc_id is not null and text is not null").select(F.col("doc_id").cast("long"), "text").mapInArrow(run, ANCHORS)


def window_rows(docs: DataFrame, window: int, gram: int) -> DataFrame:
    """docs: doc_id, text, wanted anchors, old.  The hashes of each wanted anchor's windows."""

    def run(batches):
        for batch in batches:
            ids, wanted, old = batch.column(0).to_numpy(), batch.column(2), batch.column(3)
            for block in K.text_blocks(batch.column(1)):
                words, v0, v1 = _word_values(block)
                found = K.anchors(v0, v1, words.first, gram, window)
                if not len(found.row):
                    continue
                keys = K.signed(K.row_hashes(v1, words.first))
                each, _ = K.grams(v1, words.first, window, K.BASES[1])
                rows = wanted.slice(block.rows.start, block.rows.stop - block.rows.start)
                asked = rows.flatten().to_numpy()
                asked_row = np.repeat(np.arange(len(rows)), rows.value_lengths().to_numpy())
                pair = lambda row, g: K.mix(g.view(np.uint64) + row.astype(np.uint64) * np.uint64(K.BASES[2]))
                hit = np.flatnonzero(np.isin(pair(found.row, found.gram), pair(asked_row, asked)))
                at = found.start[hit] + words.first[found.row[hit]]
                packed = [each[s : s + n].tobytes() for s, n in zip(at.tolist(), found.count[hit].tolist())]
                row = found.row[hit]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(K.signed(found.gram[hit])), pa.array(ids[block.rows][row]), pa.array(keys[row]), old.slice(block.rows.start, len(rows)).take(pa.array(row)), pa.array(found.start[hit].astype(np.int32)), pa.array(packed, pa.binary())],
                    ["gram", "doc_id", "row_key", "old", "start", "windows"],
                )

    return docs.mapInArrow(run, WINDOWS)


def _ranges(doc, row_key, at, window: int) -> pa.RecordBatch:
    """Cuts for sorted window starts, neighbours joined."""
    new = np.concatenate([[True], (row_key[1:] != row_key[:-1]) | (doc[1:] != doc[:-1]) | (at[1:] != at[:-1] + 1)])
    head = np.flatnonzero(new)
    last = np.concatenate([head[1:] - 1, [len(at) - 1]])
    return pa.RecordBatch.from_arrays([pa.array(doc[head]), pa.array(row_key[head]), pa.array(at[head].astype(np.int32)), pa.array((at[last] + window).astype(np.int32))], ["doc_id", "row_key", "start", "end"])


def repeated_windows(rows: DataFrame, window: int) -> DataFrame:
    """Windows of rows (sorted by anchor) that an earlier row of their anchor has too."""

    def judge(parts):
        gram, doc, key, old, start, packed = (np.concatenate(x) if i < 5 else [y for z in x for y in z] for i, x in enumerate(zip(*parts)))
        sizes = np.array([len(x) // 8 for x in packed])
        each = np.frombuffer(b"".join(packed), np.uint64)
        of = np.repeat(np.arange(len(sizes)), sizes)
        at = np.repeat(start, sizes) + K.concat_ranges(np.zeros(len(sizes), np.int64), sizes)
        _, group = np.unique(K.mix(each + gram[of].view(np.uint64) * np.uint64(K.BASES[2])), return_inverse=True)
        rank = np.where(old, np.int64(-(1 << 63)), doc)  # all earlier batches come first
        least = np.full(group.max() + 1, (1 << 63) - 1, np.int64)
        np.minimum.at(least, group, rank[of])
        hit = np.flatnonzero((rank[of] > least[group]) & ~old[of])
        if len(hit):
            order = hit[np.lexsort((at[hit], key[of[hit]], doc[of[hit]]))]
            yield _ranges(doc[of[order]], key[of[order]], at[order], window)

    def run(batches):
        held, size = [], 0
        for batch in batches:
            columns = [batch.column(c).to_numpy(zero_copy_only=False) for c in range(5)] + [batch.column(5).to_pylist()]
            lo = 0
            gram = columns[0]
            if size >= 20_000:  # whole anchors only: up to where the next one begins
                turn = np.flatnonzero(gram != held[-1][0][-1])
                lo = int(turn[0]) if len(turn) else len(gram)
                held.append([c[:lo] for c in columns])
                size += lo
                if lo < len(gram):
                    yield from judge(held)
                    held, size = [], 0
            if lo < len(gram):
                held.append([c[lo:] for c in columns])
                size += len(gram) - lo
        if held:
            yield from judge(held)

    return rows.mapInArrow(run, CUTS)


def repeated_windows_of_hot_anchors(rows: DataFrame, window: int) -> DataFrame:
    """The same for anchors with very many spans: by window, combined before the shuffle."""

    def explode(batches):
        for batch in batches:
            packed = batch.column(5).to_pylist()
            sizes = np.array([len(x) // 8 for x in packed], np.int64)
            of = pa.array(np.repeat(np.arange(len(sizes)), sizes))
            at = np.repeat(batch.column(4).to_numpy(), sizes) + K.concat_ranges(np.zeros(len(sizes), np.int64), sizes)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(of), pa.array(np.frombuffer(b"".join(packed), np.int64)), batch.column(1).take(of), batch.column(2).take(of), batch.column(3).take(of), pa.array(at.astype(np.int32))], ["gram", "hash", "doc_id", "row_key", "old", "start"])

    one = rows.mapInArrow(explode, "gram long, hash long, doc_id long, row_key long, old boolean, start int")
    rank = F.when(F.col("old"), F.lit(-(1 << 63))).otherwise(F.col("doc_id"))
    least = one.groupBy("gram", "hash").agg(F.min(rank).alias("least"))
    return one.where("not old").join(least, ["gram", "hash"]).where("doc_id > least").select("doc_id", "row_key", "start", (F.col("start") + window).alias("end"))


class FingerprintIndex:
    """Runs in a folder of the cluster's shared storage, with the documents they came from.

    ``keep_texts`` copies each batch's texts into the folder; without it the batches' own tables are
    read again when windows are verified, and the index serves the session that made it only.
    """

    def __init__(self, spark: SparkSession, folder: str | None = None, window: int = 50, gram: int = 20, hot: int = 2_000, keep_texts: bool = True, most_runs: int = 8):
        if not 0 < gram <= window:
            raise ValueError("an anchor lies within a window")
        self.spark, self.window, self.gram, self.hot, self.keep_texts, self.most_runs = spark, window, gram, hot, keep_texts, most_runs
        self.folder = folder or shared_dir(spark, "fingerprints")
        self.runs: list[str] = []
        self.texts: list[DataFrame] = []
        self.kept: list[str] = []
        self.version = 0

    @classmethod
    def open(cls, spark: SparkSession, folder: str) -> "FingerprintIndex":
        """The index as the last finished batch or compaction left it."""
        last = cls._last(spark, folder)
        if last is None:
            raise ValueError(f"{folder} lists no index")
        index = cls(spark, folder, last["window"], last["gram"], last["hot"], True, last["most_runs"])
        index.runs, index.kept, index.version = list(last["runs"]), list(last["texts"]), last["version"]
        index.texts = [spark.read.schema("doc_id long, text string").parquet(x) for x in index.kept]
        return index

    @staticmethod
    def _last(spark: SparkSession, folder: str):
        """The newest list, or None."""
        try:
            return spark.read.schema(LISTS).json(f"{folder}/lists/*").orderBy(F.desc("version")).first()
        except AnalysisException as e:
            if e.getCondition() != "PATH_NOT_FOUND":
                raise

    def _listed(self, run: str, text: str | None = None, merged: list[str] | None = None) -> None:
        """Lists a batch, or a run in the place of those merged into it, beside what others have listed."""
        if not self.keep_texts:
            return
        last = self._last(self.spark, self.folder)
        runs, texts, version = (list(last["runs"]), list(last["texts"]), last["version"]) if last else ([], [], 0)
        if not set(merged or []) <= set(runs):  # another index has merged some of them; its run stays
            return
        runs = [x for x in runs if x not in (merged or [])] + [run]
        texts += [text] if text else []
        self.version = version + 1
        row = (self.version, self.window, self.gram, self.hot, self.most_runs, runs, texts)
        self.spark.createDataFrame([row], LISTS).coalesce(1).write.json(f"{self.folder}/lists/{self.version:06d}")

    def _runs(self) -> DataFrame | None:
        return self.spark.read.parquet(*self.runs) if self.runs else None

    def _write_run(self, run: DataFrame) -> str:
        path = f"{self.folder}/run-{uuid.uuid4().hex[:12]}"
        run.sortWithinPartitions("gram", "span").write.parquet(path)
        return path

    def ingest(self, docs: DataFrame) -> DataFrame:
        """Adds a batch (doc_id, text); returns the word ranges to cut from it as ``CUTS``."""
        if len(self.runs) >= self.most_runs:
            self.compact()
        docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
        if self.keep_texts:
            self.kept.append(f"{self.folder}/texts-{uuid.uuid4().hex[:12]}")
            docs.write.parquet(self.kept[-1])
            docs = self.spark.read.schema(docs.schema).parquet(self.kept[-1])
        mine = materialise(anchor_rows(docs, self.window, self.gram), "anchors")
        run = self._write_run(mine.groupBy("gram", "span").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")))
        new = self.spark.read.parquet(run)
        earlier = self._runs()
        # by anchor: spans of the new run beside those of the earlier ones
        both = new.select("gram", "span", "least", F.lit(False).alias("old"))
        if earlier is not None:
            both = both.unionByName(earlier.join(new.select("gram").distinct(), "gram", "left_semi").select("gram", "span", F.lit(-(1 << 63)).alias("least"), F.col("least").alias("at")).groupBy("gram", "span").agg(F.min("least").alias("least"), F.min("at").alias("at")).select("gram", "span", "least", F.lit(True).alias("old"), "at"), allowMissingColumns=True)
        else:
            both = both.withColumn("at", F.lit(None).cast("long"))
        spans = both.groupBy("gram", "span").agg(F.min("least").alias("least"), F.max("old").alias("old"), F.min("at").alias("at"))
        spans = materialise(spans, "spans")
        mixed = spans.groupBy("gram").agg(F.count("*").alias("n_spans")).where("n_spans > 1")
        whole = mine.join(spans.select("gram", "span", "least"), ["gram", "span"]).where("doc_id > least").select("doc_id", "row_key", "start", (F.col("start") + F.col("count") - 1 + self.window).cast("int").alias("end"))
        # verification: one document for each span of a mixed anchor
        wanted = spans.join(mixed, "gram").select(F.when(F.col("old"), F.col("at")).otherwise(F.col("least")).alias("doc_id"), "old", "gram").groupBy("doc_id", "old").agg(F.collect_set("gram").alias("wanted"))
        texts = docs.withColumn("old", F.lit(False))
        for t in self.texts:
            texts = texts.unionByName(t.withColumn("old", F.lit(True)))
        asked = texts.where("text is not null").join(wanted, ["doc_id", "old"]).select("doc_id", "text", "wanted", "old")
        checked = materialise(window_rows(asked, self.window, self.gram), "windows")
        hot = mixed.where(F.col("n_spans") > self.hot).select("gram")
        usual = checked.join(mixed.where(F.col("n_spans") <= self.hot).select("gram"), "gram", "left_semi").repartition("gram").sortWithinPartitions("gram")
        cuts = whole.unionByName(repeated_windows(usual, self.window)).unionByName(repeated_windows_of_hot_anchors(checked.join(hot, "gram", "left_semi"), self.window))
        cuts = materialise(cuts, "cuts")
        self.runs.append(run)
        self.texts.append(docs)
        self._listed(run, self.kept[-1] if self.keep_texts else None)
        return cuts

    def compact(self) -> None:
        """All runs as one; a span keeps its smallest document."""
        if len(self.runs) > 1:
            merged = self._runs().groupBy("gram", "span").agg(F.min("least").alias("least"), F.sum("n").alias("n"))
            path = f"{self.folder}/compacted-{uuid.uuid4().hex[:12]}"
            merged.sortWithinPartitions("gram", "span").write.parquet(path)
            before, self.runs = self.runs, [path]
            self._listed(path, merged=before)


OUT = "doc_id long, n_words long, n_removed long, kept_sha256 string"


def apply_cuts(docs: DataFrame, cuts: DataFrame, with_text: bool = False, extra: list[str] | None = None) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 and, if asked for, kept_text (the text as it is where
    nothing is cut) and further columns of docs; all of docs' rows."""
    extra = extra or []
    per_doc = cuts.groupBy("doc_id").agg(F.collect_list(F.struct("row_key", "start", "end")).alias("_cuts"))
    joined = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *extra).join(per_doc, "doc_id", "left").select("doc_id", "text", F.col("_cuts.row_key").alias("_k"), F.col("_cuts.start").alias("_s"), F.col("_cuts.end").alias("_e"), *extra)

    def run(batches):
        for batch in batches:
            ids = batch.column(0)
            more = batch.select(extra).columns if extra else []
            for block in K.text_blocks(batch.column(1)):
                lo, n = block.rows.start, block.rows.stop - block.rows.start
                cut = batch.column(2).slice(lo, n)
                any_cut = cut.is_valid().to_pylist()
                null = batch.column(1).slice(lo, n).is_null().to_pylist()
                keys = None
                n_words, n_removed, sha, kept = [], [], [], []
                for i in range(n):
                    words = block.text(i).split()
                    removed = 0
                    if any_cut[i]:
                        if keys is None:
                            w = K.words_of(block)
                            keys = K.signed(K.row_hashes(w.hashes(block, 1), w.first))
                        own = np.array(cut[i].as_py()) == keys[i]
                        s, e = K.merge_intervals(np.array(batch.column(3)[lo + i].as_py())[own], np.array(batch.column(4)[lo + i].as_py())[own])
                        stay, at = [], 0
                        for a, b in zip(s.tolist(), e.tolist()):
                            stay += words[at:a]
                            at = b
                        stay += words[at:]
                        removed = len(words) - len(stay)
                        rest = b" ".join(stay)
                    else:
                        rest = b" ".join(words)
                    n_words.append(len(words))
                    n_removed.append(removed)
                    sha.append(hashlib.sha256(rest).hexdigest())
                    kept.append(None if not with_text or null[i] else rest.decode() if removed else block.text(i).decode())
                yield pa.RecordBatch.from_arrays([ids.slice(lo, n), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(sha, pa.string()), *([pa.array(kept, pa.string())] if with_text else []), *(c.slice(lo, n) for c in more)], ["doc_id", "n_words", "n_removed", "kept_sha256", *(["kept_text"] if with_text else []), *extra])

    return joined.mapInArrow(run, OUT + (", kept_text string" if with_text else "") + "".join(f", `{c}` {docs.schema[c].dataType.simpleString()}" for c in extra))


def dedup_substrings(docs: DataFrame, batches: int = 2, window: int = 50, gram: int = 20, with_text: bool = False, extra: list[str] | None = None) -> DataFrame:
    """The whole table through the index, in batches of ascending doc_id."""
    spark = docs.sparkSession
    whole = docs
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    shares = [k / batches for k in range(1, batches)]
    bounds = (docs.agg(F.percentile_approx("doc_id", shares, 1000)).first()[0] or []) if shares else []
    index = FingerprintIndex(spark, window=window, gram=gram, keep_texts=False)  # the table itself is there
    cuts = None
    edges = [None, *sorted(set(bounds)), None]
    for lo, hi in zip(edges, edges[1:]):
        batch = docs
        if lo is not None:
            batch = batch.where(F.col("doc_id") > lo)
        if hi is not None:
            batch = batch.where(F.col("doc_id") <= hi)
        found = index.ingest(batch)
        cuts = found if cuts is None else cuts.unionByName(found)
    return apply_cuts(whole, cuts, with_text, extra)
