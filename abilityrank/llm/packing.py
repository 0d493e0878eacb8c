"""Vector best-fit packing of documents into fixed-length sequences.

A sequence has three capacities: tokens, documents and attention cost (the sum of squared piece
lengths).  Pieces go from the longest to the shortest; each goes to the open sequence, among those
that still have room under every capacity, that scores best: by the weighted dot product of the
piece's needs and the sequence's residuals, or by the smallest weighted norm of what would be left
of all three.  The usual weights let tokens lead: one token less counts more than all documents and
all cost together, which decide between sequences with the same room for tokens.

Only the histogram of piece lengths is needed to decide: equal lengths are interchangeable, so the
plan handles sequences in classes with equal residuals and moves whole ranges of them at a time.
Its size depends on the sequence length, not on the number of documents.  Pieces then find their
sequence by length and running number.

A null text is an empty one and still has its end id.  Rows that share a doc_id are packed apart.
Every piece is placed; empty tables give no rows.
"""

from __future__ import annotations

import bisect
import itertools
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .encode import PieceEncoder, vocabulary
from .shared import materialise, shared_dir


#: Of tokens, documents and cost in the norm; see ``leads``.
WEIGHTS = (1.0, 1e-8, 1e-8)


def leads(capacities: "Capacities", weights) -> bool:
    """Whether a difference of one token outweighs any difference in documents and cost."""
    return weights[0] / capacities.tokens**2 > weights[1] + weights[2]


@dataclass(frozen=True)
class Capacities:
    tokens: int = 2048
    documents: int | None = None  # none: as many as there are tokens
    cost: int | None = None  # none: one full-length piece

    def vector(self) -> tuple[int, int, int]:
        return self.tokens, self.documents or self.tokens, self.cost or self.tokens**2


def plan(histogram: dict[int, int], capacities: Capacities = Capacities(), rule: str = "norm", weights=WEIGHTS) -> list[tuple[int, int, int, int, int]]:
    """(length, first number, count, first sequence, offset): pieces of a length with those running
    numbers go to consecutive sequences at the offset.

    Where tokens lead, the norm is smallest among the classes with the fewest residual tokens that
    have room, and only those are compared; otherwise all are.
    """
    if rule not in ("norm", "dot"):
        raise ValueError("rule: norm or dot")
    full = capacities.vector()
    # class: residual vector -> ranges (first sequence, count); classes in order of residual tokens
    classes: dict[tuple[int, int, int], list[list[int]]] = {}
    order: list[tuple[int, int, int]] = []
    out, opened = [], 0
    first_by_tokens = rule == "norm" and leads(capacities, weights)
    w = np.array(weights)

    def put(residual, start, count):
        if residual not in classes:
            classes[residual] = []
            bisect.insort(order, residual)
        classes[residual].append([start, count])

    def best(need):
        at = bisect.bisect_left(order, (need[0], -1, -1))
        if first_by_tokens:
            fits = []
            for r in itertools.islice(order, at, None):
                if fits and r[0] > fits[0][0]:
                    break
                if r[1] >= need[1] and r[2] >= need[2]:
                    fits.append(r)
        else:
            fits = [r for r in order[at:] if r[1] >= need[1] and r[2] >= need[2]]
        if len(fits) < 2:
            return fits[0] if fits else None
        left, wants = np.array(fits) / full, np.array(need) / full
        score = ((left - wants) ** 2 * w).sum(1) if rule == "norm" else -(left * wants * w).sum(1)
        return fits[int(score.argmin())]

    for length in sorted(histogram, reverse=True):
        need, number, left = (length, 1, length * length), 0, histogram[length]
        if any(a > b for a, b in zip(need, full)):
            raise ValueError(f"a piece of {length} tokens exceeds a sequence's capacities")
        while left:
            residual = best(need)
            if residual is None:  # as many as are filled with this length alone are opened together
                fit = max(1, min(full[0] // length, full[1], full[2] // (length * length)))
                count = -(-left // fit)
                put(full, opened, count)
                opened += count
                continue
            ranges = classes[residual]
            start, have = ranges[-1]
            count = min(have, left)
            if count == have:
                ranges.pop()
                if not ranges:
                    del classes[residual]
                    order.remove(residual)
            else:
                ranges[-1][1] -= count
                start += have - count
            out.append((length, number, count, start, full[0] - residual[0]))
            number += count
            left -= count
            after = tuple(a - b for a, b in zip(residual, need))
            if after[0] > 0:
                put(after, start, count)
    return out


def encode_pieces(df: DataFrame, most: int, tokenizer: str | None = None, end_id: int = 0) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, task: each document's ids and end id, cut at ``most``."""
    path = tokenizer or vocabulary("word_bpe_49k.json")

    def run(batches):
        from pyspark import TaskContext

        task = TaskContext.get().partitionId()
        encoder = PieceEncoder.get(path, False)
        end = np.array([end_id], encoder.dtype).tobytes()
        number: dict[int, int] = {}
        for batch in batches:
            doc, texts = batch.column(0), batch.column(1)
            for lo in range(0, len(texts), 256):
                at, piece, start, length, crc, order = [], [], [], [], [], []
                for i, raw in enumerate(encoder.payloads([t or "" for t in texts.slice(lo, 256).to_pylist()])):
                    ids = np.frombuffer(raw + end, encoder.dtype)
                    for k, s in enumerate(range(0, len(ids), most)):
                        part = ids[s : s + most]
                        at.append(lo + i)
                        piece.append(k)
                        start.append(s)
                        length.append(len(part))
                        crc.append(zlib.crc32(part.astype("<u4").tobytes()))
                        order.append(number.setdefault(len(part), 0))
                        number[len(part)] += 1
                yield pa.RecordBatch.from_arrays(
                    [doc.take(pa.array(at, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()), pa.array([task] * len(at), pa.int32()), pa.array(order, pa.int64())],
                    ["doc_id", "piece", "start", "length", "ids_crc32", "task", "order"],
                )

    return df.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, task int, order long")


def pack(df: DataFrame, capacities: Capacities = Capacities(), tokenizer: str | None = None, end_id: int = 0, rule: str = "norm", weights=WEIGHTS) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    spark = df.sparkSession
    pieces = materialise(encode_pieces(df, capacities.tokens, tokenizer, end_id), "pieces")
    counts = materialise(pieces.groupBy("length", "task").agg(F.count("*").alias("n")), "lengths")
    # at most one row for each length: bounded by the sequence length
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    moves = plan(histogram, capacities, rule, weights)
    before = counts.select("length", "task", (F.sum("n").over(Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")).alias("before"))
    # numbers within a length: those of earlier tasks, then the order within the task
    by_length: dict[int, np.ndarray] = {}
    for length in histogram:
        by_length[length] = np.array([m[1:] for m in moves if m[0] == length], np.int64).reshape(-1, 4) if len(moves) < 20_000 else None
    if len(moves) >= 20_000:
        table = np.array(moves, np.int64)
        table = table[np.lexsort((table[:, 1], table[:, 0]))]
        cut = np.flatnonzero(np.diff(table[:, 0])) + 1
        by_length = {int(x[0, 0]): x[:, 1:] for x in np.split(table, cut)}
    sent = spark.sparkContext.broadcast({k: v[np.argsort(v[:, 0])] for k, v in by_length.items()})  # bounded: see the module's text

    def place(batches):
        for batch in batches:
            length, number = batch.column(3).to_numpy(), batch.column(5).to_numpy() + batch.column(6).to_numpy()
            sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            for x in np.unique(length):
                at = np.flatnonzero(length == x)
                moved = sent.value[int(x)]
                k = np.searchsorted(moved[:, 0], number[at], side="right") - 1
                sequence[at] = moved[k, 2] + number[at] - moved[k, 0]
                offset[at] = moved[k, 3]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in range(5)), pa.array(sequence), pa.array(offset)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    joined = pieces.join(before, ["length", "task"]).select("doc_id", "piece", "start", "length", "ids_crc32", "order", "before")
    return joined.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
