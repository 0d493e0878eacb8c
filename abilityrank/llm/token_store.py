"""Token-id shards with a minimal perfect hash index from document keys to places in them.

Layout under a folder: ``shard/<name>.ids`` holds raw little-endian ids and nothing else, in
ascending key order; ``index/<name>.mph`` holds one hash partition of the index; two small Parquet
tables, written by Spark, list the shards and index files that count, so files of failed or
repeated task attempts are never read.

An index partition is a cascade of bit arrays: each key falls, under one seed a level, on a bit
that no other key of its level has; the rank of that bit is the key's slot.  A slot stores a 32-bit
fingerprint of its key and its places (shard, offset, tokens), so a lookup is a few probes whatever
the number of keys, and a key that was never stored is refused.

A null text is stored as an empty one.  Rows that share a key keep all their places, in order; a
null key is stored first and looked up as one.  Empty tables give no shards and no rows.
"""

from __future__ import annotations

import json
import struct
import uuid
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .encode import PieceEncoder, vocabulary
from .kernels import concat_ranges, mix
from .shared import open_fs

NULL_KEY = -(1 << 63)
#: Pieces whose ids a worker keeps: some hundred bytes each.
STORED_PIECES = 2_000_000


def _level_bits(keys: np.ndarray, level: int, size: int) -> np.ndarray:
    return (mix(keys ^ np.uint64((level + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1)) % np.uint64(size)).astype(np.int64)


class PerfectHash:
    """Distinct 64-bit keys to slots 0..n-1."""

    def __init__(self, levels: list[np.ndarray], ranks: list[np.ndarray], sizes: list[int]):
        self.levels, self.ranks, self.sizes = levels, ranks, sizes

    @classmethod
    def build(cls, keys: np.ndarray, gamma: float = 2.0) -> "PerfectHash":
        levels, sizes, left, level = [], [], keys.astype(np.uint64), 0
        while len(left):
            size = max(64, -(-int(gamma * len(left)) // 64) * 64)
            bit = _level_bits(left, level, size)
            alone = np.bincount(bit, minlength=size) == 1
            levels.append(np.packbits(alone, bitorder="little"))
            sizes.append(size)
            left = left[~alone[bit]]
            level += 1
        return cls(levels, cls._ranks(levels), sizes)

    @staticmethod
    def _ranks(levels: list[np.ndarray]) -> list[np.ndarray]:
        """Set bits before each byte, over all levels."""
        out, before = [], 0
        for bits in levels:
            ones = np.bitwise_count(bits).astype(np.int64)
            out.append(before + np.cumsum(ones) - ones)
            before += int(ones.sum())
        return out

    def slots(self, keys: np.ndarray) -> np.ndarray:
        """-1 where no level has a bit for the key."""
        keys = keys.astype(np.uint64)
        out = np.full(len(keys), -1, np.int64)
        left = np.arange(len(keys))
        for level, (bits, ranks, size) in enumerate(zip(self.levels, self.ranks, self.sizes)):
            if not len(left):
                break
            bit = _level_bits(keys[left], level, size)
            byte = bits[bit >> 3]
            hit = (byte >> (bit & 7).astype(np.uint8)) & 1 == 1
            below = byte & ((np.uint8(1) << (bit & 7).astype(np.uint8)) - np.uint8(1))
            out[left[hit]] = (ranks[bit >> 3] + np.bitwise_count(below))[hit]
            left = left[~hit]
        return out


def fingerprints(keys: np.ndarray) -> np.ndarray:
    return (mix(keys.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(32)).astype(np.uint32)


@dataclass
class IndexPart:
    hash: PerfectHash
    prints: np.ndarray
    first: np.ndarray  # of each slot, its first place; one more at the end
    places: np.ndarray  # shard, offset in tokens, tokens

    @classmethod
    def build(cls, keys: np.ndarray, shard: np.ndarray, offset: np.ndarray, tokens: np.ndarray) -> "IndexPart":
        unique, where, counts = np.unique(keys, return_inverse=True, return_counts=True)
        found = PerfectHash.build(unique.view(np.uint64))
        slot = found.slots(unique.view(np.uint64))
        order = np.lexsort((offset, shard, slot[where]))
        per_slot = np.zeros(len(unique), np.int64)
        per_slot[slot] = counts
        prints = np.zeros(len(unique), np.uint32)
        prints[slot] = fingerprints(unique.view(np.uint64))
        return cls(found, prints, np.concatenate([[0], np.cumsum(per_slot)]), np.stack([shard, offset, tokens], 1)[order].astype(np.int64))

    def to_bytes(self) -> bytes:
        parts = [*self.hash.levels, self.prints, self.first.astype(np.int64), self.places]
        head = json.dumps({"sizes": self.hash.sizes, "bytes": [p.nbytes for p in parts]}).encode()
        return struct.pack("<4sI", b"MPH1", len(head)) + head + b"".join(np.ascontiguousarray(p).tobytes() for p in parts)

    @classmethod
    def from_bytes(cls, raw: bytes) -> "IndexPart":
        magic, n = struct.unpack_from("<4sI", raw)
        if magic != b"MPH1":
            raise ValueError("not an index file")
        head, at, parts = json.loads(raw[8 : 8 + n]), 8 + n, []
        for size in head["bytes"]:
            parts.append(np.frombuffer(raw, np.uint8, size, at))
            at += size
        levels = parts[:-3]
        return cls(PerfectHash(levels, PerfectHash._ranks(levels), head["sizes"]), parts[-3].view(np.uint32), parts[-2].view(np.int64), parts[-1].view(np.int64).reshape(-1, 3))

    def lookup(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index of the key asked, place row) of each place found."""
        slot = self.hash.slots(keys.view(np.uint64))
        ok = np.flatnonzero(slot >= 0)
        ok = ok[self.prints[slot[ok]] == fingerprints(keys.view(np.uint64)[ok])]
        n = self.first[slot[ok] + 1] - self.first[slot[ok]]
        return np.repeat(ok, n), concat_ranges(self.first[slot[ok]], n)


def _put(folder: str, kind: str, suffix: str, chunks) -> str:
    fs, path = open_fs(folder)
    fs.create_dir(f"{path}/{kind}", recursive=True)
    name = f"{kind}/{uuid.uuid4().hex}{suffix}"  # another name at each attempt
    with fs.open_output_stream(f"{path}/{name}") as f:
        for x in chunks:
            f.write(x)
    return name


def _part_of(key, parts: int):
    return F.pmod(F.xxhash64(key), F.lit(parts)).cast("int")


class TokenStore:
    """Written with ``write``; ``open`` finds one that is there."""

    def __init__(self, spark: SparkSession, folder: str, dtype: str, parts: int):
        self.spark, self.folder, self.dtype, self.parts = spark, folder, dtype, parts

    @property
    def shards(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.folder}/shards")

    @classmethod
    def open(cls, spark: SparkSession, folder: str) -> "TokenStore":
        head = spark.read.json(f"{folder}/head").first()
        return cls(spark, folder, head["dtype"], head["parts"])

    @classmethod
    def write(cls, df: DataFrame, folder: str, tokenizer: str | None = None, byte_level: bool = True, end_id: int | None = 2, shards: int | None = None, parts: int | None = None) -> "TokenStore":
        """df: doc_id and text.  Shards are ranges of keys; equal keys may span two."""
        spark = df.sparkSession
        path = tokenizer or vocabulary("byte_bpe_50k.json")
        dtype = np.dtype(PieceEncoder.get(path, byte_level).dtype).name
        shards = shards or int(spark.conf.get("spark.sql.shuffle.partitions"))
        parts = parts or max(1, shards // 4)
        ranged = df.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_KEY)).alias("key"), F.coalesce("text", F.lit("")).alias("text")).repartitionByRange(shards, "key").sortWithinPartitions("key", F.xxhash64("text"))

        def encode(batches):
            encoder = PieceEncoder.get(path, byte_level, STORED_PIECES)
            end = b"" if end_id is None else np.array([end_id], encoder.dtype).tobytes()
            width = np.dtype(encoder.dtype).itemsize
            keys, sizes = [], []

            def chunks():
                for batch in batches:
                    keys.append(batch.column(0).to_numpy())
                    texts = batch.column(1)
                    for lo in range(0, len(texts), 256):
                        for raw in encoder.payloads(texts.slice(lo, 256).to_pylist()):
                            raw += end
                            sizes.append(len(raw) // width)
                            yield raw

            stream = chunks()
            head = next(stream, None)
            if head is None:
                return
            name = _put(folder, "shard", ".ids", (x for part in ([head], stream) for x in part))
            n, key = np.array(sizes, np.int64), np.concatenate(keys)
            offset = np.cumsum(n) - n
            size = 65536
            for lo in range(0, len(n), size):
                k = slice(lo, lo + size)
                m = len(n[k])
                yield pa.RecordBatch.from_arrays([pa.array([name] * m), pa.array(key[k]), pa.array(offset[k]), pa.array(n[k])], ["shard", "key", "offset", "n_tokens"])

        placed_path = f"{folder}/placed"
        ranged.mapInArrow(encode, "shard string, key long, offset long, n_tokens long").write.parquet(placed_path)
        placed = spark.read.parquet(placed_path)
        summary = placed.groupBy("shard").agg(F.min("key").alias("first_key"), F.max("key").alias("last_key"), F.count("*").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
        # one row a shard: numbering them and adding up what is before is a small table's work
        rows = sorted(((r["first_key"], r["last_key"], r["shard"], r["n_docs"], r["n_tokens"]) for r in summary.collect()))
        base, out = 0, []
        for i, (lo, hi, name, docs, tokens) in enumerate(rows):
            out.append((i, name, None if lo == NULL_KEY else lo, hi, docs, tokens, base))
            base += tokens
        spark.createDataFrame(out, "shard int, file string, first_key long, last_key long, n_docs long, n_tokens long, start long").coalesce(1).write.parquet(f"{folder}/shards")
        numbered = F.broadcast(spark.read.parquet(f"{folder}/shards").select(F.col("file").alias("shard"), F.col("shard").alias("number")))  # one row a shard file
        rows = placed.join(numbered, "shard").select(_part_of(F.col("key"), parts).alias("part"), "key", "number", "offset", "n_tokens").repartition(parts, "part").sortWithinPartitions("part")

        def index(batches):
            held: dict[int, list] = {}

            def done(part):
                k, s, o, n = (np.concatenate(x) for x in zip(*held.pop(part)))
                built = IndexPart.build(k, s, o, n)
                name = _put(folder, "index", ".mph", [built.to_bytes()])
                return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([name]), pa.array([len(built.prints)])], ["part", "file", "n_keys"])

            for batch in batches:
                part = batch.column(0).to_numpy()
                cut = np.flatnonzero(np.diff(part)) + 1
                for lo, hi in zip([0, *cut], [*cut, len(part)]):
                    if hi == lo:
                        continue
                    for old in [p for p in held if p != part[lo]]:
                        yield done(old)
                    held.setdefault(int(part[lo]), []).append([batch.column(c).to_numpy()[lo:hi] for c in range(1, 5)])
            for old in list(held):
                yield done(old)

        rows.mapInArrow(index, "part int, file string, n_keys long").write.parquet(f"{folder}/parts")
        spark.createDataFrame([(dtype, parts)], "dtype string, parts int").coalesce(1).write.json(f"{folder}/head")
        return cls(spark, folder, dtype, parts)

    def lookup(self, keys: DataFrame, column: str = "doc_id") -> DataFrame:
        """key, shard, offset, n_tokens of every place of every key, by the index."""
        folder, parts = self.folder, self.parts
        files = self.spark.sparkContext.broadcast({r["part"]: r["file"] for r in self.spark.read.parquet(f"{folder}/parts").collect()})  # one entry an index file
        asked = keys.select(F.coalesce(F.col(column).cast("long"), F.lit(NULL_KEY)).alias("key")).distinct().select(_part_of(F.col("key"), parts).alias("part"), "key").repartition(parts, "part").sortWithinPartitions("part")

        def run(batches):
            fs, root = open_fs(folder)
            current, index = None, None
            for batch in batches:
                part, key = batch.column(0).to_numpy(), batch.column(1).to_numpy()
                cut = np.flatnonzero(np.diff(part)) + 1
                for lo, hi in zip([0, *cut], [*cut, len(part)]):
                    if hi == lo or int(part[lo]) not in files.value:
                        continue
                    if current != part[lo]:
                        current = part[lo]
                        with fs.open_input_stream(f"{root}/{files.value[int(current)]}") as f:
                            index = IndexPart.from_bytes(f.read())
                    who, row = index.lookup(key[lo:hi])
                    place = index.places[row]
                    yield pa.RecordBatch.from_arrays([pa.array(key[lo:hi][who]), pa.array(place[:, 0].astype(np.int32)), pa.array(place[:, 1]), pa.array(place[:, 2])], ["key", "shard", "offset", "n_tokens"])

        return asked.mapInArrow(run, "key long, shard int, offset long, n_tokens long")

    def read(self, places: DataFrame, digest: bool = False) -> DataFrame:
        """The ids (or their crc32 as 32-bit integers) at places, read from the shard files."""
        folder, dtype = self.folder, np.dtype(self.dtype)
        shards = self.spark.sparkContext.broadcast({r["shard"]: (r["file"], r["start"]) for r in self.shards.collect()})  # one entry a shard file
        n = max(1, len(shards.value))
        sorted_places = places.select("shard", "offset", "n_tokens", "key").repartitionByRange(n, "shard", "offset").sortWithinPartitions("shard", "offset")
        kind = "ids_crc32 long" if digest else "ids array<int>"

        def run(batches):
            fs, root = open_fs(folder)
            current, f = None, None
            for batch in batches:
                shard, offset, size, key = (batch.column(c).to_numpy() for c in range(4))
                out = []
                for s, o, m in zip(shard.tolist(), offset.tolist(), size.tolist()):
                    if s != current:
                        if f is not None:
                            f.close()
                        current, f = s, fs.open_input_file(f"{root}/{shards.value[s][0]}")
                    ids = np.frombuffer(f.read_at(m * dtype.itemsize, o * dtype.itemsize), dtype)
                    out.append(zlib.crc32(ids.astype("<u4").tobytes()) if digest else ids.astype(np.int32))
                start = np.array([shards.value[s][1] for s in shard.tolist()], np.int64) + offset
                doc = pa.array(key, mask=key == NULL_KEY)
                yield pa.RecordBatch.from_arrays([doc, pa.array(start), pa.array(size), pa.array(out, pa.int64() if digest else pa.list_(pa.int32()))], ["doc_id", "start", "n_tokens", kind.split()[0]])
            if f is not None:
                f.close()

        return sorted_places.mapInArrow(run, f"doc_id long, start long, n_tokens long, {kind}")
