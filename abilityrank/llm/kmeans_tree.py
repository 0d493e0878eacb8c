"""Nearest neighbours by cosine with a hierarchical k-means tree and best-bin-first search.

The tree is fitted on a bounded sample (``sample`` rows by hash of the id) and is small enough to
send everywhere: at most about ``sample / least_leaf`` leaves.  Every valid vector is put in a leaf.
A query walks the tree through a priority queue of unexplored branches, nearest centre first, and
so orders the leaves it would visit.  How many it visits is calibrated: the exact neighbours of a
bounded set of queries are found by brute force over the whole table, and the visits widen until
they would have found the wanted share.  Any query goes on until it has seen k other vectors.

The two nearest leaves meet their queries in tiles of bounded numbers of vectors and queries, so that
neither a leaf nor a query crowd is ever gathered in one task.  The further leaves, which may be most
of them, are not joined with queries: each task holds a bounded chunk of vectors in the order of their
leaves and reads the queries, one row each with the set of leaves it visits, from the shared folder in
blocks.  Of exact copies of a vector only the k + 1 smallest ids travel: no query can return more.

Vectors that are null, of another length than the sample's most frequent one, zero, or that hold
nulls or non-finite values take no part; neither do rows without an id.  Rows that share an id are
one candidate each.  Empty tables give no rows.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import kernels as K
from .shared import materialise, open_fs, shared_dir


@dataclass
class Tree:
    centres: np.ndarray  # one row a node, unit length
    children: list[np.ndarray]  # empty for leaves
    leaf: np.ndarray  # number of each leaf node, -1 for others
    n_leaves: int

    @classmethod
    def fit(cls, vectors: np.ndarray, branching: int = 8, leaf_rows: int = 32, rounds: int = 8, seed: int = 7) -> "Tree":
        """vectors: unit rows of the sample."""
        rng = np.random.default_rng(seed)
        centres, children, leaf = [vectors.mean(0) if len(vectors) else np.zeros(1)], [np.zeros(0, np.int64)], [-1]
        todo, n = [(0, np.arange(len(vectors)))], 0
        while todo:
            node, rows = todo.pop()
            parts = _split(vectors[rows], min(branching, -(-len(rows) // leaf_rows)), rounds, rng) if len(rows) > leaf_rows else []
            if len(parts) < 2:
                leaf[node], n = n, n + 1
                continue
            kids = []
            for centre, members in parts:
                kids.append(len(centres))
                centres.append(centre)
                children.append(np.zeros(0, np.int64))
                leaf.append(-1)
                todo.append((kids[-1], rows[members]))
            children[node] = np.array(kids)
        return cls(np.array(centres, np.float64), children, np.array(leaf), n)

    def assign(self, vectors: np.ndarray) -> np.ndarray:
        """The leaf that each vector reaches by the nearest child at every node."""
        out = np.zeros(len(vectors), np.int64)
        todo = [(0, np.arange(len(vectors)))]
        while todo:
            node, rows = todo.pop()
            if not len(self.children[node]):
                out[rows] = self.leaf[node]
                continue
            nearest = (vectors[rows] @ self.centres[self.children[node]].T).argmax(1)
            for k in np.unique(nearest):
                todo.append((self.children[node][k], rows[nearest == k]))
        return out

    def visits(self, far: list[float]):
        """Leaves in best-bin-first order; far has the negated cosine of every node's centre."""
        queue = [(0.0, 0)]
        while queue:
            _, node = heapq.heappop(queue)
            kids = self.children[node]
            if not len(kids):
                yield int(self.leaf[node])
                continue
            for k in kids.tolist():
                heapq.heappush(queue, (far[k], k))

    def far(self, vectors: np.ndarray) -> list[list[float]]:
        return (-(vectors @ self.centres.T)).tolist()


def _split(vectors: np.ndarray, k: int, rounds: int, rng) -> list[tuple[np.ndarray, np.ndarray]]:
    """Spherical k-means; parts that are not empty, with their centres."""
    k = min(k, len(vectors))
    centres = vectors[rng.choice(len(vectors), k, replace=False)]
    for _ in range(rounds):
        own = (vectors @ centres.T).argmax(1)
        sums = np.zeros_like(centres)
        np.add.at(sums, own, vectors)
        norms = np.linalg.norm(sums, axis=1, keepdims=True)
        centres = np.where(norms > 0, sums / np.where(norms > 0, norms, 1), centres)
    own = (vectors @ centres.T).argmax(1)
    return [(centres[i], np.flatnonzero(own == i)) for i in range(k) if (own == i).any()]


def _dense(column: pa.Array, width: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(rows that hold valid vectors, their values as doubles)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    sizes = column.value_lengths().fill_null(0).to_numpy()
    if width is None:
        width = int(np.bincount(sizes[sizes > 0]).argmax()) if (sizes > 0).any() else 0
    rows = np.flatnonzero((sizes == width) & column.is_valid().to_numpy(zero_copy_only=False)) if width else np.zeros(0, np.int64)
    values = column.take(pa.array(rows)).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, max(width, 1))
    ok = np.isfinite(values).all(1) & (values != 0).any(1)
    return rows[ok], values[ok]


def _unit(values: np.ndarray) -> np.ndarray:
    scaled = values / np.abs(values).max(1, keepdims=True)  # no overflow of squares
    return scaled / np.linalg.norm(scaled, axis=1, keepdims=True)


def cosines(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return (a @ b.T) / np.linalg.norm(a, axis=1)[:, None] / np.linalg.norm(b, axis=1)[None, :]


def _best(scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the k largest and of all equal to the last of them."""
    if len(scores) <= k:
        return np.arange(len(scores))
    return np.flatnonzero(scores >= np.partition(scores, len(scores) - k)[len(scores) - k])


def _paired(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The cosine of each row of a with the same row of b, whatever rows stand around them."""
    return (a * b).sum(1) / np.linalg.norm(a, axis=1) / np.linalg.norm(b, axis=1)


def _vectors_of(raw: list[bytes], width: int) -> np.ndarray:
    """As doubles; of four or eight bytes a value."""
    kind = np.float32 if raw and len(raw[0]) == 4 * width else np.float64
    return np.frombuffer(b"".join(raw), kind).reshape(-1, width).astype(np.float64)


def _place(df: DataFrame, tree, width: int, k: int) -> DataFrame:
    """leaf, vector, ids of every distinct vector of each partition; at most k + 1 smallest ids."""

    def run(batches):
        def flush(held):
            if held:
                yield pa.RecordBatch.from_arrays([pa.array(tree.value.assign(_unit(_vectors_of(list(held), width)))), pa.array(list(held), pa.binary()), pa.array([sorted(x)[: k + 1] for x in held.values()], pa.list_(pa.int64()))], ["leaf", "vector", "ids"])

        held: dict[bytes, list[int]] = {}
        for batch in batches:
            rows, values = _dense(batch.column(1), width)
            values = (values + 0.0).astype(np.float32 if pa.types.is_float32(batch.column(1).type.value_type) else np.float64)  # one zero
            for i, v in zip(batch.column(0).take(pa.array(rows)).to_pylist(), values):
                ids = held.setdefault(v.tobytes(), [])
                ids.append(i)
                if len(ids) > 64:
                    held[v.tobytes()] = sorted(ids)[: k + 1]
            if len(held) > 20_000:
                yield from flush(held)
                held = {}
        yield from flush(held)

    return df.mapInArrow(run, "leaf long, vector binary, ids array<long>")


def brute_force(placed: DataFrame, queries: list[tuple[int, np.ndarray]], width: int, k: int) -> DataFrame:
    """Exact neighbours of a bounded list of queries over the whole table: query_id, rank, vec_id, leaf, score."""
    sent = placed.sparkSession.sparkContext.broadcast(queries)

    def run(batches):
        ids = [q for q, _ in sent.value]
        asked = np.array([v for _, v in sent.value]).reshape(-1, width)
        for batch in batches:
            scores = cosines(asked, _vectors_of(batch.column(1).to_pylist(), width))
            leaf, names = batch.column(0).to_numpy(), batch.column(2).to_pylist()
            out = [(q, i, int(leaf[j]), float(s[j])) for q, s in zip(ids, scores) for j in _best(s, k + 1) for i in names[j] if i != q]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out) if out else ([], [], [], []), (pa.int64(), pa.int64(), pa.int64(), pa.float64()))], ["query_id", "vec_id", "leaf", "score"])

    return _ranked(placed.mapInArrow(run, "query_id long, vec_id long, leaf long, score double"), k)


def _ranked(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def _top(query: np.ndarray, vec: np.ndarray, score: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best of each query, equal scores by vec."""
    order = np.lexsort((vec, -score, query))
    query, vec, score = query[order], vec[order], score[order]
    first = np.flatnonzero(np.concatenate([[True], query[1:] != query[:-1]])) if len(query) else np.zeros(0, np.int64)
    rank = np.arange(len(query)) - np.repeat(first, np.diff(np.concatenate([first, [len(query)]])))
    return query[rank < k], vec[rank < k], score[rank < k]


def _further(placed: DataFrame, folder: str, width: int, k: int, chunk: int = 1 << 17, block: int = 2_048, piece: int = 1_024, most: int = 1 << 18) -> DataFrame:
    """query_id, vec_id, score of the vectors in the leaves that a query has in ``leaves`` that reach its bar.

    placed is in the order of leaves; folder holds query_id, q, leaves (a bit a leaf), bar.  Products of single
    precision find the pairs that may reach the bar, which rises as a block's pairs are found; those are computed anew."""
    slack = 1e-6 + 2e-7 * width

    def met(leaf: np.ndarray, raw: list[bytes], own: list[list[int]], fs, files: list[str]):
        import pyarrow.parquet as pq

        rows: dict[tuple[int, bytes], list[int]] = {}
        for x, r, i in zip(leaf.tolist(), raw, own):
            rows.setdefault((x, r), []).extend(i)
        at = np.array([x for x, _ in rows], np.int64)
        order = np.argsort(at, kind="stable")
        names = [sorted(x)[: k + 1] for x in rows.values()]
        raw = [r for _, r in rows]
        names, raw, at = [names[i] for i in order], [raw[i] for i in order], at[order]
        exact = np.frombuffer(b"".join(raw), np.float32 if len(raw[0]) == 4 * width else np.float64).reshape(-1, width)
        unit = np.concatenate([_unit(exact[lo : lo + piece].astype(np.float64)).astype(np.float32) for lo in range(0, len(exact), piece)])
        sizes = np.array([len(x) for x in names])
        first, flat = np.concatenate([[0], np.cumsum(sizes)]), np.concatenate([np.array(x, np.int64) for x in names])
        heads = [*np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]])).tolist(), len(at)]
        pieces = [(lo, min(lo + piece, end)) for begin, end in zip(heads, heads[1:]) for lo in range(begin, end, piece)]
        for file in files:
            with fs.open_input_file(file) as f:
                for asked in pq.ParquetFile(f).iter_batches(block):
                    if not asked.num_rows:
                        continue
                    ids, bar = asked.column(0).to_numpy(), asked.column(3).to_numpy(zero_copy_only=False).copy()
                    q = np.frombuffer(b"".join(asked.column(1).to_pylist()), np.float64).reshape(-1, width)
                    seen = np.frombuffer(b"".join(asked.column(2).to_pylist()), np.uint8).reshape(len(ids), -1)
                    u = _unit(q).astype(np.float32)
                    held, n = [], 0
                    for lo, hi in pieces:
                        x = int(at[lo])
                        some = np.flatnonzero(seen[:, x >> 3] >> (7 - (x & 7)) & 1)
                        if not len(some):
                            continue
                        scores = u[some] @ unit[lo:hi].T
                        floor = (bar[some] - slack).astype(np.float32)
                        if hi - lo > 4 * k:  # a query whose bar is still low keeps its best and what may equal them
                            low = np.flatnonzero((scores >= floor[:, None]).sum(1) > 4 * k)
                            if len(low):
                                floor[low] = np.maximum(floor[low], np.partition(scores[low], hi - lo - k - 1, axis=1)[:, hi - lo - k - 1] - np.float32(2 * slack))
                        i, j = np.nonzero(scores >= floor[:, None])
                        for a in range(0, len(i), most):
                            i1, j1 = some[i[a : a + most]], j[a : a + most] + lo
                            s = _paired(q[i1], exact[j1].astype(np.float64))
                            good = s >= bar[i1]
                            i1, j1, s = i1[good], j1[good], s[good]
                            of = np.repeat(i1, sizes[j1])
                            vec = flat[K.concat_ranges(first[j1], sizes[j1])]
                            other = vec != ids[of]
                            held.append((of[other], vec[other], np.repeat(s, sizes[j1])[other]))
                            n += int(other.sum())
                            if n > most:
                                held = [_top(*map(np.concatenate, zip(*held)), k)]
                                of, _, s = held[0]
                                n = len(of)
                                full = np.flatnonzero(np.bincount(of, minlength=len(bar)) == k)
                                worst = np.full(len(bar), np.inf)
                                np.minimum.at(worst, of, s)
                                bar[full] = np.maximum(bar[full], worst[full])
                    if n:
                        of, vec, s = _top(*map(np.concatenate, zip(*held)), k)
                        yield pa.RecordBatch.from_arrays([pa.array(ids[of]), pa.array(vec), pa.array(s)], ["query_id", "vec_id", "score"])

    def run(batches):
        from pyarrow.fs import FileSelector

        fs, root = open_fs(folder)
        files = sorted(x.path for x in fs.get_file_info(FileSelector(root)) if x.path.endswith(".parquet"))
        leaf, raw, own = [], [], []
        for batch in batches:
            leaf.append(batch.column(0).to_numpy())
            raw.extend(batch.column(1).to_pylist())
            own.extend(batch.column(2).to_pylist())
            if len(raw) >= chunk:
                yield from met(np.concatenate(leaf), raw, own, fs, files)
                leaf, raw, own = [], [], []
        if raw:
            yield from met(np.concatenate(leaf), raw, own, fs, files)

    return placed.mapInArrow(run, "query_id long, vec_id long, score double")


def neighbours(df: DataFrame, every: int = 50, k: int = 5, id_column: str = "vec_id", vector: str = "embedding", recall: float = 0.95, sample: int = 20_000, calibration: int = 128, tile: int = 2_048, branching: int = 8, least_leaf: int = 8, rows_a_leaf: int = 512) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of each row whose id ``every`` divides."""
    spark = df.sparkSession
    rows = df.select(F.col(id_column).cast("long").alias("id"), F.col(vector).alias("v")).where("id is not null and v is not null")
    n = rows.count()
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    taken = rows.orderBy(F.xxhash64("id"), "id").limit(sample).toArrow()  # bounded by ``sample``
    _, values = _dense(taken.column("v")) if taken.num_rows else (None, np.zeros((0, 1)))
    if not len(values):
        return empty
    width = values.shape[1]
    leaf_rows = max(least_leaf, int(rows_a_leaf * len(values) / max(n, 1)))
    tree = spark.sparkContext.broadcast(Tree.fit(_unit(values), branching, leaf_rows))
    n_leaves = tree.value.n_leaves
    placed = materialise(_place(rows, tree, width, k), "placed")
    asked = rows.where(F.col("id") % every == 0)

    # how far to go: visits of a bounded set of queries, against their exact neighbours
    some = asked.orderBy(F.xxhash64("id", F.lit(1)), "id").limit(calibration).toArrow()
    held, vectors = _dense(some.column("v"), width) if some.num_rows else (np.zeros(0, np.int64), np.zeros((0, width)))
    ids = some.column("id").to_numpy()[held] if len(held) else []
    if not len(held) and not asked.limit(1).count():
        return empty
    true = brute_force(placed, list(zip(map(int, ids), vectors)), width, k).select("query_id", "leaf").toArrow().to_pydict()
    order = {int(q): {leaf: i for i, leaf in enumerate(tree.value.visits(far))} for q, far in zip(ids, tree.value.far(_unit(vectors)) if len(vectors) else [])}
    at = np.array([order[q][leaf] for q, leaf in zip(true["query_id"], true["leaf"])], np.int64)
    visits = 1
    while visits < n_leaves and len(at) and (at < visits).mean() < recall:
        visits = min(n_leaves, visits + max(1, visits // 4))

    # one row a leaf: bounded by the tree
    sizes = {r["leaf"]: r["n"] for r in placed.groupBy("leaf").agg(F.count("*").alias("n")).collect()}
    counts = spark.sparkContext.broadcast(sizes)

    def walk(batches):
        for batch in batches:
            rows, values = _dense(batch.column(1), width)
            names = batch.column(0).take(pa.array(rows)).to_numpy()
            for lo in range(0, len(names), 256):
                some = values[lo : lo + 256]
                near, leaves = [], np.zeros((len(some), n_leaves), bool)
                for i, far in enumerate(tree.value.far(_unit(some))):
                    seen, gone, first = 0, 0, []
                    for x in tree.value.visits(far):
                        here = counts.value.get(x, 0)
                        if here and gone < 2:
                            first.append(x)
                        elif here:
                            leaves[i, x] = True
                        seen, gone = seen + here, gone + 1
                        if gone >= visits and seen > k:
                            break
                    near.append(first)
                yield pa.RecordBatch.from_arrays([pa.array(names[lo : lo + 256]), pa.array([v.tobytes() for v in some], pa.binary()), pa.array(near, pa.list_(pa.int64())), pa.array([x.tobytes() for x in np.packbits(leaves, axis=1)], pa.binary())], ["query_id", "q", "near", "leaves"])

    walks = materialise(asked.mapInArrow(walk, "query_id long, q binary, near array<long>, leaves binary"), "walks")
    out_schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])

    def meet(vectors: pa.Table, queries: pa.Table) -> pa.Table:
        if not vectors.num_rows or not queries.num_rows:
            return out_schema.empty_table()
        ids: dict[bytes, list[int]] = {}
        for raw, own in zip(vectors.column("vector").to_pylist(), vectors.column("ids").to_pylist()):
            ids.setdefault(raw, []).extend(own)
        names = [sorted(x)[: k + 1] for x in ids.values()]
        asked, held = _vectors_of(queries.column("q").to_pylist(), width), _vectors_of(list(ids), width)
        out = []
        for q, v, s in zip(queries.column("query_id").to_pylist(), asked, cosines(asked, held)):
            best = _best(np.round(s, 12), k + 1)
            out += [(q, i, x) for j, x in zip(best, _paired(v[None, :], held[best]).tolist()) for i in names[j] if i != q]
        return pa.table([pa.array(x, t) for x, t in zip(zip(*out) if out else ([], [], []), out_schema.types)], schema=out_schema)

    tiles = ["leaf", "vp", "qp"]

    crowd = {r["leaf"]: r["n"] for r in walks.select(F.explode("near").alias("leaf")).groupBy("leaf").agg(F.count("*").alias("n")).collect()}
    plan = F.broadcast(spark.createDataFrame([(leaf, -(-m // tile), max(1, -(-crowd.get(leaf, 0) // tile)), leaf in crowd) for leaf, m in sizes.items()] or [(-1, 1, 1, False)], "leaf long, v_parts int, q_parts int, asked boolean"))  # one row a leaf

    # the nearest leaves first: what the others return must reach the k-th score found there
    dealt = placed.join(plan, "leaf").withColumn("vp", F.pmod(F.xxhash64("vector"), F.col("v_parts")).cast("int"))
    left = dealt.where("asked").select("leaf", "vp", F.explode(F.sequence(F.lit(0), F.col("q_parts") - 1)).alias("qp"), "vector", "ids")
    right = walks.select("query_id", "q", F.explode("near").alias("leaf")).join(plan, "leaf").select("leaf", F.explode(F.sequence(F.lit(0), F.col("v_parts") - 1)).alias("vp"), F.pmod(F.xxhash64("query_id"), F.col("q_parts")).cast("int").alias("qp"), "query_id", "q")
    met = left.groupBy(*tiles).cogroup(right.groupBy(*tiles)).applyInArrow(meet, "query_id long, vec_id long, score double")
    near = materialise(_ranked(met, k), "near")
    bars = near.where(F.col("rank") == k).select("query_id", F.col("score").alias("bar"))
    folder = shared_dir(spark, "queries")
    walks.join(bars, "query_id", "left").select("query_id", "q", "leaves", F.coalesce("bar", F.lit(-2.0)).alias("bar")).write.parquet(folder)
    by_leaf = dealt.repartition("leaf", "vp").sortWithinPartitions("leaf", "vp").select("leaf", "vector", "ids")
    found = near.select("query_id", "vec_id", "score").unionByName(_further(by_leaf, folder, width, k))
    return _ranked(found, k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
