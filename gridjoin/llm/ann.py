"""Operator 1, approximate nearest neighbours with score-aware quantisation.

Nearness is turned into an inner product: of q and x, q.x - |x|^2 / 2 is largest where |q - x| is least. Vectors are centred and cut into
subspaces of two components, each with 16 centroids, so a code takes four bits. Codes and centroids minimise an anisotropic loss: the residual's part
along the vector weighs ETA times its part across, as that is what moves large inner products. Codes are chosen by coordinate
descent, centroids by least squares under the same loss, on a bounded sample of SAMPLE vectors (those of least hash of vec_id).

1. Every vector is encoded into a stored index of slabs: ids, codes, two further layers of four-bit codes (each of what the layers before
   leave, by plain least squares), |x|^2 / 2, and the same of the vector that all layers add up to. The vectors stay in their own table.
2. Queries are packed into blocks of about QUERIES; each slab meets each block (the blocks are a broadcast while they have at most BLOCK_BYTES). A task makes
   tables of two codes at a time for a few queries, scans the slab's codes, refines its WIDE best estimates of each query to the
   distance from what all layers add up to, and keeps the KEEP best of these over its slabs.
3. The KEEP best estimates of all tasks are measured exactly, in double precision, on the original vectors, which are fetched for these only.

Equal vectors have equal codes and norms, hence equal estimates. Of such a group only the k + 1 rows of least vec_id are kept, in a slab, in a task and
over all, as no other can be among k nearest with ties to the smaller id. So a vector that a third of the rows share cannot fill the candidates.

Defined cases: vectors that are null, empty, zero, or hold null or non-finite components take no part, nor do those of another length than
the most frequent one (ties: the larger), nor rows with null vec_id. Of rows that repeat a vec_id the one of least vector is the query; as candidates all are measured, and the
nearest counts, so each pair is returned once.
Empty tables give no rows. With k or fewer candidates, all are returned. Other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import lean, pieces, settled, stored, table
from .textnum import mix

SAMPLE, QUERIES, SLAB, LAYERS, WIDE, KEEP = 20_000, 1024, 4096, 2, 768, 192
#: Queries of a block that are scanned together, blocks whose best a task holds, bytes of blocks and rows of candidates that may be broadcast.
TOGETHER, HELD, BLOCK_BYTES, MAX_BROADCAST = 128, 16, 1 << 26, 1_000_000
#: The inner products that matter are at least this share of the norms; it sets ETA.
THRESHOLD = 0.2
ROUNDS, SEED = 3, 1


def eta(dim: int, threshold: float = THRESHOLD) -> float:
    """Weight of the parallel part over the part across."""
    return max(1.0, (dim - 1) * threshold**2 / (1 - threshold**2))


def padded(x: np.ndarray) -> np.ndarray:
    """An even number of subspaces of two: four components at a time."""
    extra = -x.shape[1] % 4
    return np.pad(x, ((0, 0), (0, extra))) if extra else x


def units(x: np.ndarray) -> np.ndarray:
    norm = np.linalg.norm(x, axis=1, keepdims=True)
    return x / np.where(norm == 0, 1, norm)


def encode(x: np.ndarray, books: np.ndarray, weight: float, rounds: int = 2) -> np.ndarray:
    """x: [n, d] centred and padded; books: [subspaces, 16, 2]. Codes [n, subspaces]."""
    n, s = len(x), len(books)
    parts, dirs = x.reshape(n, s, 2), units(x).reshape(n, s, 2)
    codes = np.empty((n, s), np.uint8)
    rows = np.arange(n)
    for j in range(s):
        codes[:, j] = ((parts[:, j, None] - books[j]) ** 2).sum(axis=2).argmin(axis=1)
    along = np.zeros(n)
    for j in range(s):
        along += ((parts[:, j] - books[j][codes[:, j]]) * dirs[:, j]).sum(axis=1)
    for _ in range(rounds):
        for j in range(s):
            rest = parts[:, j, None] - books[j]
            mine = (rest * dirs[:, j, None]).sum(axis=2)
            total = (along - mine[rows, codes[:, j]])[:, None] + mine
            codes[:, j] = ((rest**2).sum(axis=2) + (weight - 1) * total**2).argmin(axis=1)
            along = total[rows, codes[:, j]]
    return codes


def train(x: np.ndarray, weight: float, rounds: int = ROUNDS, seed: int = SEED) -> np.ndarray:
    """Centroids [subspaces, 16, 2] for centred, padded vectors."""
    n, d = x.shape
    s = d // 2
    rng = np.random.default_rng(seed)
    parts = x.reshape(n, s, 2)
    books = parts[rng.integers(0, n, (16, s)), np.arange(s)].transpose(1, 0, 2).copy()
    for j in range(s):
        for _ in range(8):
            own = ((parts[:, j, None] - books[j]) ** 2).sum(axis=2).argmin(axis=1)
            for c in range(16):
                if (mine := own == c).any():
                    books[j, c] = parts[mine, j].mean(axis=0)
    u = units(x)
    for _ in range(rounds):
        codes = encode(x, books, weight)
        width = s * 32
        left, right = np.zeros((width, width)), np.zeros(width)
        for i in range(0, n, 2000):
            v, c = np.zeros((min(2000, n - i), width)), codes[i : i + 2000].astype(np.int64)
            rows = np.arange(len(c))
            along = (x[i : i + 2000] * u[i : i + 2000]).sum(axis=1)
            for j in range(s):
                for k in range(2):
                    at = j * 32 + c[:, j] * 2 + k
                    v[rows, at] = u[i : i + 2000, 2 * j + k]
                    right += np.bincount(at, weights=x[i : i + 2000, 2 * j + k], minlength=width)
                    left[np.arange(width), np.arange(width)] += np.bincount(at, minlength=width)
            left += (weight - 1) * (v.T @ v)
            right += (weight - 1) * (v.T @ along)
        used = np.diag(left) > 0
        left[np.arange(width), np.arange(width)] += 1e-6 * n / 16
        right += 1e-6 * n / 16 * books.reshape(-1)
        new = np.linalg.solve(left, right)
        books = np.where(used, new, books.reshape(-1)).reshape(s, 16, 2)
    return books


def vectors(column: pa.Array, dim: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Rows that take part, and their vectors in double precision."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    size = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    rows = np.flatnonzero(size == dim) if dim else np.zeros(0, np.int64)
    if not len(rows):
        return rows, np.zeros((0, dim or 0))
    taken = column.take(pa.array(rows))
    flat = taken.flatten().cast(pa.float64()).to_numpy(zero_copy_only=False)
    x = flat.reshape(len(rows), dim)
    good = np.isfinite(x).all(axis=1) & (x != 0).any(axis=1)
    return rows[good], x[good]


def decoded(codes: np.ndarray, books: np.ndarray) -> np.ndarray:
    return books[np.arange(len(books)), codes].reshape(len(codes), -1)


def refine(est: np.ndarray, luts: np.ndarray, codes: np.ndarray, gain: np.ndarray, top: np.ndarray) -> np.ndarray:
    """Estimates of the chosen rows with the inner products of their further layers added, and the gain, by which half the squared norm of what all layers
    add up to is less than that of the vector. luts: as for scan, top: [queries, chosen]."""
    out = np.take_along_axis(est, top, 1) + gain.astype(np.float32)[top]
    row = np.arange(len(top))[:, None]
    for j in range(len(luts)):
        out += luts[j][row, codes[top, j]]
    return out


def signatures(codes: np.ndarray, half: np.ndarray) -> np.ndarray:
    """64 bits of each row's codes and norm; equal vectors have equal ones."""
    wide = np.zeros((len(codes), -(-codes.shape[1] // 8) * 8), np.uint8)
    wide[:, : codes.shape[1]] = codes
    out = mix(half.view(np.uint64))
    for word in wide.view(np.uint64).T:
        out = mix(out * np.uint64(31) + word)
    return out.view(np.int64)


def fewest(ids: np.ndarray, sig: np.ndarray, most: int) -> np.ndarray:
    """Rows of the least ids, at most ``most`` of each signature."""
    by = np.lexsort((ids, sig))
    first = np.flatnonzero(np.concatenate([[True], np.diff(sig[by]) != 0]))
    rank = np.arange(len(by)) - np.repeat(first, np.diff(np.append(first, len(by))))
    return by[rank < most]


def best_of(est: np.ndarray, ids: np.ndarray, sig: np.ndarray, keep: int, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each row of estimates the ``keep`` largest (ties: by signature, then the least id), at most ``most`` of one estimate and signature."""
    order = np.lexsort((ids, sig, -est), axis=1)
    est, ids, sig = (np.take_along_axis(x, order, 1) for x in (est, ids, sig))
    fresh = np.ones(est.shape, bool)
    fresh[:, 1:] = (est[:, 1:] != est[:, :-1]) | (sig[:, 1:] != sig[:, :-1])
    at = np.arange(est.shape[1])
    rank = at - np.maximum.accumulate(np.where(fresh, at, 0), axis=1)
    est = np.where(rank < most, est, -np.inf)
    order = np.argsort(-est, axis=1, kind="stable")[:, :keep]
    return tuple(np.take_along_axis(x, order, 1) for x in (est, ids, sig))


def tables(q: np.ndarray, books: np.ndarray) -> np.ndarray:
    """q: [Q, d] centred, padded. For each query and byte of two codes the sum of their inner products: [bytes, Q, 256]."""
    s = len(books)
    one = np.einsum("qsd,scd->sqc", q.reshape(len(q), s, 2), books).astype(np.float32)
    return (one[0::2][:, :, :, None] + one[1::2][:, :, None, :]).reshape(s // 2, len(q), 256)


def scan(luts: np.ndarray, codes: np.ndarray, half: np.ndarray) -> np.ndarray:
    """Estimated q.x - |x|^2 / 2 for all queries and rows; codes: bytes [n, subspaces / 2]."""
    out = np.repeat(-half[None, :].astype(np.float32), luts.shape[1], axis=0)
    for j in range(len(luts)):
        out += luts[j][:, codes[:, j]]
    return out


def _encode_all(state, dim: int):
    schema = pa.schema([(c, pa.binary()) for c in ("ids", "codes", "more", "half", "gain")])
    pack = lambda codes: np.ascontiguousarray(codes[:, 0::2] << 4 | codes[:, 1::2])

    def run(batches):
        centre, books, layers, weight = state.value
        for batch in pieces(batches, SLAB):
            ids = batch.column("vec_id")
            rows, x = vectors(batch.column("embedding"), dim)
            keep = ids.is_valid().to_numpy(zero_copy_only=False)[rows]
            rows, x = rows[keep], x[keep]
            if len(rows):
                c = padded(x - centre)
                codes = encode(c, books, weight)
                rest, more = c - decoded(codes, books), []
                for b in layers:
                    more.append(encode(rest, b, 1.0, 0))
                    rest = rest - decoded(more[-1], b)
                yield pa.record_batch([pa.array([v.tobytes()], pa.binary()) for v in (ids.take(pa.array(rows)).to_numpy(), pack(codes), pack(np.concatenate(more, axis=1)), (c * c).sum(axis=1) / 2, ((c * c).sum(axis=1) - ((c - rest) ** 2).sum(axis=1)) / 2)], schema=schema)

    return run


def _scan_pairs(state, dim: int, k: int):
    """Rows: a slab (ids, codes, more, half, gain) beside a block of queries (block, asked: vec_id and q), to query_id, vec_id, est, sig."""
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("est", pa.float32()), ("sig", pa.int64())])

    def run(batches):
        centre, books, layers = state.value
        held: dict[int, tuple] = {}

        def out(block: int) -> pa.RecordBatch:
            qid, est, ids, sig = held.pop(block)
            real = np.isfinite(est)
            return pa.record_batch([pa.array(np.repeat(qid, real.sum(axis=1))), pa.array(ids[real]), pa.array(est[real]), pa.array(sig[real])], schema=schema)

        for batch in pieces(batches, 16):
            for block, asked, *slab in zip(batch.column("block").to_pylist(), batch.column("asked"), *(batch.column(c).to_pylist() for c in ("ids", "codes", "more", "half", "gain")), strict=True):
                ids, half, gain = np.frombuffer(slab[0], np.int64), np.frombuffer(slab[3], np.float64), np.frombuffer(slab[4], np.float64)
                codes, more = (np.frombuffer(x, np.uint8).reshape(len(ids), -1) for x in slab[1:3])
                sig = signatures(np.concatenate([codes, more], axis=1), half)
                few = fewest(ids, sig, k + 1)
                ids, codes, more, half, gain, sig = ids[few], codes[few], more[few], half[few], gain[few], sig[few]
                qid = asked.values.field("vec_id").to_numpy()
                q = padded(asked.values.field("q").flatten().to_numpy().reshape(len(qid), dim) - centre)
                if block not in held:
                    if len(held) >= HELD:
                        yield out(next(iter(held)))
                    held[block] = qid, np.full((len(qid), KEEP), -np.inf, np.float32), np.zeros((len(qid), KEEP), np.int64), np.zeros((len(qid), KEEP), np.int64)
                _, best, names, sigs = held[block]
                for i in range(0, len(qid), TOGETHER):
                    part = slice(i, i + TOGETHER)
                    est = scan(tables(q[part], books), codes, half)
                    est[ids == qid[part, None]] = -np.inf
                    m = min(WIDE, len(ids))
                    top = np.argpartition(-est, m - 1, axis=1)[:, :m]
                    new = refine(est, np.concatenate([tables(q[part], b) for b in layers]), more, gain, top), ids[top], sig[top]
                    best[part], names[part], sigs[part] = best_of(*(np.concatenate([old[part], x], axis=1) for old, x in zip((best, names, sigs), new, strict=True)), KEEP, k + 1)
        while held:
            yield out(next(iter(held)))

    return run


def _measure(dim: int):
    """query_id, vec_id, q and embedding to the exact distance."""
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])

    def run(batches):
        for batch in pieces(batches, 2048):
            q, x = (batch.column(c).flatten().cast(pa.float64()).to_numpy(zero_copy_only=False).reshape(-1, dim) for c in ("q", "embedding"))
            yield pa.record_batch([batch.column("query_id"), batch.column("vec_id"), pa.array(np.sqrt(((x - q) ** 2).sum(axis=1)))], schema=schema)

    return run


def nearest(base: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """query_id, rank, vec_id, score. base and queries: vec_id, embedding; a query's own id is no candidate."""
    spark = base.sparkSession
    none = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    base, queries = (d.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>")) for d in (base, queries))
    whole = F.forall("embedding", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < F.lit(float("inf")))) & F.exists("embedding", lambda c: c != 0)
    sizes = base.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & whole).groupBy(F.size("embedding").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    if sizes is None:
        return none
    dim = int(sizes["d"])
    fit = (F.size("embedding") == dim) & whole & F.col("vec_id").isNotNull()
    sample = base.where(fit).orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).select("embedding").toArrow()
    _, x = vectors(sample.column("embedding"), dim)
    centre, weight = x.mean(axis=0), eta(dim)
    x = padded(x - centre)
    books = train(x, weight)
    rest, layers = x - decoded(encode(x, books, weight), books), []
    for _ in range(LAYERS):
        layers.append(train(rest, 1.0, 0))
        rest = rest - decoded(encode(rest, layers[-1], 1.0, 0), layers[-1])
    sent = spark.sparkContext.broadcast((centre, books, layers, weight))
    asked = stored(queries.where(fit).groupBy("vec_id").agg(F.min("embedding").alias("q")), "asked")
    count = asked.count()
    if not count:
        return none
    blocks = -(-count // QUERIES)
    small = F.broadcast if count * dim * 8 <= BLOCK_BYTES else (lambda d: d)
    packed = asked.groupBy(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).alias("block")).agg(F.collect_list(F.struct("vec_id", "q")).alias("asked"))
    index = stored(base.mapInArrow(lean(_encode_all(sent, dim)), "ids binary, codes binary, more binary, half binary, gain binary"), "index")
    pairs = index.withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))).join(small(packed), "block")
    rough = pairs.mapInArrow(lean(_scan_pairs(spark.sparkContext.broadcast((centre, books, layers)), dim, k)), "query_id long, vec_id long, est float, sig long")
    alike = Window.partitionBy("query_id", "est", "sig").orderBy("vec_id")
    best = Window.partitionBy("query_id").orderBy(F.desc("est"), "sig", "vec_id")
    rough = rough.dropDuplicates(["query_id", "vec_id", "est", "sig"]).withColumn("r", F.row_number().over(alike)).where(F.col("r") <= k + 1)
    rough = stored(rough.withColumn("r", F.row_number().over(best)).where(F.col("r") <= KEEP).select("query_id", "vec_id").distinct(), "rough")
    few = F.broadcast if rough.count() <= MAX_BROADCAST else (lambda d: d)
    rows = base.where(fit).join(few(rough), "vec_id").join(small(asked.withColumnRenamed("vec_id", "query_id")), "query_id")
    exact = rows.select("query_id", "vec_id", "q", "embedding").mapInArrow(lean(_measure(dim)), "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    found = exact.groupBy("query_id", "vec_id").agg(F.min("score").alias("score")).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return settled(found.select("query_id", "rank", "vec_id", "score"), "nearest", asked, index, rough)


def op1_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = table(spark, sf_dir, "embeddings")
    return nearest(base, base.where("vec_id % 100 = 0"))
