"""Operator 10, n-gram Jaccard join by a prefix tree.

A document's set is its distinct 5-word shingles (with fewer words, the whole sequence; without words, nothing), as 64-bit numbers: a
60-bit hash under a 4-bit rank, which is higher the more common the shingle's words are. Sets are sorted by that number, so one global order puts
shingles of rare words first. Two documents link when 100 * intersection >= 75 * union. The result is each document's component.

1. One scan gives each document its set's size and 128-bit digest, and counts the shingles that a task meets more than once. Equal
   sets are one class, which gets a number; copies go no further. The word ranks (from a bounded sample of
   WORD_SAMPLE documents) and the counts only order the shingles. The order changes the work, never the result.
2. A second scan posts the first n - ceil(0.75 n) + DEPTH shingles of each set. Two sets that link share at least
   need(n, m) - ceil(0.75 max(n, m)) + DEPTH of them, where need is the intersection they must have. Postings are sorted by shingle; a shingle of one
   class is passed over.
3. Groups of at most SMALL classes give their pairs (so at most SMALL for each posting); pairs that pass the size, position and
   count bounds are verified on whole sets. Around a hub, the candidates' sorted sets are walked as a prefix tree: along equal beginnings
   the partial overlap is shared, and a subtree ends when the remaining lengths cannot reach the needed overlap. Hubs with
   one least neighbour are verified together, so that a set goes once to each such cluster; a cluster of more than TOGETHER pairs is salted.
4. Larger groups are joined whole. Groups with the same least member are one cluster (near copies share most of their groups). Its classes are dealt
   to blocks of about BLOCK, and each block's links are found by counting intersections of those that share a group; only a spanning forest leaves it. Then
   the roots of all blocks are joined in the same way. What steps 3 and 4 have linked so far are components; only classes of one cluster that are in
   different ones are still compared, in blocks made by component. So a set goes once to each of its clusters, and once more to each
   block of classes that are not linked with it; a thousand near copies never become rows of pairs. A class joins all but the last
   ``skipped`` of its large groups. Which groups are large is free to choose: those of HOT classes or more are from the start, so their postings are salted, and
   of a longer group than LONG rows no task holds more than these.

Where a link shares more large groups than either class skips, the first that they share is skipped by neither, and step 4 settles it. Where it shares
fewer, step 3 has counted all its other postings, and its bound there is lowered by as many as the two classes' large groups can be.
Components need no copies expanded. The list of common shingles is cut at MAX_COMMON (the rest merely sort by word rank), which bounds its broadcast.

Defined cases: null or empty text has 0 shingles and is its own component. Repeated rows are reported each; rows of one doc_id with different texts are
linked each by its text. A null doc_id takes part as any other and cannot name a component; alone, its component is null. Ties have no part in the
result. Texts may be of any length. Empty tables give no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import drop_stored, lean, pieces, settled, stored, table
from .components import connected_components
from .textnum import shingle_hashes, slices, utf8, word_hashes

K, PERCENT = 5, 75
COMMON, MAX_COMMON = 24, 1 << 20
#: Linked sets share at least so many of the posted shingles (small sets: all that they need to share).
DEPTH = 24
#: Pairs with one least neighbour are verified together, about so many at a time.
TOGETHER = 128
SMALL, BLOCK = 24, 128
#: Shingles of so many classes are dealt by salt and their groups are large in any case; rows of a group that are held at once.
HOT, SALTS, LONG = 1 << 16, 64, 1 << 16
WORD_SAMPLE, WORDS = 2000, 1024
#: log2 of the probability at which ranks begin, of a word that is not in the list, and the step of a rank.
RARE, OTHER, STEP = -46.0, -17.0, 2.0
MAX_BROADCAST = 1_000_000
FLUSH = 1 << 21


Ranks = tuple[np.ndarray, np.ndarray]
NO_RANKS: Ranks = (np.zeros(0, np.uint64), np.zeros(0, np.float32))


def word_ranks(texts: list[str], most: int = WORDS) -> Ranks:
    """Sorted hashes of the most frequent words of a sample and log2 of their shares."""
    data, offsets = utf8(pa.array(texts, pa.string()))
    parts = [word_hashes(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])[0] for i, j in slices(offsets)]
    words = np.concatenate(parts) if parts else np.zeros(0, np.uint64)
    keys, count = np.unique(words, return_counts=True)
    top = np.sort(np.lexsort((keys, -count))[:most])
    return keys[top], np.maximum(np.log2(count[top] / max(1, len(words))), OTHER).astype(np.float32)


def sets_of(column, k: int = K, ranks: Ranks = NO_RANKS) -> Iterator[np.ndarray]:
    """The sorted distinct shingles of each text, the rank in the upper four bits."""
    data, offsets = utf8(column)
    keys, logs = ranks
    for i, j in slices(offsets):
        words, at = word_hashes(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
        h, begin = shingle_hashes(words, at, k)
        h >>= np.uint64(4)
        if len(keys) and len(words) >= k:
            where = np.minimum(np.searchsorted(keys, words), len(keys) - 1)
            share = np.where(keys[where] == words, logs[where], np.float32(OTHER)).astype(np.float64)
            total = np.concatenate([[0], np.cumsum(share)])
            full = total[k:] - total[:-k]
            n = np.diff(begin)
            first = np.repeat(at[:-1] - begin[:-1], n) + np.arange(begin[-1])
            rank = np.clip((full[np.minimum(first, len(full) - 1)] - RARE) // STEP, 0, 15)
            rank[np.repeat(np.diff(at) < k, n)] = 0
            h |= rank.astype(np.uint64) << np.uint64(60)
        for a, b in zip(begin[:-1], begin[1:], strict=True):
            yield np.unique(h[a:b])


def digest(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def _scan(k: int, ranks):
    """kind 0: doc_id, n, g (digest); kind 1: h, c (a shingle and how many of the task's classes have it)."""
    schema = pa.schema([("kind", pa.int8()), ("doc_id", pa.int64()), ("n", pa.int64()), ("g", pa.binary()), ("h", pa.int64()), ("c", pa.int64())])

    def common(parts: list[np.ndarray]) -> pa.RecordBatch:
        h, c = np.unique(np.concatenate(parts), return_counts=True)
        h, c = h[c > 1].view(np.int64), c[c > 1]
        m = len(h)
        return pa.record_batch([pa.array(np.ones(m, np.int8)), pa.nulls(m, pa.int64()), pa.nulls(m, pa.int64()), pa.nulls(m, pa.binary()), pa.array(h), pa.array(c)], schema=schema)

    def run(batches):
        parts, held, seen = [], 0, set()
        for batch in pieces(batches, 1000):
            n, g = [], []
            for s in sets_of(batch.column("text"), k, ranks.value):
                n.append(len(s))
                g.append(digest(s))
                if len(s) and g[-1] not in seen:
                    seen.add(g[-1])
                    parts.append(s)
                    held += len(s)
                if held > FLUSH:
                    yield common(parts)
                    parts, held, seen = [], 0, set()
            m = len(n)
            yield pa.record_batch([pa.array(np.zeros(m, np.int8)), batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(g, pa.binary()), pa.nulls(m, pa.int64()), pa.nulls(m, pa.int64())], schema=schema)
        if parts:
            yield common(parts)

    return run


def _postings(common, k: int, percent: int, ranks, hot: int):
    """h, salt, n, pos, g for the prefix of each set; a task posts a set once. Shingles of ``hot`` classes or more are salted by the class."""
    schema = pa.schema([("h", pa.int64()), ("salt", pa.int8()), ("n", pa.int32()), ("pos", pa.int32()), ("g", pa.binary())])

    def run(batches):
        keys, counts = common.value
        seen: set[bytes] = set()
        for batch in pieces(batches, 1000):  # a posting is wider than its word, so batches are cut
            hs, ss, ns, ps, gs = [], [], [], [], []
            for s in sets_of(batch.column("text"), k, ranks.value):
                n = len(s)
                if not n or (g := digest(s)) in seen:
                    continue
                if len(seen) > 500_000:
                    seen = set()
                seen.add(g)
                m = posted(n, percent)
                salt = np.zeros(m, np.int8)
                if len(keys):
                    at = np.minimum(np.searchsorted(keys, s), len(keys) - 1)
                    rank = np.where(keys[at] == s, counts[at], 0)
                    if rank.any():
                        order = np.lexsort((s, rank))
                        s = s[order]
                        salt[rank[order][:m] >= hot] = 1 + g[0] % SALTS
                ss.append(salt)
                hs.append(s[:m].view(np.int64))
                ns.append(np.full(m, n, np.int32))
                ps.append(np.arange(m, dtype=np.int32))
                gs.append((g, m))
            if hs:
                names = pa.array([g for g, _ in gs], pa.binary())
                which = np.repeat(np.arange(len(gs)), [m for _, m in gs])
                yield pa.record_batch([pa.array(np.concatenate(hs)), pa.array(np.concatenate(ss)), pa.array(np.concatenate(ns)), pa.array(np.concatenate(ps)), names.take(pa.array(which))], schema=schema)

    return run


def _groups(batches, columns: list[str]) -> Iterator[tuple[dict[str, np.ndarray], bool]]:
    """Sorted batches, cut so that no group of equal h and salt is split, without groups of one row (but of salted ones); and, with True, the parts of a group of more than LONG rows,
    which is not held. g becomes an array of 16-byte values."""
    held: pa.Table | None = None
    long = None

    def arrays(t: pa.Table) -> dict[str, np.ndarray]:
        out = {c: t.column(c).to_numpy() for c in columns if c != "g"}
        g, _ = utf8(t.column("g").cast(pa.large_binary()))
        return out | {"g": g.view("V16")}

    def several(t: pa.Table) -> pa.Table:
        h, salt = t.column("h").to_numpy(), t.column("salt").to_numpy()
        same = (h[1:] == h[:-1]) & (salt[1:] == salt[:-1])
        keep = salt > 0
        keep[1:] |= same
        keep[:-1] |= same
        return t.filter(pa.array(keep))

    for batch in batches:
        if not batch.num_rows:
            continue
        t = pa.Table.from_batches([batch])
        t = t if held is None else pa.concat_tables([held, t])
        held = None
        h, salt = t.column("h").to_numpy(), t.column("salt").to_numpy()
        if long is not None:
            others = np.flatnonzero((h != long[0]) | (salt != long[1]))
            n = int(others[0]) if len(others) else len(h)
            if n:
                yield arrays(t.slice(0, n)), True
            if n == len(h):
                continue
            long, t, h, salt = None, t.slice(n), h[n:], salt[n:]
        others = np.flatnonzero((h != h[-1]) | (salt != salt[-1]))
        cut = int(others[-1]) + 1 if len(others) else 0
        held, t = t.slice(cut), t.slice(0, cut)
        if t.num_rows and (t := several(t)).num_rows:
            yield arrays(t), False
        if held.num_rows > LONG:
            a = arrays(held)
            fresh = np.concatenate([[True], a["g"][1:] != a["g"][:-1]])
            if fresh.sum() > SMALL:
                yield a, True
                long, held = (h[-1], salt[-1]), None
            else:  # copies of a few classes
                held = held.filter(pa.array(fresh))
    if held is not None and (t := several(held)).num_rows:
        yield arrays(t), False


def need(n, m, percent: int = PERCENT):
    """The least intersection of sets of n and m elements that link."""
    return -(-(percent * (n + m)) // (100 + percent))


def posted(n: int, percent: int) -> int:
    """How many shingles of a set of n are posted."""
    return min(n, n - -(-percent * n // 100) + DEPTH)


def least_met(n: np.ndarray, m: np.ndarray, percent: int) -> np.ndarray:
    """So many posted shingles two linked sets share at least: whichever ends first in the order, all that it shares but what follows its posted part."""
    both = need(n, m, percent)
    rest = lambda x: x - np.minimum(x, x - -(-percent * x // 100) + DEPTH)
    return np.maximum(1, both - np.maximum(rest(n), rest(m)))


def skipped(n, percent: int = PERCENT):
    """So many of its large groups a class of n shingles leaves out: fewer than a link must share."""
    return F.least(F.lit(DEPTH - 1), F.ceil(n * F.lit(percent) / 100).cast("int") - 1)


def _small_pairs(percent: int):
    """kind 0: pairs g, g2 of small groups, how often met (c) and how often they must be (n); kind 1: h, g and n (the set's size) of large groups."""
    schema = pa.schema([("kind", pa.int8()), ("h", pa.int64()), ("g", pa.binary()), ("g2", pa.binary()), ("n", pa.int32()), ("c", pa.int32())])

    def binary(v: np.ndarray) -> pa.Array:
        v = np.ascontiguousarray(v)
        return pa.Array.from_buffers(pa.binary(), len(v), [None, pa.py_buffer(np.arange(0, 16 * len(v) + 1, 16, dtype=np.int32)), pa.py_buffer(v.tobytes())])

    def run(batches):
        for a, long in _groups(batches, ["h", "salt", "n", "pos"]):
            fresh = np.ones(len(a["h"]), bool)
            fresh[1:] = (a["h"][1:] != a["h"][:-1]) | (a["g"][1:] != a["g"][:-1])
            h, salt, n, pos, g = (a[c][fresh] for c in ("h", "salt", "n", "pos", "g"))
            edge = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (salt[1:] != salt[:-1]), [True]]))
            size = np.repeat(np.diff(edge), np.diff(edge))
            large = (size > SMALL) | (salt > 0) | long
            if m := int(large.sum()):
                yield pa.record_batch([pa.array(np.ones(m, np.int8)), pa.array(h[large]), binary(g[large]), pa.nulls(m, pa.binary()), pa.array(n[large].astype(np.int32)), pa.nulls(m, pa.int32())], schema=schema)
            keep = (size > 1) & ~large
            h, n, pos, g = h[keep], n[keep].astype(np.int64), pos[keep].astype(np.int64), g[keep]
            left, right = [], []
            for step in range(1, SMALL):  # rows that far apart in one group
                if step >= len(h):
                    break
                i = np.flatnonzero(h[step:] == h[:-step])
                if not len(i):
                    break
                j = i + step
                ok = (n[i] * 100 >= percent * n[j]) & (np.minimum(pos[i], pos[j]) + np.minimum(n[i] - pos[i], n[j] - pos[j]) >= need(n[i], n[j], percent))
                left.append(i[ok])
                right.append(j[ok])
            i, j = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (left, right))
            if len(i):
                # sizes rise within a group and digests within a size, so a pair always stands one way round
                both, at, count = np.unique(np.stack([g[i], g[j]], 1).view("S32").ravel(), return_index=True, return_counts=True)
                both, p = both.view("V16").reshape(-1, 2), len(both)
                yield pa.record_batch([pa.array(np.zeros(p, np.int8)), pa.nulls(p, pa.int64()), binary(both[:, 0]), binary(both[:, 1]), pa.array(least_met(n[i], n[j], percent)[at].astype(np.int32)), pa.array(count.astype(np.int32))], schema=schema)

    return run


def forest(a: np.ndarray, b: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the graph of edges a, b over n nodes, as each node's root."""
    root = np.arange(n)
    while True:
        new = root.copy()
        np.minimum.at(new, a, root[b])
        np.minimum.at(new, b, root[a])
        new = new[new]
        if (new == root).all():
            break
        root = new
    own = np.flatnonzero(root != np.arange(n))
    return root[own], own


def block_links(sets: list[np.ndarray], marks: list[np.ndarray], side: np.ndarray, percent: int, apart: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Linked pairs of a block that share a mark (a large group). side: 0 or 1 for two different blocks, whose own pairs are left out; one value for
    a block with itself. apart: numbers of components; pairs of one component are left out."""
    m = len(sets)
    n = np.array([len(s) for s in sets], np.int32)
    todo = np.zeros((m, m), bool)
    row = np.repeat(np.arange(m), [len(x) for x in marks])
    _, col = np.unique(np.concatenate(marks), return_inverse=True)
    col = col.ravel()
    for c in range(0, int(col.max()) + 1, 1024):
        own = (col >= c) & (col < c + 1024)
        dense = np.zeros((m, 1024), np.float32)
        dense[row[own], col[own] - c] = 1
        todo |= dense @ dense.T > 0
    todo &= np.triu(np.ones((m, m), bool), 1)
    if side.min() != side.max():
        todo &= side[:, None] != side[None, :]
    if apart is not None:
        todo &= apart[:, None] != apart[None, :]
    todo &= np.minimum(n[:, None], n[None, :]) * 100 >= percent * np.maximum(n[:, None], n[None, :])
    i, j = np.nonzero(todo)
    if not len(i):
        return i, j
    wanted = need(n[i].astype(np.int64), n[j].astype(np.int64), percent)
    if len(i) <= 4 * m:
        common = np.array([len(np.intersect1d(sets[x], sets[y], assume_unique=True)) for x, y in zip(i, j, strict=True)])
        ok = common >= wanted
        return i[ok], j[ok]
    used = np.unique(np.concatenate([i, j]))
    token = np.concatenate([sets[x] for x in used])
    row = np.repeat(used, n[used])
    order = np.argsort(token, kind="stable")
    token, row = token[order], row[order]
    first = np.flatnonzero(np.concatenate([[True], token[1:] != token[:-1]]))
    count = np.diff(np.append(first, len(token)))
    total = np.zeros((m, m), np.float32)
    for c in range(2, 9):  # rare shingles by pairs, the others by products
        at = first[count == c]
        for x in range(c):
            for y in range(x + 1, c):
                total += np.bincount(row[at + x] * m + row[at + y], minlength=m * m).reshape(m, m) if len(at) > m else 0
                if 0 < len(at) <= m:
                    np.add.at(total, (row[at + x], row[at + y]), 1)
    total += total.T
    often = np.flatnonzero(count > 8)
    for c in range(0, len(often), 1024):
        part = often[c : c + 1024]
        dense = np.zeros((m, len(part)), np.float32)
        size = count[part]
        at = np.repeat(first[part] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
        dense[row[at], np.repeat(np.arange(len(part)), size)] = 1
        total += dense @ dense.T
    ok = total[i, j] >= wanted
    return i[ok], j[ok]


_LINK = "a long, b long"


def _link_rows(a, b) -> pa.RecordBatch:
    return pa.record_batch([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])


def _large_groups(percent: int):
    """Rows sorted by cluster, c1, c2: a cluster's pair of blocks, with node, side, marks, comp (null where pairs of one component count too) and set, to
    links a, b: each node of a linked part with its root."""

    def run(batches):
        key, rows = None, []

        def links():
            if len(rows) > 1:
                node, side, marks, comp, sets = zip(*rows, strict=True)
                apart = None if comp[0] is None else np.array(comp, np.int64)
                i, j = block_links(list(sets), list(marks), np.array(side), percent, apart)
                if len(i):
                    a, b = forest(i, j, len(node))
                    node = np.array(node, np.int64)
                    yield _link_rows(node[a], node[b])

        for batch in pieces(batches):
            for cluster, c1, c2, node, side, marks, comp, s in zip(*(batch.column(c).to_pylist() for c in ("cluster", "c1", "c2", "node", "side", "marks", "comp", "s")), strict=True):
                if (cluster, c1, c2) != key:
                    yield from links()
                    key, rows = (cluster, c1, c2), []
                rows.append((node, side, np.array(marks, np.int64), comp, np.frombuffer(s, np.uint64)))
        yield from links()

    return run


def tree_matches(hub: np.ndarray, others: list[np.ndarray], percent: int = PERCENT) -> np.ndarray:
    """Which sets link with the hub. The sorted sets in lexicographic order are a prefix tree laid out flat: each shares with the one
    before it a beginning, and along that the partial overlap counted before."""
    out = np.zeros(len(others), bool)
    width = 64
    order = sorted(range(len(others)), key=lambda i: others[i].astype(">u8").tobytes())
    before, done, counts = np.zeros(0, np.uint64), 0, np.zeros(1, np.int64)
    for i in order:
        s = others[i]
        m = min(len(s), done)
        differ = np.flatnonzero(s[:m] != before[:m])
        depth = int(differ[0]) if len(differ) else m  # the path shared with the set before
        wanted = int(need(len(hub), len(s), percent))
        path = np.empty(len(s) + 1, np.int64)
        path[: depth + 1] = counts[: depth + 1]
        at = depth
        while True:
            have = int(path[at])
            beyond = len(hub) - (int(np.searchsorted(hub, s[at - 1], "right")) if at else 0)
            if have + min(len(s) - at, beyond) < wanted or at == len(s):
                break
            part = s[at : at + width]
            place = np.searchsorted(hub, part)
            hit = hub[np.minimum(place, len(hub) - 1)] == part
            path[at + 1 : at + 1 + len(part)] = have + np.cumsum(hit)
            at += len(part)
        out[i] = at == len(s) and path[at] >= wanted
        before, done, counts = s, at, path
    return out


def _verify(percent: int):
    """Rows sorted by cluster and salt: node, partners (whose pairs with the node are to be verified), set; to the links a, b."""

    def run(batches):
        key, sets, todo = None, {}, []

        def linked():
            for node, partners in todo:
                near = [p for p in partners if p in sets]
                if node in sets and near:
                    ok = np.array(near, np.int64)[tree_matches(sets[node], [sets[p] for p in near], percent)]
                    if len(ok):
                        yield _link_rows(np.full(len(ok), node), ok)

        for batch in pieces(batches):
            for cluster, salt, node, partners, s in zip(*(batch.column(c).to_pylist() for c in ("cluster", "salt", "node", "partners", "s")), strict=True):
                if (cluster, salt) != key:
                    yield from linked()
                    key, sets, todo = (cluster, salt), {}, []
                sets[node] = np.frombuffer(s, np.uint64)
                if partners:
                    todo.append((node, partners))
        yield from linked()

    return run


def _set_rows(k: int, ranks):
    schema = pa.schema([("g", pa.binary()), ("s", pa.binary())])

    def run(batches):
        for batch in pieces(batches, 500):
            sets = list(sets_of(batch.column("text"), k, ranks.value))
            yield pa.record_batch([pa.array([digest(s) for s in sets], pa.binary()), pa.array([s.tobytes() for s in sets], pa.binary())], schema=schema)

    return run


def sets_for(wanted: DataFrame, docs: DataFrame, k: int, ranks) -> DataFrame:
    """node, s (the set) of the classes in wanted (g, d, node). d is the doc_id that stands for the class, or null; texts of other classes may have it too."""
    small = F.broadcast if wanted.limit(MAX_BROADCAST + 1).count() <= MAX_BROADCAST else (lambda x: x)
    texts = docs.join(small(wanted.select("d")), F.col("doc_id").eqNullSafe(F.col("d")), "left_semi")
    return stored(texts.mapInArrow(lean(_set_rows(k, ranks)), "g binary, s binary").join(small(wanted.select("g", "node")), "g").select("node", "s"), "sets", compression="none")


def with_sets(rows: DataFrame, sets: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """rows (node and others) with the node's set. Sets that no row asks for stay where they are while the nodes asked for can be broadcast."""
    ids = (rows if nodes is None else nodes).select("node").distinct()
    if ids.limit(MAX_BROADCAST + 1).count() <= MAX_BROADCAST:
        sets = sets.join(F.broadcast(ids), "node", "left_semi")
    return rows.join(sets, "node")


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs a < b that link, on the whole sets. A node has at most SMALL partners for each posted shingle."""
    least = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("cluster"))
    led = pairs.join(least, "a")
    led = led.join(led.groupBy("cluster").agg(F.ceil(F.count("*") / TOGETHER).cast("int").alias("salts")), "cluster")
    led = led.select("cluster", F.pmod(F.hash("a"), F.col("salts")).alias("salt"), "a", "b")
    none = F.lit(None).cast("long")
    members = led.select("cluster", "salt", F.col("a").alias("node"), F.col("b").alias("partner")).unionByName(led.select("cluster", "salt", F.col("b").alias("node"), none.alias("partner")))
    members = members.groupBy("cluster", "salt", "node").agg(F.collect_list("partner").alias("partners"))
    nodes = pairs.select(F.col("a").alias("node")).unionAll(pairs.select(F.col("b").alias("node")))
    rows = with_sets(members, sets, nodes).repartition("cluster", "salt").sortWithinPartitions("cluster", "salt", "node")
    return rows.select("cluster", "salt", "node", "partners", "s").mapInArrow(lean(_verify(percent)), _LINK)


def in_blocks(dealt: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links within pairs of blocks. dealt: cluster, c1, c2, side, node, marks, comp."""
    rows = with_sets(dealt, sets).repartition("cluster", "c1", "c2").sortWithinPartitions("cluster", "c1", "c2", "node")
    return rows.select("cluster", "c1", "c2", "node", "side", "marks", "comp", "s").mapInArrow(lean(_large_groups(percent)), _LINK)


def paired(dealt: DataFrame, blocks: DataFrame) -> DataFrame:
    """Each row in every pair of blocks that has its own. blocks: cluster, own, other."""
    dealt = dealt.join(blocks, ["cluster", "own"])
    return dealt.select("cluster", F.least("own", "other").alias("c1"), F.greatest("own", "other").alias("c2"), (F.col("own") > F.col("other")).cast("int").alias("side"), "node", "marks", "comp")


def joined_groups(large: DataFrame, sets: DataFrame, small_links: DataFrame, percent: int) -> DataFrame:
    """node, comp: components by the links of large groups and those of small ones. large: node, marks (its large groups, sorted, without those skipped)."""
    single = large.select("node", F.explode("marks").alias("h"))
    none = F.lit(None).cast("long")
    dealt = single.join(single.groupBy("h").agg(F.min("node").alias("cluster")), "h").groupBy("cluster", "node").agg(F.collect_list("h").alias("marks"))
    sizes = dealt.groupBy("cluster").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("m"))
    dealt = stored(dealt.join(sizes, "cluster").select("cluster", "node", "marks", "m", F.pmod(F.hash("node"), F.col("m")).alias("own")), "dealt")
    first = stored(small_links.unionByName(in_blocks(dealt.select("cluster", F.col("own").alias("c1"), F.col("own").alias("c2"), F.lit(0).alias("side"), "node", "marks", none.alias("comp")), sets, percent)), "first")
    split = dealt.where("m > 1")
    if split.isEmpty():
        comps = connected_components(first)
        drop_stored(dealt)
        drop_stored(first)
        return comps
    # a root is a class that no link of its block points away from; the links of a block point at its nodes from their roots
    roots = split.join(first.select(F.col("b").alias("node")).distinct(), "node", "left_anti")
    rooms = roots.groupBy("cluster").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("r"))
    every = F.explode(F.sequence(F.lit(0), F.col("r") - 1))
    rows = roots.drop("own").join(rooms, "cluster").withColumn("own", F.pmod(F.hash("node", "cluster"), F.col("r")))
    second = stored(in_blocks(paired(rows.select("cluster", "own", "node", "marks", none.alias("comp")), rooms.select("cluster", every.alias("own"), "r").select("cluster", "own", every.alias("other"))), sets, percent), "second")
    comps = connected_components(first.unionByName(second))
    # classes of one cluster in different components; a component keeps to its own blocks where it fills any
    of = split.join(comps.withColumnRenamed("comp", "found"), "node", "left").select("cluster", "node", "marks", F.coalesce("found", "node").alias("comp"))
    count = of.groupBy("cluster", "comp").agg(F.count("*").alias("n"))
    several = count.groupBy("cluster").agg(F.count("*").alias("k"), F.sum(F.when(F.col("n") < BLOCK, F.col("n"))).alias("rest")).where("k > 1")
    count = count.join(several, "cluster")
    # blocks are named by a component and a number; small components share blocks without a name
    full, none = F.col("n") >= BLOCK, F.lit(-1)
    count = count.select("cluster", "comp", F.when(full, F.col("comp")).otherwise(none).alias("of"), F.ceil(F.when(full, F.col("n")).otherwise(F.col("rest")) / BLOCK).cast("int").alias("m"))
    part = F.pmod(F.when(F.col("of") == none, F.hash("comp")).otherwise(F.hash("node")), F.col("m"))
    rows = of.join(count, ["cluster", "comp"]).select("cluster", "node", "marks", "comp", F.struct("of", part.alias("part")).alias("own"))
    rooms = count.select("cluster", "of", F.explode(F.sequence(F.lit(0), F.col("m") - 1)).alias("part")).distinct().select("cluster", F.struct("of", "part").alias("own"))
    both = rooms.join(rooms.withColumnRenamed("own", "other"), "cluster").where((F.col("own.of") == none) | (F.col("own.of") != F.col("other.of")))
    third = stored(in_blocks(paired(rows, both), sets, percent), "third")
    out = comps if third.isEmpty() else connected_components(comps.select(F.col("node").alias("a"), F.col("comp").alias("b")).unionByName(third))
    for x in (dealt, first, second, third, *([comps] if out is not comps else [])):
        drop_stored(x)
    return out


def link_documents(docs: DataFrame, k: int = K, percent: int = PERCENT, hot: int = HOT) -> DataFrame:
    """doc_id, n_shingles, component_id. docs: doc_id, text."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    some = [r[0] for r in docs.select("doc_id").where("doc_id IS NOT NULL").orderBy(F.xxhash64("doc_id"), "doc_id").limit(WORD_SAMPLE).collect()]
    ranks = spark.sparkContext.broadcast(word_ranks([r[0] or "" for r in docs.where(F.col("doc_id").isin(some)).select("text").collect()] if some else []))
    scanned = stored(docs.mapInArrow(lean(_scan(k, ranks)), "kind byte, doc_id long, n long, g binary, h long, c long"), "scan")
    members = scanned.where("kind = 0").select("doc_id", "n", "g")
    counts = scanned.where("kind = 1").groupBy("h").agg(F.sum("c").alias("c")).where(F.col("c") >= COMMON)
    top = counts.orderBy(F.desc("c"), "h").limit(MAX_COMMON).toPandas()
    keys = top["h"].to_numpy(np.int64).view(np.uint64)
    order = np.argsort(keys)
    common = spark.sparkContext.broadcast((keys[order], top["c"].to_numpy(np.int64)[order]))
    postings = docs.mapInArrow(lean(_postings(common, k, percent, ranks, hot)), "h long, salt byte, n int, pos int, g binary")
    met = stored(postings.repartition("h", "salt").sortWithinPartitions("h", "salt", "n", "g").mapInArrow(lean(_small_pairs(percent)), "kind byte, h long, g binary, g2 binary, n int, c int"), "met")
    classes = stored(members.where("n > 0").groupBy("g").agg(F.min("doc_id").alias("d")).withColumn("node", F.monotonically_increasing_id()), "classes")
    one, two = classes.select("g", F.col("node").alias("x")), classes.select(F.col("g").alias("g2"), F.col("node").alias("y"))
    of_large = met.where("kind = 1").groupBy("g").agg(F.count("*").alias("large"))
    # counted under a hash of the pair, which is half as wide; the few that pass fetch their digests back
    # the low bits of that hash are the count that a pair must reach (more than 4094 is written as 4095, which only lets more pairs through)
    key = F.xxhash64("g", "g2").bitwiseAND(F.lit(~4095)).bitwiseOR(F.least(F.col("n"), F.lit(4095)).cast("long"))
    pairs = met.where("kind = 0").select("g", "g2", "c", key.alias("pair"))
    often = pairs.groupBy("pair").agg(F.sum("c").alias("c")).withColumn("least", F.col("pair").bitwiseAND(F.lit(4095)))
    often = stored(often.where(F.col("c") > F.col("least") - DEPTH), "often")
    pairs = pairs.select("g", "g2", "pair").join(F.broadcast(often) if often.count() <= MAX_BROADCAST else often, "pair").dropDuplicates(["g", "g2"])
    pairs = pairs.join(of_large, "g", "left").join(of_large.select(F.col("g").alias("g2"), F.col("large").alias("large2")), "g2", "left")
    pairs = pairs.where(F.col("c") >= F.col("least") - F.least(F.lit(DEPTH - 1), F.coalesce("large", F.lit(0)), F.coalesce("large2", F.lit(0))))
    pairs = stored(pairs.join(one, "g").join(two, "g2").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")), "pairs")
    groups = met.where("kind = 1").groupBy("g", "n").agg(F.array_sort(F.collect_set("h")).alias("marks")).where(F.size("marks") > skipped(F.col("n"), percent)).join(classes.select("g", "node"), "g")
    large = stored(groups.select("node", F.slice("marks", F.lit(1), F.size("marks") - skipped(F.col("n"), percent)).alias("marks")), "large")
    drop_stored(met)
    drop_stored(often)
    nodes = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).unionByName(large.select("node")).distinct()
    sets = sets_for(classes.join(nodes, "node"), docs, k, ranks)
    comps = joined_groups(large, sets, verified(pairs, sets, percent), percent)
    # a component is named by its least doc_id, which need not be that of its least class
    named = comps.join(classes, "node").groupBy("comp").agg(F.min("d").alias("component_id"))
    own = classes.join(comps.join(named, "comp"), "node", "left").select("g", F.coalesce("component_id", "d").alias("component_id"))
    found = members.join(own, "g", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))
    return settled(found, "components", scanned, classes, pairs, large, sets, comps)


def op10_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_documents(table(spark, sf_dir, "documents").select("doc_id", "text"))


def components_sql(docs: str = "documents") -> str:
    """DuckDB SQL: doc_id, n_shingles, component_id."""
    return f"""
    WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM {docs} WHERE text IS NOT NULL),
    s AS (SELECT doc_id, unnest(list_distinct(CASE WHEN len(w) >= {K} THEN list_transform(range(1, len(w) - {K - 2}), lambda i: array_to_string(w[i:i + {K - 1}], ' ')) ELSE [array_to_string(w, ' ')] END)) AS s FROM w WHERE len(w) > 0),
    n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id),
    l AS (SELECT a, b FROM o JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= {PERCENT} * (x.n + y.n - c)),
    e AS (SELECT a AS x, b AS y FROM l UNION ALL SELECT b, a FROM l),
    r AS (SELECT doc_id AS x, doc_id AS y FROM {docs} UNION SELECT r.x, e.y FROM r JOIN e ON r.y = e.x),
    c AS (SELECT x AS doc_id, min(y) AS component_id FROM r GROUP BY x)
    SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, component_id FROM {docs} d LEFT JOIN n ON n.doc_id = d.doc_id JOIN c ON c.doc_id = d.doc_id
    """


def oracle() -> str:
    return components_sql()
