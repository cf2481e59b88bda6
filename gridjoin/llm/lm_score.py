"""Operator 8, scoring by a gated recurrent language model, with corpus counts behind it.

Model: a GRU over words with a class-factored softmax, P(w | state) = P(class | state) P(w | class, state), trained in numpy by truncated
backpropagation: streams of text are read in windows, the state is carried from one to the next, gradients stop at their edge. It learns from all
documents of the learning folds, whole. It starts on the driver with SAMPLE of them (those of least hash of doc_id, which are all where there are no more); then
every task goes on from that start over all learning texts of its partition, and the tasks' models are averaged by tokens. So weights depend
on how the table is partitioned where there are more than SAMPLE documents. Its vocabulary is VOCAB entries: the most frequent words of the learning folds, the end and one
entry for all other words; such a word's probability is that entry's, times its share among other words by corpus counts,
(c + 0.5) / (N' + 0.5 (V' + 1)). A document is scored whole: state is carried over all its windows.

Counts cover every document of the learning folds, exactly:
1. A first scan counts all words, summed in the tasks before they are shuffled. The HOT most frequent may be hot keys; their counts are a broadcast of bounded size.
2. A second scan runs the model, adds the hot words' terms, and posts all other words. Postings leave as packed arrays, one row
   for each batch and bucket of word hashes. A bucket holds about POSTS postings: their number follows the words that the first scan counted. Batches are
   cut at BATCH_BYTES, and the network's outputs are kept for SCORE_ROWS tokens at a time, so a task's memory follows neither rows nor lengths.
3. Each bucket counts its words and returns sums by batch and row; sums meet the documents by batch.

Defined cases: null or empty text is the end token alone. Without learning documents the model is untrained and N = V = 0. A null
doc_id is scored, not learned from, and not held out. Repeated rows are each scored, and counted each. Words of equal count are
ranked by their hash, for the vocabulary. Texts of any length are scored whole. Empty tables give no rows. Other columns
are not read. The table must be a scan (its rows in a fixed order in each partition), as batches are named by partition and number.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, settled, sized, stored, table
from .textnum import slices, utf8, word_hashes

SAMPLE, HOT, POSTS = 1500, 1 << 16, 1_000_000
CLASSES, PER_CLASS, HIDDEN, EMBED = 32, 32, 16, 16
VOCAB = CLASSES * PER_CLASS
STREAMS, WINDOW, EPOCHS = 64, 20, 2
#: Streams at most where all texts are read, windows of a stream at least (while there are as many tokens), tokens held at once, and tasks that sum the models of the others.
MANY, LONG, HELD, SUMS = 512, 100, 1 << 20, 16
#: Most tokens whose states are scored at once, most bytes of a batch's texts (a longer text stands alone).
SCORE_ROWS, BATCH_BYTES = 1 << 16, 1 << 24
#: The end token's hash; no word has it but by chance.
END = np.uint64(0x5851F42D4C957F2D)
LN10 = np.log(10.0)


# ---- the model ----------------------------------------------------------------------------------------------------------------


def fresh_model(seed: int = 8) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(seed)
    r = lambda *s: (rng.standard_normal(s) * 0.15).astype(np.float32)
    z = lambda *s: np.zeros(s, np.float32)
    return {"e": r(VOCAB, EMBED), "wx": r(EMBED, 3 * HIDDEN), "wh": r(HIDDEN, 3 * HIDDEN), "b": z(3 * HIDDEN), "uc": r(CLASSES, HIDDEN), "bc": z(CLASSES), "uw": r(VOCAB, HIDDEN), "bw": z(VOCAB)}


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


def gru_step(m: dict, x: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, tuple]:
    """x: projected input [n, 3H] (reset, update, candidate)."""
    k = HIDDEN
    a = h @ m["wh"]
    gates = _sigmoid(x[:, : 2 * k] + a[:, : 2 * k])
    r, u = gates[:, :k], gates[:, k:]
    c = np.tanh(x[:, 2 * k :] + r * a[:, 2 * k :])
    return u * h + (1 - u) * c, (r, u, c, a[:, 2 * k :])


def _log_softmax(x: np.ndarray) -> np.ndarray:
    x = x - x.max(axis=-1, keepdims=True)
    return x - np.log(np.exp(x).sum(axis=-1, keepdims=True))


def window_loss(m: dict, inputs: np.ndarray, targets: np.ndarray, h0: np.ndarray) -> tuple[float, dict, np.ndarray]:
    """Mean loss (natural log) of a window [T, n], its gradients, and the last state. Words are grouped by class and inputs by word, so that each group is one product or sum."""
    T, n = inputs.shape
    k = HIDDEN
    x = (m["e"] @ m["wx"] + m["b"])[inputs]
    hs, saved = np.empty((T + 1, n, k), x.dtype), []
    hs[0] = h0
    for t in range(T):
        hs[t + 1], s = gru_step(m, x[t], hs[t])
        saved.append(s)
    y = targets.ravel()
    cls = (y // PER_CLASS).astype(np.int16)
    order = np.argsort(cls, kind="stable")
    edge = np.searchsorted(cls[order], np.arange(CLASSES + 1))
    H, cls, own = hs[1:].reshape(T * n, k)[order], cls[order], (y % PER_CLASS)[order]
    g = {}
    loss, dc = _softmax_loss(H @ m["uc"].T + m["bc"], cls)
    g["uc"], g["bc"] = dc.T @ H, dc.sum(axis=0)
    dH = dc @ m["uc"]
    g["uw"], g["bw"] = np.zeros_like(m["uw"]), np.zeros_like(m["bw"])
    for c in range(CLASSES):
        rows, part = slice(edge[c], edge[c + 1]), slice(c * PER_CLASS, (c + 1) * PER_CLASS)
        if edge[c] < edge[c + 1]:
            more, dw = _softmax_loss(H[rows] @ m["uw"][part].T + m["bw"][part], own[rows])
            loss += more
            g["uw"][part], g["bw"][part] = dw.T @ H[rows], dw.sum(axis=0)
            dH[rows] += dw @ m["uw"][part]
    back = np.empty_like(dH)
    back[order] = dH
    dH = (back / len(y)).reshape(T, n, k)
    for c in ("uc", "bc", "uw", "bw"):
        g[c] /= len(y)
    g["wh"], dx, dh = np.zeros_like(m["wh"]), np.empty_like(x), np.zeros_like(h0)
    for t in range(T - 1, -1, -1):
        r, u, c, a = saved[t]
        d = dH[t] + dh
        rest = d * (1 - u)
        dx[t, :, k : 2 * k] = rest * (hs[t] - c) * u
        dx[t, :, 2 * k :] = dcand = rest * (1 - c * c)
        dx[t, :, :k] = dcand * a * r * (1 - r)
        da = dx[t].copy()
        da[:, 2 * k :] *= r
        g["wh"] += hs[t].T @ da
        dh = d * u + da @ m["wh"].T
    words = inputs.ravel().astype(np.int16)
    order = np.argsort(words, kind="stable")
    words = words[order]
    first = np.flatnonzero(np.concatenate([[True], words[1:] != words[:-1]]))
    by_word = np.zeros((VOCAB, 3 * k), x.dtype)
    by_word[words[first]] = np.add.reduceat(dx.reshape(T * n, 3 * k)[order], first, axis=0)
    g["e"], g["wx"], g["b"] = by_word @ m["wx"].T, m["e"].T @ by_word, by_word.sum(axis=0)
    return float(loss / len(y)), g, hs[-1]


def _softmax_loss(x: np.ndarray, at: np.ndarray) -> tuple[float, np.ndarray]:
    """Summed loss of the entries ``at`` under a softmax of each row, and its gradient."""
    rows = np.arange(len(at))
    x -= x.max(axis=1, keepdims=True)
    chosen = x[rows, at]
    np.exp(x, out=x)
    total = x.sum(axis=1)
    x /= total[:, None]
    x[rows, at] -= 1
    return float((np.log(total) - chosen).sum()), x


class Adam:
    def __init__(self, m: dict, rate: float):
        self.m, self.rate, self.step = m, rate, 0
        self.first, self.second = ({k: np.zeros_like(v) for k, v in m.items()} for _ in range(2))

    def read(self, x: np.ndarray, y: np.ndarray) -> None:
        """Windows of x, y [length, streams] in turn; the state is carried from one to the next."""
        h = np.zeros((x.shape[1], HIDDEN), np.float32)
        for t in range(0, len(x), WINDOW):
            _, g, h = window_loss(self.m, x[t : t + WINDOW], y[t : t + WINDOW], h)
            self.step += 1
            for k in self.m:
                self.first[k] += 0.1 * (g[k] - self.first[k])
                self.second[k] += 0.01 * (g[k] * g[k] - self.second[k])
                self.m[k] -= (self.rate * (self.first[k] / (1 - 0.9**self.step)) / (np.sqrt(self.second[k] / (1 - 0.99**self.step)) + 1e-8)).astype(np.float32)


def _streams(ids: np.ndarray, streams: int) -> tuple[np.ndarray, np.ndarray]:
    length = (len(ids) - 1) // streams
    return ids[: streams * length].reshape(streams, length).T, ids[1 : streams * length + 1].reshape(streams, length).T


def train(ids: np.ndarray, seed: int = 8, epochs: int = EPOCHS, rate: float = 0.01) -> dict[str, np.ndarray]:
    """ids: the sample's tokens with an end after each document. Truncated backpropagation with carried state, by Adam."""
    m = fresh_model(seed)
    if (len(ids) - 1) // STREAMS < 2:
        return m
    adam = Adam(m, rate)
    for _ in range(epochs):
        adam.read(*_streams(ids, STREAMS))
    return m


def read_on(adam: Adam, ids: np.ndarray, last: bool) -> np.ndarray:
    """Training goes on over all of ids in many streams; returns what is left for the next tokens to follow, after the last ones nothing that could be predicted."""
    while len(ids) > (1 if last else HELD):
        streams = max(1, min(MANY, (len(ids) - 1) // (LONG * WINDOW)))
        x, y = _streams(ids, streams)
        adam.read(x, y)
        ids = ids[x.size :]
    return ids


def _trained(state):
    """One row for each task: its model after all its texts, as a sum weighted by tokens."""
    schema = pa.schema([("at", pa.int32()), ("n", pa.int64()), ("model", pa.binary())])

    def run(batches):
        keys, vocab, m, other_id = state.value
        m = {k: v.copy() for k, v in m.items()}
        adam, left, n = Adam(m, 0.003), np.zeros(0, np.int64), 0
        for batch in sized(batches, "text", BATCH_BYTES):
            for _, _, h, _ in tokens(batch.column("text")):
                where = place(keys, h)
                n += len(h)
                left = read_on(adam, np.concatenate([left, np.where(where >= 0, vocab[where], other_id)]), False)
        if n:
            read_on(adam, left, True)
            yield pa.record_batch([pa.array([TaskContext.get().partitionId() % SUMS], pa.int32()), pa.array([n]), pa.array([(_flat(m) * n).tobytes()], pa.binary())], schema=schema)

    return run


def _flat(m: dict) -> np.ndarray:
    return np.concatenate([m[k].ravel() for k in sorted(m)]).astype(np.float64)


def _summed(batches):
    total, n = None, 0
    for batch in batches:
        for more, blob in zip(batch.column("n").to_pylist(), batch.column("model"), strict=True):
            x = np.frombuffer(blob.as_buffer(), np.float64)
            total, n = (x.copy() if total is None else total + x), n + more
    if n:
        yield pa.record_batch([pa.array([n]), pa.array([total.tobytes()], pa.binary())], names=["n", "model"])


def train_on(texts: DataFrame, keys: np.ndarray, vocab: np.ndarray, m: dict) -> dict[str, np.ndarray]:
    """The model after all texts: each task goes on from m over all its own, and their models are averaged by tokens, in SUMS tasks first."""
    state = texts.sparkSession.sparkContext.broadcast((keys, vocab, m, VOCAB - 1))
    rows = texts.mapInArrow(lean(_trained(state)), "at int, n long, model binary").repartitionById(SUMS, F.col("at")).mapInArrow(_summed, "n long, model binary").collect()
    n = sum(r["n"] for r in rows)
    if not n:
        return m
    mean, out, at = sum(np.frombuffer(r["model"], np.float64) for r in sorted(rows, key=lambda r: (r["n"], bytes(r["model"])))) / n, {}, 0
    for k in sorted(m):
        out[k] = mean[at : at + m[k].size].reshape(m[k].shape).astype(np.float32)
        at += m[k].size
    return out


def token_logs(m: dict, states: np.ndarray, targets: np.ndarray) -> np.ndarray:
    """Natural log probabilities of targets; tokens are grouped by class, so each class is one product."""
    cls = targets // PER_CLASS
    x = states @ m["uc"].T + m["bc"]
    out = x[np.arange(len(x)), cls] - _log_sum(x)
    order = np.argsort(cls, kind="stable")
    edge = np.searchsorted(cls[order], np.arange(CLASSES + 1))
    for c in range(CLASSES):
        own = order[edge[c] : edge[c + 1]]
        if len(own):
            part = slice(c * PER_CLASS, (c + 1) * PER_CLASS)
            x = states[own] @ m["uw"][part].T + m["bw"][part]
            out[own] += x[np.arange(len(x)), targets[own] - c * PER_CLASS] - _log_sum(x)
    return out


def _log_sum(x: np.ndarray) -> np.ndarray:
    """Scores of this model are small enough for float32 without taking out the maximum first; checked by clipping."""
    return np.log(np.exp(np.clip(x, -80, 80)).sum(axis=1))


def score_documents(m: dict, ids: np.ndarray, at: np.ndarray, start: int) -> np.ndarray:
    """Log10 probability of each document; ids has its tokens, the end included; start is the id that stands before the first."""
    n = len(at) - 1
    size = np.diff(at)
    order = np.argsort(-size, kind="stable")
    size, first = size[order], at[:-1][order]
    project = m["e"] @ m["wx"] + m["b"]
    h = np.zeros((n, HIDDEN), np.float32)
    last = np.full(n, start, np.int64)
    total = np.zeros(n)
    longest = int(size[0]) if n else 0
    alive = np.searchsorted(-size, -np.arange(longest), "left")  # documents with more than t tokens
    t0 = 0
    while t0 < longest:
        states, targets, owner = [], [], []
        until = min(longest, t0 + max(1, SCORE_ROWS // int(alive[t0])))
        for t in range(t0, until):
            k = int(alive[t])
            h[:k], _ = gru_step(m, project[last[:k]], h[:k])
            y = ids[first[:k] + t]
            states.append(h[:k].copy())
            targets.append(y)
            owner.append(np.arange(k))
            last[:k] = y
        logs = token_logs(m, np.concatenate(states), np.concatenate(targets))
        k = int(alive[t0])
        total[:k] += np.bincount(np.concatenate(owner), weights=logs, minlength=k)
        t0 = until
    out = np.empty(n)
    out[order] = total / LN10
    return out


# ---- counting -----------------------------------------------------------------------------------------------------------------


def tokens(column) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Pieces of the texts: first, last, token hashes with an END after each text, where each text's tokens begin."""
    data, offsets = utf8(column)
    for i, j in slices(offsets):
        h, at = word_hashes(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
        out = np.insert(h, at[1:], END)
        yield i, j, out, at + np.arange(len(at))


def place(keys: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Places of h in the sorted keys, -1 where missing."""
    if not len(keys):
        return np.full(len(h), -1)
    at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
    return np.where(keys[at] == h, at, -1)


def _word_counts(batches):
    """word, c: tokens by hash (as a signed number), summed over a task's texts while they are few."""
    schema = pa.schema([("word", pa.int64()), ("c", pa.int64())])
    keys, counts = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    for batch in sized(batches, "text", BATCH_BYTES):
        for _, _, h, _ in tokens(batch.column("text")):
            new, c = np.unique(h, return_counts=True)
            keys, at = np.unique(np.concatenate([keys, new]), return_inverse=True)
            counts = np.bincount(at.ravel(), weights=np.concatenate([counts, c])).astype(np.int64)
            if len(keys) > POSTS:
                yield pa.record_batch([pa.array(keys.view(np.int64)), pa.array(counts)], schema=schema)
                keys, counts = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    if len(keys):
        yield pa.record_batch([pa.array(keys.view(np.int64)), pa.array(counts)], schema=schema)


_ROWS = "kind int, bucket int, batch long, ids binary, a binary, b binary, c binary, d binary, e binary, f binary"


def _schema():
    return pa.schema([("kind", pa.int32()), ("bucket", pa.int32()), ("batch", pa.int64()), *((x, pa.binary()) for x in ("ids", "a", "b", "c", "d", "e", "f"))])


def _row(kind: int, bucket: int, batch: int, *arrays: np.ndarray) -> pa.RecordBatch:
    blobs = [pa.array([x.tobytes()], pa.binary()) for x in arrays] + [pa.array([None], pa.binary())] * (7 - len(arrays))
    return pa.record_batch([pa.array([kind], pa.int32()), pa.array([bucket], pa.int32()), pa.array([batch], pa.int64()), *blobs], schema=_schema())


def _scan(state, buckets: int):
    """kind 0: a batch's documents (ids, nulls, tokens, known hot tokens, model score, hot terms, hot terms of other words, other tokens);
    kind 1: a bucket's postings of a batch (hash, row, times, learning)."""

    def run(batches):
        keys, logs, counts, vocab, m, end_id, other_id = state.value
        part = TaskContext.get().partitionId()
        for number, batch in enumerate(sized(batches, "text", BATCH_BYTES)):
            name = part << 32 | number
            n = batch.num_rows
            learn = batch.column("learn").to_numpy(zero_copy_only=False).astype(bool)
            all_ids, sizes, rare_h, rare_row = [], [], [], []
            known, hot_sum, other_sum, other_n = np.zeros(n, np.int64), np.zeros(n), np.zeros(n), np.zeros(n, np.int64)
            for i, j, h, at in tokens(batch.column("text")):
                size = np.diff(at)
                row = np.repeat(np.arange(i, j), size)
                where = place(keys, h)
                hot = where >= 0
                ids = np.where(hot, vocab[where], other_id).astype(np.int16)
                w, r = where[hot], row[hot]
                known += np.bincount(r, weights=counts[w] > 0, minlength=n).astype(np.int64)
                hot_sum += np.bincount(r, weights=logs[w], minlength=n)
                out = ids == other_id
                other_n += np.bincount(row[out], minlength=n)
                both = out & hot
                other_sum += np.bincount(row[both], weights=logs[where[both]], minlength=n)
                rare_h.append(h[~hot])
                rare_row.append(row[~hot].astype(np.int32))
                all_ids.append(ids)
                sizes.append(size)
            size = np.concatenate(sizes) if sizes else np.zeros(0, np.int64)
            ids = np.concatenate(all_ids) if all_ids else np.zeros(0, np.int16)
            score = score_documents(m, ids, np.concatenate([[0], np.cumsum(size)]), end_id)
            doc = batch.column("doc_id")
            doc_ids = doc.fill_null(0).to_numpy().astype(np.int64)
            null = doc.is_null().to_numpy(zero_copy_only=False)
            flags = null.astype(np.int64) * 2 + batch.column("held_out").to_numpy(zero_copy_only=False).astype(np.int64)
            yield _row(0, name % buckets, name, doc_ids, np.concatenate([flags, size, known, other_n]), score, hot_sum, other_sum)
            h, r = (np.concatenate(x) for x in (rare_h, rare_row)) if rare_h else (np.zeros(0, np.uint64), np.zeros(0, np.int32))
            bucket = (h >> np.uint64(40)).astype(np.int64) % buckets
            order = np.lexsort((r, h, bucket))
            h, r, bucket = h[order], r[order], bucket[order]
            first = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (r[1:] != r[:-1])])) if len(h) else np.zeros(0, np.int64)
            times = np.diff(np.append(first, len(h))).astype(np.int32)
            h, r, bucket = h[first], r[first], bucket[first]
            edge = np.searchsorted(bucket, np.arange(buckets + 1))
            for b in range(buckets):
                x, y = edge[b], edge[b + 1]
                if x < y:
                    yield _row(1, b, name, h[x:y], r[x:y], np.where(learn[r[x:y]], times[x:y], -times[x:y]))

    return run


def _count(batches):
    """Rows of one bucket after another. Postings become sums by batch and row (kind 1); the bucket's distinct words are kind 2."""

    def finish(bucket: int, rows: list):
        h = np.concatenate([r[1] for r in rows])
        times = np.concatenate([r[3] for r in rows])
        keys, inverse = np.unique(h, return_inverse=True)
        c = np.bincount(inverse.ravel(), weights=np.maximum(times, 0), minlength=len(keys))
        term = (np.log10(c + 0.5))[inverse.ravel()] * np.abs(times)
        known = np.where(c[inverse.ravel()] > 0, np.abs(times), 0)
        yield _row(2, bucket, 0, np.array([(c > 0).sum()], np.int64))
        at = 0
        for name, x, row, _ in rows:
            part = slice(at, at + len(x))
            at += len(x)
            docs, own = np.unique(row, return_inverse=True)
            yield _row(1, bucket, name, docs, np.bincount(own.ravel(), weights=term[part]), np.bincount(own.ravel(), weights=known[part]).astype(np.int32))

    held, rows = None, []
    for batch in batches:
        for i in range(batch.num_rows):
            one = batch.slice(i, 1)
            if one.column("kind")[0].as_py() == 0:
                yield one
                continue
            bucket = one.column("bucket")[0].as_py()
            if bucket != held and rows:
                yield from finish(held, rows)
                rows = []
            held = bucket
            rows.append((one.column("batch")[0].as_py(), *(np.frombuffer(one.column(x)[0].as_py(), t) for x, t in (("ids", np.uint64), ("a", np.int32), ("b", np.int32)))))
    if rows:
        yield from finish(held, rows)


def _merge(batches):
    """Rows sorted by batch and kind: the documents of a batch, then their sums."""
    names = ("doc_id", "held_out", "n_tokens", "n_known", "model", "logs", "other_logs", "other_n")
    types = (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.int64())
    schema = pa.schema(list(zip(names, types, strict=True)))
    docs = None

    def out():
        if docs is not None:
            ids, flags, size, known, other_n, score, logs, other = docs
            yield pa.record_batch([pa.array(ids, mask=flags >= 2), pa.array((flags & 1).astype(bool)), pa.array(size), pa.array(known), pa.array(score), pa.array(logs), pa.array(other), pa.array(other_n)], schema=schema)

    for batch in batches:
        for kind, *blobs in zip(*(batch.column(c).to_pylist() for c in ("kind", "ids", "a", "b", "c", "d")), strict=True):
            if kind == 0:
                yield from out()
                ids = np.frombuffer(blobs[0], np.int64)
                flags, size, known, other_n = np.frombuffer(blobs[1], np.int64).reshape(4, len(ids))
                docs = ids, flags, size, known.copy(), other_n, *(np.frombuffer(x, np.float64).copy() for x in blobs[2:5])
            else:
                row, term = np.frombuffer(blobs[0], np.int32), np.frombuffer(blobs[1], np.float64)
                docs[3][row] += np.frombuffer(blobs[2], np.int32)
                docs[6][row] += term
                docs[7][row] += term
    yield from out()


def vocabulary(keys: np.ndarray, count: np.ndarray, hot: int = HOT) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes of the most frequent words (END among them) of sorted keys, and their vocabulary ids (the last id: other words). The most frequent VOCAB
    or more of a corpus give the same ids as all of its words."""
    top = np.lexsort((keys, -count))[:hot]
    if END not in keys[top]:
        top[-1] = np.searchsorted(keys, END)
    ids = np.full(len(keys), VOCAB - 1)
    ids[top[: VOCAB - 1]] = np.arange(min(len(top), VOCAB - 1))
    end = int(np.searchsorted(keys, END))
    if ids[end] == VOCAB - 1:
        ids[top[VOCAB - 2]], ids[end] = VOCAB - 1, VOCAB - 2
    chosen = np.sort(top)
    return keys[chosen], ids[chosen]


def token_ids(texts: list[str], keys: np.ndarray, vocab: np.ndarray) -> np.ndarray:
    at = [place(keys, h) for _, _, h, _ in tokens(pa.array(texts, pa.string()))]
    at = np.concatenate(at) if at else np.zeros(0, np.int64)
    return np.where(at >= 0, vocab[at], VOCAB - 1)


def learn_vocabulary(texts: list[str], hot: int = HOT) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """vocabulary() of the words of texts, and the token ids."""
    every = [h for _, _, h, _ in tokens(pa.array(texts, pa.string()))]
    keys, count = np.unique(np.append(np.concatenate(every) if every else np.zeros(0, np.uint64), END), return_counts=True)
    keys, vocab = vocabulary(keys, count, hot)
    return keys, vocab, token_ids(texts, keys, vocab)


def score_texts(docs: DataFrame, sample: int = SAMPLE, hot: int = HOT, posts: int = POSTS) -> DataFrame:
    """docs: doc_id, text, learn (whether counts and model may use it), held_out."""
    spark = docs.sparkSession
    rows = docs.where("learn").select(F.xxhash64("doc_id").alias("r"), "doc_id").orderBy("r", "doc_id").limit(sample).collect()
    found = sorted((r["doc_id"], r["text"] or "") for r in docs.where("learn").where(F.col("doc_id").isin([r["doc_id"] for r in rows])).select("doc_id", "text").collect()) if rows else []
    learning = docs.where("learn").select("text")
    words = stored(learning.mapInArrow(lean(_word_counts), "word long, c long").groupBy("word").agg(F.sum("c").alias("c")), "words")
    total = words.agg(F.sum("c")).first()[0] or 0
    # words of equal count by their hash, which is unsigned
    top = words.orderBy(F.desc("c"), F.col("word").bitwiseXOR(F.lit(-(1 << 63)))).limit(max(hot, VOCAB)).collect()
    count = {r["word"] % (1 << 64): r["c"] for r in top}
    end = int(END)
    if end not in count:
        count[end] = words.where(F.col("word") == int(END.view(np.int64))).agg(F.sum("c")).first()[0] or 0
    every = np.array(sorted(count), np.uint64)
    keys, vocab = vocabulary(every, np.array([count[int(k)] + (int(k) == end) for k in every], np.int64), hot)
    counts = np.array([count[int(k)] for k in keys], np.int64)
    model = train(token_ids([t for _, t in found], keys, vocab))
    n_docs, n_learn = docs.agg(F.count("*"), F.count_if("learn")).first()
    if n_learn > len(found):
        model = train_on(learning, keys, vocab, model)
    end_id = int(vocab[np.searchsorted(keys, END)])
    state = spark.sparkContext.broadcast((keys, np.log10(counts + 0.5), counts, vocab, model, end_id, VOCAB - 1))
    buckets = max(16, -(-(total - int(counts.sum())) * n_docs // (max(1, n_learn) * posts)))
    posted = docs.mapInArrow(lean(_scan(state, buckets)), _ROWS).repartitionById(buckets, F.col("bucket")).sortWithinPartitions("bucket", "kind")
    counted = stored(posted.mapInArrow(lean(_count), _ROWS), "counted")
    rare = counted.where("kind = 2").select("ids").mapInArrow(_distinct, "v long").agg(F.sum("v")).first()[0] or 0
    v = int((counts > 0).sum()) + int(rare)
    inside = vocab < VOCAB - 1
    n_other, v_other = total - int(counts[inside].sum()), v - int((counts[inside] > 0).sum())
    merged = counted.where("kind < 2").repartition("batch").sortWithinPartitions("batch", "kind").mapInArrow(lean(_merge), "doc_id long, held_out boolean, n_tokens long, n_known long, model double, logs double, other_logs double, other_n long")
    scores = merged.select(
        "doc_id",
        "held_out",
        "n_tokens",
        "n_known",
        F.lit(total).cast("long").alias("train_tokens"),
        (F.col("logs") - F.col("n_tokens") * F.lit(float(np.log10(total + 0.5 * (v + 1))))).alias("base_score"),
        (F.col("model") + F.col("other_logs") - F.col("other_n") * F.lit(float(np.log10(n_other + 0.5 * (v_other + 1))))).alias("score"),
    )
    return settled(scores, "scores", counted, words)


def _distinct(batches):
    for batch in batches:
        yield pa.record_batch([pa.array([int(np.frombuffer(x, np.int64)[0]) for x in batch.column("ids").to_pylist()], pa.int64())], names=["v"])


def op8_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    fold = F.crc32(F.col("doc_id").cast("string")) % 5
    return score_texts(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), F.coalesce(fold != 1, F.lit(False)).alias("learn"), F.coalesce(fold == 1, F.lit(False)).alias("held_out")))
