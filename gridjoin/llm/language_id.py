"""Operator 7, language identification by a linear-chain conditional random field over words.

Each word gets a label, by affix and n-gram features (byte n-grams of 2 to 4 over the word with its boundary marks, hashed), a
lexicon feature (the word itself, where the sample has it LEXICON_MIN times) and learned transitions. Marginals come from forward-backward
over windows of WINDOW words, so code-switched text gets a label for every word; a document's language is the label with the
largest sum of marginals over all its words, its score that label's share.

Learning: a bounded sample, PER_LANG documents of each language (those of least hash of doc_id among the rows in the
learning folds) and at most SEGMENTS segments of 16 words of each language. Training sequences join segments of one or of several
languages, so the transitions have seen switches. The objective is the log-likelihood with an L2 term, by Adam on the full sample, with a
fixed seed. Languages are a bounded set (checked), so their list may be collected.

Prediction is one scan without a shuffle: words are hashed from the Arrow buffers, features are made once for the distinct words of a
chunk of about CHUNK bytes, and forward-backward runs over all windows of the chunk together.

Defined cases: null text and text without a letter are ``und`` with score 0. A table without labelled rows in the learning folds gives
``und`` throughout. Rows with null doc_id are predicted but not learned from, held_out is false. Repeated rows are each predicted.
Of languages of equal mass the first by name is predicted. Texts of any length are labelled whole, in windows. Other columns pass through unread, but
for lang_pred and score, which are replaced.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, pieces, small_batches, table
from .textnum import segment_hashes, slices, utf8

PER_LANG, SEGMENTS, SEGMENT = 150, 3000, 16
LEXICON_MIN, BUCKETS, WINDOW, CHUNK = 3, 1 << 16, 256, 1 << 21
MAX_LANGS = 500
_LETTER = np.zeros(256, bool)
_LETTER[65:91] = _LETTER[97:123] = True
_LETTER[128:] = True


def letters(data: np.ndarray) -> np.ndarray:
    """Lower case for A-Z and for the Latin-1 capitals, which are C3 80 to C3 9E in UTF-8 (C3 97 is a sign)."""
    low = data.copy()
    low[(low >= 65) & (low <= 90)] += 32
    if len(low) > 1:
        second = np.flatnonzero((data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E) & (data[1:] != 0x97)) + 1
        low[second] += 32
    return low


def words_of(data: np.ndarray, offsets: np.ndarray):
    """Bytes in lower case; start, end, hash of each run of letters; where each text's words begin."""
    low = letters(data)
    return low, *segment_hashes(low, _LETTER[low], offsets)


def distinct_words(low: np.ndarray, starts: np.ndarray, ends: np.ndarray, h: np.ndarray):
    """Hashes, bytes and sizes of the distinct words, and each word's place among them."""
    keys, first, inverse = np.unique(h, return_index=True, return_inverse=True)
    size = ends[first] - starts[first]
    begin = np.cumsum(size) - size
    take = np.repeat(starts[first] - begin, size) + np.arange(int(size.sum()))
    return keys, low[take], size, inverse.ravel()


def feature_ids(text: np.ndarray, size: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """For n = 2, 3, 4 the hashed n-gram that begins at each byte of the marked words (0 where it would cross the end), and where words begin."""
    n = len(size)
    begin = np.cumsum(size + 2) - size - 2
    marked = np.full(int((size + 2).sum()) + 4, 2, np.uint32)
    marked[begin] = 1
    inner = np.ones(len(marked) - 4, bool)
    inner[begin] = inner[begin + size + 1] = False
    marked[:-4][inner] = text.astype(np.uint32) + 3
    left = np.repeat(begin + size + 2, size + 2) - np.arange(len(marked) - 4) if n else np.zeros(0, np.int64)
    out, code = [], marked[:-4].copy()
    for k in (1, 2, 3):
        code = code * np.uint32(0x01000193) + marked[k : len(marked) - 4 + k]
        ids = ((code ^ (code >> np.uint32(15))) * np.uint32(0x85EBCA6B) >> np.uint32(8)) % np.uint32(BUCKETS - 1) + np.uint32(1)
        out.append(np.where(left > k, ids, 0).astype(np.int64))
    return out, begin


def emissions(model: dict, keys: np.ndarray, text: np.ndarray, size: np.ndarray) -> np.ndarray:
    """A row of label scores for each distinct word."""
    ids, begin = feature_ids(text, size)
    out = np.zeros((len(size), model["w"].shape[1]), np.float32)
    if len(size):
        for x in ids:
            out += np.add.reduceat(model["w"][x], begin, axis=0)
        if len(model["lexicon"]):
            at = np.minimum(np.searchsorted(model["lexicon"], keys), len(model["lexicon"]) - 1)
            known = model["lexicon"][at] == keys
            out[known] += model["v"][at[known]]
    return out


def forward_backward(e: np.ndarray, index: np.ndarray, size: np.ndarray, trans: np.ndarray, start: np.ndarray, pairs: bool = False):
    """Marginals of windows. e: scores of distinct words; index[b, t]: the word at place t of window b; size: words of each window, not rising.

    Returns marginals [b, t, label], and with pairs also the expected transitions and the log of each window's partition sum."""
    n, width = index.shape
    labels = e.shape[1]
    top = e.max(axis=1)
    p, a = np.exp(e - top[:, None]), np.exp(trans)
    alive = (size[None, :] > np.arange(width)[:, None]).sum(axis=1)
    fw = np.zeros((width, n, labels), np.float32)
    logs = np.zeros(n)
    x = p[index[:, 0]] * np.exp(start)
    scale = x.sum(axis=1, keepdims=True)
    fw[0] = x / scale
    logs += np.log(scale[:, 0]) + top[index[:, 0]]
    for t in range(1, width):
        m = alive[t]
        x = (fw[t - 1, :m] @ a) * p[index[:m, t]]
        scale = x.sum(axis=1, keepdims=True)
        fw[t, :m] = x / scale
        if pairs:
            logs[:m] += np.log(scale[:, 0]) + top[index[:m, t]]
    back = np.ones((n, labels), np.float32)
    expected = np.zeros((labels, labels))
    for t in range(width - 2, -1, -1):
        m = alive[t + 1]
        y = p[index[:m, t + 1]] * back[:m]
        if pairs:
            z = fw[t, :m].T[:, None, :] * a[:, :, None] * y.T[None, :, :]
            expected += (z / z.sum(axis=(0, 1))).sum(axis=2)
        y = y @ a.T
        back[:m] = y / y.sum(axis=1, keepdims=True)
        x = fw[t, :m] * back[:m]
        fw[t, :m] = x / x.sum(axis=1, keepdims=True)
    return fw.transpose(1, 0, 2), expected, logs


def windows(at: np.ndarray, width: int = WINDOW):
    """Windows of at most width words in each text: text, first word, size; longest first."""
    n = np.diff(at)
    count = -(-n // width)
    text = np.repeat(np.arange(len(n)), count)
    part = np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)
    first = at[:-1][text] + part * width
    size = np.minimum(width, at[1:][text] - first)
    order = np.argsort(-size, kind="stable")
    return text[order], first[order], size[order]


def train(texts: list[str], langs: list[str], seed: int = 7, rounds: int = 40) -> dict:
    """A model from labelled texts."""
    names = sorted(set(langs))
    rng = np.random.default_rng(seed)
    data, offsets = utf8(pa.array(texts, pa.string()))
    low, starts, ends, h, at = words_of(data, offsets)
    keys, text, size, word = distinct_words(low, starts, ends, h)
    doc, first, length = windows(at, SEGMENT)
    label = np.array([names.index(x) for x in langs], np.int64)[doc] if len(langs) else np.zeros(0, np.int64)
    model = {"names": names, "w": np.zeros((BUCKETS, len(names)), np.float32), "trans": np.zeros((len(names), len(names)), np.float32), "start": np.zeros(len(names), np.float32), "lexicon": np.zeros(0, np.uint64), "v": np.zeros((0, len(names)), np.float32)}
    chosen = np.concatenate([rng.permutation(np.flatnonzero(label == k))[:SEGMENTS] for k in range(len(names))]) if names else np.zeros(0, np.int64)
    if len(names) < 2 or not len(chosen):
        return model
    rows, gold = [], []
    pool = rng.permutation(chosen)
    while len(pool):  # sequences of four segments: of one language, or of any
        if rng.random() < 0.5:
            mine = label[pool] == label[pool[0]]
            four = pool[mine][:4]
        else:
            four = pool[:4]
        pool = pool[~np.isin(pool, four)]
        ids = np.concatenate([np.arange(first[s], first[s] + length[s]) for s in four])
        rows.append(word[ids])
        gold.append(np.repeat(label[four], length[four]))
    order = np.argsort([-len(r) for r in rows], kind="stable")
    width = max(map(len, rows))
    index, truth, count = np.zeros((len(rows), width), np.int64), np.full((len(rows), width), -1), np.array([len(rows[i]) for i in order])
    for i, k in enumerate(order):
        index[i, : len(rows[k])], truth[i, : len(rows[k])] = rows[k], gold[k]
    real = truth >= 0
    seen = np.bincount(index[real], minlength=len(keys))
    lexical = np.flatnonzero(seen >= LEXICON_MIN)
    model["lexicon"], model["v"] = keys[lexical], np.zeros((len(lexical), len(names)), np.float32)
    ids, _ = feature_ids(text, size)
    owner = np.repeat(np.arange(len(size)), size + 2)
    L = len(names)
    hot = np.zeros((len(keys), L), np.float64)
    np.add.at(hot, (index[real], truth[real]), 1)
    moves = np.zeros((L, L))
    both = real[:, 1:] & real[:, :-1]
    np.add.at(moves, (truth[:, :-1][both], truth[:, 1:][both]), 1)
    begins = np.bincount(truth[:, 0], minlength=L)
    total = real.sum()
    state = {k: [np.zeros_like(model[k]), np.zeros_like(model[k])] for k in ("w", "v", "trans", "start")}
    for step in range(1, rounds + 1):
        e = emissions(model, keys, text, size)
        marg, expected, _ = forward_backward(e, index, count, model["trans"], model["start"], pairs=True)
        mass = np.zeros((len(keys), L))
        for k in range(L):
            mass[:, k] = np.bincount(index[real], weights=marg[:, :, k][real], minlength=len(keys))
        diff = (hot - mass) / total
        grad = {"v": diff[lexical], "trans": (moves - expected) / total, "start": (begins - marg[:, 0].sum(axis=0)) / total}
        w = np.zeros_like(model["w"], np.float64)
        for x in ids:
            for k in range(L):
                w[:, k] += np.bincount(x, weights=diff[owner, k], minlength=BUCKETS)
        w[0] = 0
        grad["w"] = w
        for k, (m, v) in state.items():
            g = grad[k] - 1e-6 * model[k]
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            model[k] += (0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
        model["w"][0] = 0
    return model


def predict(model: dict, column) -> tuple[list[str], np.ndarray]:
    """The language and score of each text."""
    n, names = len(column), model["names"]
    data, offsets = utf8(column)
    best, score = np.full(n, -1), np.zeros(n)
    for i, j in slices(offsets, CHUNK):
        low, starts, ends, h, at = words_of(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
        if not len(h) or not names:
            continue
        keys, text, size, word = distinct_words(low, starts, ends, h)
        e = emissions(model, keys, text, size)
        doc, first, count = windows(at)
        index = word[np.minimum(first[:, None] + np.arange(int(count[0])), len(word) - 1)]
        marg, _, _ = forward_backward(e, index, count, model["trans"], model["start"])
        marg[np.arange(index.shape[1]) >= count[:, None]] = 0
        mass = np.zeros((j - i, len(names)))
        np.add.at(mass, doc, marg.sum(axis=1))
        full = np.diff(at) > 0
        best[i:j][full] = mass[full].argmax(axis=1)
        score[i:j][full] = mass[full].max(axis=1) / mass[full].sum(axis=1)
        ascii_letter = np.zeros(len(low) + 1, np.int64)
        np.cumsum((low >= 97) & (low <= 122), out=ascii_letter[1:])
        own = offsets[i : j + 1] - offsets[i]
        for k in np.flatnonzero(full & (ascii_letter[own[1:]] == ascii_letter[own[:-1]])):
            if not any(c.isalpha() for c in column[i + int(k)].as_py()):
                best[i + k], score[i + k] = -1, 0
    return [names[b] if b >= 0 else "und" for b in best], np.clip(score, 0, 1)


def learning_sample(docs: DataFrame, per_lang: int = PER_LANG, max_langs: int = MAX_LANGS) -> tuple[list[str], list[str]]:
    """Texts and languages of at most per_lang documents of each language, those of least hash of doc_id. More than max_langs languages are an error."""
    rows = docs.where("lang IS NOT NULL AND text IS NOT NULL AND doc_id IS NOT NULL")
    langs = [r[0] for r in rows.select("lang").distinct().limit(max_langs + 1).collect()]
    if len(langs) > max_langs:
        raise ValueError(f"more than {max_langs} languages")
    wanted = [r[0] for lang in sorted(langs) for r in rows.where(F.col("lang") == lang).select("doc_id", F.xxhash64("doc_id").alias("r")).orderBy("r", "doc_id").limit(per_lang).collect()]
    found = sorted(((r["doc_id"], r["lang"], r["text"]) for r in rows.where(F.col("doc_id").isin(wanted)).select("doc_id", "lang", "text").collect()) if wanted else [])
    return [t for _, _, t in found], [lang for _, lang, _ in found]


def identify(docs: DataFrame, learn_from: DataFrame, per_lang: int = PER_LANG, max_langs: int = MAX_LANGS) -> DataFrame:
    """The rows of docs with lang_pred and score added; columns of docs with these names are replaced. learn_from: doc_id, text, lang."""
    small_batches(docs.sparkSession)
    docs = docs.drop("lang_pred", "score")
    model = docs.sparkSession.sparkContext.broadcast(train(*learning_sample(learn_from, per_lang, max_langs)))
    names = docs.columns
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = docs.schema
    arrow = to_arrow_schema(schema)

    def run(batches):
        for batch in pieces(batches, 2000):
            lang, score = predict(model.value, batch.column(names.index("text")))
            arrays = [batch.column(k) for k in range(len(names))]
            yield pa.RecordBatch.from_arrays([*arrays, pa.array(lang, pa.string()), pa.array(score)], names=[*arrow.names, "lang_pred", "score"])

    ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema.fields)
    return docs.mapInArrow(lean(run), f"{ddl}, lang_pred string, score double")


def fold(docs: DataFrame, m: int):
    return F.crc32(F.col("doc_id").cast("string")) % m


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = identify(docs.select("doc_id", "text"), docs.where(fold(docs, 3) != 1).select("doc_id", "text", "lang"))
    return found.select("doc_id", F.coalesce(fold(found, 3) == 1, F.lit(False)).alias("held_out"), "lang_pred", "score")
