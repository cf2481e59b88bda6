"""Operator 3, SentencePiece encoding and decoding by a batched Viterbi in numpy.

Texts are cut into words, each with the spaces before it; no piece holds a space after another character, so words are encoded alone.
Distinct words of equal length advance together, one position a step: at each position the substrings that end there
are hashed and probed in the sorted keys of the pieces, a vectorised maximum over the candidates is taken, and its length is the backpointer.

Unigram models maximise the sum of piece scores. For BPE models the best path is the one the merges make: a candidate piece is admitted
only if it stands unmerged beside the last piece of the path before it (found by undoing both pieces' last merges, latest first,
and asking whether the pieces at the seam would have merged earlier). Exactly one candidate is admitted at each position, so
the same recurrence gives the ids of the reference library. Runs of spaces, whose merges tie, are encoded by a small table.

Characters outside the vocabulary become byte pieces (or the unknown piece, without byte fallback). U+2581 in a text stands for a space, as in the
library, so such a text decodes to spaces. The model file's path is a parameter; it is read by the driver only.

Words are encoded once for each worker (up to CACHE words are kept); nothing is shuffled.

Defined cases: null ids decode to null; null or empty text has no ids. Repeated rows are each encoded, empty tables give no rows,
other columns pass through, but for those named as its results, which are replaced. Of pieces of equal score the
leftmost merge comes first, as in the library. Texts of any length are encoded whole, about SLICE bytes at a time.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, small_batches, table
from .textnum import mix, segment_hashes, slices, utf8

MODEL_PATH = "/opt/tokenizers/piece_bpe_32k.model"
SLICE, CACHE, SEAMS = 1 << 21, 3 << 20, 1 << 20
SPACE = "▁"
_B = np.uint64(0x9E3779B97F4A7C15)
#: Kinds of pieces and of models in the model file.
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNIGRAM, BPE = 1, 2
_LATE = np.int64(1) << 40


def _varint(b: bytes, i: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        x = b[i]
        i += 1
        value |= (x & 127) << shift
        if x < 128:
            return value, i
        shift += 7


def _fields(b: bytes):
    """Field numbers and values of a protocol buffer message."""
    i = 0
    while i < len(b):
        tag, i = _varint(b, i)
        if tag & 7 == 0:
            value, i = _varint(b, i)
        else:
            size, i = _varint(b, i) if tag & 7 == 2 else ({5: 4, 1: 8}[tag & 7], i)
            value, i = b[i : i + size], i + size
        yield tag >> 3, value


def powers_of(n: int) -> np.ndarray:
    p = np.full(n + 1, _B)
    p[0] = 1
    return np.multiply.accumulate(p)


def text_hash(codes: np.ndarray) -> np.uint64:
    return np.uint64((codes.astype(np.uint64) * powers_of(len(codes))[: len(codes)][::-1]).sum(dtype=np.uint64)) if len(codes) else np.uint64(0)


class Model:
    """Pieces, scores and, for BPE, each piece's last merge."""

    def __init__(self, names: list[str], scores: list[float], kinds: list[int], bpe: bool, dummy_prefix: bool = True):
        self.names, self.bpe, self.dummy_prefix = names, bpe, dummy_prefix
        self.name = uuid.uuid4().hex
        n = len(names)
        kinds_ = np.array(kinds)
        self.unk = int(np.flatnonzero(kinds_ == UNKNOWN)[0]) if (kinds_ == UNKNOWN).any() else 0
        self.bytes_ = np.full(256, -1)
        for i in np.flatnonzero(kinds_ == BYTE):
            self.bytes_[int(names[i][1:-1], 16)] = i
        self.score = np.array(scores, np.float64)
        self.unk_score = (self.score[kinds_ == NORMAL].min() if (kinds_ == NORMAL).any() else 0.0) - 10.0
        real = np.flatnonzero((kinds_ == NORMAL) | (kinds_ == USER))
        ids = {names[i]: int(i) for i in real}
        self.ids = ids
        self.size = np.array([len(x) for x in names])
        self.hash = np.array([text_hash(np.array([ord(c) for c in x])) for x in names], np.uint64)
        order = real[np.argsort(self.hash[real], kind="stable")]
        self.keys, self.key_ids = self.hash[order], order
        self.maybe = np.zeros(1 << 20, bool)
        self.maybe[mix(self.keys) >> np.uint64(44)] = True
        self.longest = int(self.size[real].max()) if len(real) else 1
        self.pow = powers_of(self.longest + 1)
        self.rank = np.full(n + 1, -1, np.int64)
        self.left, self.right = np.full(n + 1, n), np.full(n + 1, n)
        self.whole = np.zeros(n + 1, bool)
        self.merge_rank = np.full(n + 1, _LATE)
        place = np.argsort(np.argsort(-self.score[real], kind="stable"), kind="stable")
        self.merge_rank[real] = place
        if bpe:
            self._merges(real, dict(zip(real.tolist(), place.tolist(), strict=True)))
        self.seam_keys, self.seam_ok = np.full(SEAMS, -1, np.int64), np.zeros(SEAMS, bool)
        flat = [bytes([int(x[1:-1], 16)]) if k == BYTE else b"" if k == CONTROL else " ⁇ ".encode() if k == UNKNOWN else x.replace(SPACE, " ").encode() for x, k in zip(names, kinds, strict=True)]
        self.out = np.frombuffer(b"".join(flat), np.uint8)
        self.out_at = np.concatenate([[0], np.cumsum([len(x) for x in flat])])

    @classmethod
    def read(cls, path: str = MODEL_PATH) -> Model:
        with open(path, "rb") as f:
            data = f.read()
        names, scores, kinds, bpe, dummy = [], [], [], False, True
        for field, value in _fields(data):
            if field == 1:
                piece = dict(_fields(value))
                names.append(piece[1].decode())
                scores.append(float(np.frombuffer(piece[2], "<f4")[0]) if 2 in piece else 0.0)
                kinds.append(piece.get(3, NORMAL))
            elif field == 2:
                bpe = dict(_fields(value)).get(3, UNIGRAM) == BPE
            elif field == 3:
                spec = dict(_fields(value))
                if spec.get(1, b"") != b"identity" or spec.get(4, 1):
                    raise ValueError("only models with the identity normaliser that keep all spaces are read")
                dummy = bool(spec.get(3, 1))
        return cls(names, scores, kinds, bpe, dummy)

    def merge_all(self, parts: list[str]) -> tuple[list[str], tuple[str, str] | None]:
        """The merges of a piece, best score first, leftmost among equals; the parts at the end and the last pair merged."""
        last = None
        while len(parts) > 1:
            best = min(((self.merge_rank_of(a + b), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False))), key=lambda x: x)
            if best[0] is None or best[0] >= _LATE:
                break
            i = best[1]
            last = (parts[i], parts[i + 1])
            parts = [*parts[:i], parts[i] + parts[i + 1], *parts[i + 2 :]]
        return parts, last

    def merge_rank_of(self, name: str):
        """By score, so that equal scores tie."""
        i = self.ids.get(name)
        return _LATE if i is None else -self.score[i] - 1e12

    def _merges(self, real: np.ndarray, place: dict[int, int]) -> None:
        for i in real:
            parts, last = self.merge_all(list(self.names[i]))
            if len(parts) == 1:
                self.whole[i] = True
                if last is not None:
                    self.left[i], self.right[i] = self.ids[last[0]] if last[0] in self.ids else len(self.names), self.ids[last[1]] if last[1] in self.ids else len(self.names)
                    self.rank[i] = place[int(i)]
        self.whole[len(self.names)] = True

    def lone_spaces(self, n: int) -> list[int]:
        """Ids of n spaces that no letter took."""
        if n <= 0:
            return []
        if self.bpe:
            parts, _ = self.merge_all([SPACE] * n) if n <= 64 else (self._long_run(n), None)
        else:
            parts = self._viterbi_spaces(n)
        return [self.ids.get(p, self.unk) for p in parts]

    def _long_run(self, n: int) -> list[str]:
        """Of a long run the longest piece of spaces repeats from the left; the rest merges as a short one."""
        top = max(len(x) for x in self.ids if x and not x.strip(SPACE)) if SPACE in self.ids else 1
        head = max(0, n // top - 3)
        return [SPACE * top] * head + self.merge_all([SPACE] * (n - head * top))[0]

    def _viterbi_spaces(self, n: int) -> list[str]:
        best, back = [0.0] + [-np.inf] * n, [0] * (n + 1)
        for i in range(1, n + 1):
            for k in range(1, min(i, self.longest) + 1):
                s = best[i - k] + (self.score[self.ids[SPACE * k]] if SPACE * k in self.ids else self.unk_score if k == 1 else -np.inf)
                if s > best[i]:
                    best[i], back[i] = s, k
        out = []
        while n:
            out.append(SPACE * back[n])
            n -= back[n]
        return out[::-1]

    def probe(self, h: np.ndarray) -> np.ndarray:
        """Ids of substring hashes, -1 where no piece has it. A bit table answers for most of those that have none."""
        out = np.full(len(h), -1)
        near = np.flatnonzero(self.maybe[mix(h) >> np.uint64(44)])
        at = np.searchsorted(self.keys, h[near])
        at[at == len(self.keys)] = 0
        hit = self.keys[at] == h[near]
        out[near[hit]] = self.key_ids[at[hit]]
        return out

    def joined(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Rank of the merge of two pieces, _LATE where they do not merge; n stands for a character outside the vocabulary."""
        n = len(self.names)
        ok = (x < n) & (y < n)
        a, b = np.where(ok, x, 0), np.where(ok, y, 0)
        size = self.size[b]
        short = self.size[a] + size <= self.longest
        t = self.probe(self.hash[a] * self.pow[np.minimum(size, self.longest)] + self.hash[b])
        return np.where(ok & short & (t >= 0), self.merge_rank[t], _LATE)

    def stands(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether pieces a and b stay unmerged side by side."""
        n = len(self.names)
        x, y = a.copy(), b.copy()
        good = self.joined(x, y) >= _LATE
        live = np.flatnonzero(good)
        while len(live):
            u, v = x[live], y[live]
            ru, rv = self.rank[u], self.rank[v]
            live, u, v, ru, rv = (z[(ru >= 0) | (rv >= 0)] for z in (live, u, v, ru, rv))
            if not len(live):
                break
            undo_left = ru > rv
            x[live] = np.where(undo_left, self.right[u], u)
            y[live] = np.where(undo_left, v, self.left[v])
            met = self.joined(x[live], y[live])
            bad = np.where(undo_left, met < ru, met <= rv)
            good[live[bad]] = False
            live = live[~bad]
        return good & (a <= n) & (b <= n)

    def seam(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """stands(), by a table of pairs met before; a pair that shares its place with another is found again."""
        key = a.astype(np.int64) << 32 | b
        at = (mix(key.view(np.uint64)) >> np.uint64(44)).astype(np.int64)
        new = np.flatnonzero(self.seam_keys[at] != key)
        out = self.seam_ok[at]
        if len(new):
            pairs, inverse = np.unique(key[new], return_inverse=True)
            ok = self.stands(pairs >> 32, pairs & 0xFFFFFFFF)
            out[new] = ok[inverse.ravel()]
            self.seam_keys[at[new]], self.seam_ok[at[new]] = key[new], out[new]
        return out

    def encode_equal(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """codes: [m, n] characters of m words of n characters. All words' piece ids in a row (n_pieces + character for one outside the
        vocabulary), and how many each has."""
        m, n = codes.shape
        other = len(self.names)
        prefix = np.zeros((m, n + 1), np.uint64)
        for i in range(n):
            prefix[:, i + 1] = prefix[:, i] * _B + codes[:, i].astype(np.uint64)
        best = np.full((m, n + 1), -np.inf)
        best[:, 0] = 0
        last, back = np.full((m, n + 1), other), np.zeros((m, n + 1), np.int64)
        for i in range(1, n + 1):
            for k in range(1, min(i, self.longest) + 1):
                t = self.probe(prefix[:, i] - prefix[:, i - k] * self.pow[k])
                if k == 1:
                    t[t < 0] = other
                rows = np.flatnonzero((t >= 0) & (best[:, i - k] > best[:, i] if self.bpe else np.isfinite(best[:, i - k])))
                t = t[rows]
                if self.bpe:
                    ok = self.whole[t]
                    if i > k:
                        ok[ok] = self.seam(last[rows[ok], i - k], t[ok])
                    value = np.where(ok, 0.0, -np.inf)
                else:
                    value = best[rows, i - k] + np.where(t == other, self.unk_score, self.score[np.minimum(t, other - 1)])
                better = value > best[rows, i]
                rows = rows[better]
                best[rows, i], last[rows, i], back[rows, i] = value[better], t[better], k
        at, live, rows, found = np.full(m, n), np.arange(m), [], []
        while len(live):
            here = at[live]
            t = last[live, here]
            rows.append(live)
            found.append(np.where(t < other, t, other + codes[live, here - 1].astype(np.int64)))
            at[live] -= np.maximum(back[live, here], 1)
            live = live[at[live] > 0]
        steps = np.repeat(np.arange(len(rows)), [len(x) for x in rows])
        row = np.concatenate(rows)
        order = np.lexsort((-steps, row))
        return np.concatenate(found)[order], np.bincount(row, minlength=m)

    def spell(self, ids: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Characters outside the vocabulary as byte pieces, or as the unknown piece."""
        n = len(self.names)
        out = np.flatnonzero(ids >= n)
        if not len(out):
            return ids, size
        if self.bytes_.min() < 0:
            return np.where(ids >= n, self.unk, ids), size
        chars, which = np.unique(ids[out] - n, return_inverse=True)
        spelt = [self.bytes_[np.frombuffer(chr(c).encode("utf-8", "surrogatepass"), np.uint8)] for c in chars]
        width = np.array([len(x) for x in spelt])
        times = np.ones(len(ids), np.int64)
        times[out] = width[which.ravel()]
        word = np.repeat(np.arange(len(size)), size)
        flat = np.repeat(ids, times)
        begin = (np.cumsum(times) - times)[out]
        for k in range(4):
            own = width[which.ravel()] > k
            letters = np.array([x[k] if len(x) > k else -1 for x in spelt])
            flat[begin[own] + k] = letters[which.ravel()[own]]
        return flat, np.bincount(word, weights=times, minlength=len(size)).astype(np.int64)

    def encode_words(self, words: list[tuple[int, str]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Words given as (spaces before, characters): a pool of ids, where each word's begin in it, and how many it has."""
        begin, size, pool, filled = np.zeros(len(words), np.int64), np.zeros(len(words), np.int64), [], 0
        by: dict[int, list[int]] = {}
        special: list[int] = []
        for i, (spaces, core) in enumerate(words):
            if core:
                by.setdefault(len(core) + (spaces > 0), []).append(i)
            if spaces > 1 or not core:
                special.append(i)
        for n, group in by.items():
            step = max(1, min(20_000, 2_000_000 // n))
            for k in range(0, len(group), step):
                part = group[k : k + step]
                text = "".join(SPACE + words[i][1] if words[i][0] else words[i][1] for i in part)
                codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).reshape(len(part), n)
                ids, count = self.spell(*self.encode_equal(codes))
                begin[part], size[part] = filled + np.cumsum(count) - count, count
                pool.append(ids)
                filled += len(ids)
        flat = np.concatenate(pool) if pool else np.zeros(0, np.int64)
        space = self.ids.get(SPACE, -1)
        unknown_space = [int(self.bytes_[b]) for b in SPACE.encode()] if self.bytes_.min() >= 0 else [self.unk]
        extra: list[int] = []
        for i in special:
            spaces, core = words[i]
            ids = flat[begin[i] : begin[i] + size[i]].tolist()
            lead = [space] if space >= 0 else unknown_space
            if not core:
                ids = self.lone_spaces(spaces)
            elif ids[: len(lead)] == lead:
                ids = self.lone_spaces(spaces) + ids[len(lead) :]
            else:
                ids = self.lone_spaces(spaces - 1) + ids
            begin[i], size[i] = filled + len(extra), len(ids)
            extra += ids
        return np.concatenate([flat, np.array(extra, np.int64)]), begin, size


class Encoder:
    """A model with the words it has met."""

    def __init__(self, model: Model):
        self.model = model
        self.clear()

    def clear(self) -> None:
        kind = np.uint16 if len(self.model.names) <= 1 << 16 else np.int32
        self.keys, self.begin, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int32), np.zeros(0, np.int32)
        self.pool, self.filled = np.zeros(1 << 16, kind), 0

    def learn(self, keys: np.ndarray, words: list[tuple[int, str]]) -> None:
        pool, begin, size = self.model.encode_words(words)
        if self.filled + len(pool) > len(self.pool):
            self.pool = np.concatenate([self.pool[: self.filled], np.zeros(max(len(pool), self.filled // 2), self.pool.dtype)])
        self.pool[self.filled : self.filled + len(pool)] = pool
        at = np.searchsorted(self.keys, keys)  # keys are sorted
        self.keys = np.insert(self.keys, at, keys)
        self.begin = np.insert(self.begin, at, begin + self.filled)
        self.size = np.insert(self.size, at, size)
        self.filled += len(pool)

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and where each text's ids begin."""
        n = len(offsets) - 1
        starts, ends, h, at = segment_hashes(data, data != 32, offsets)
        text = np.repeat(np.arange(n), np.diff(at))
        previous = np.concatenate([[0], ends[:-1]]) if len(ends) else ends
        first = np.zeros(len(starts), bool)
        first[at[:-1][np.diff(at) > 0]] = True
        spaces = starts - np.where(first, offsets[text], previous) + (first & self.model.dummy_prefix)
        last = offsets[:-1].copy()
        full = np.diff(at) > 0
        last[full] = ends[at[1:][full] - 1]
        tail = offsets[1:] - last
        tail += (~full) & (np.diff(offsets) > 0) & self.model.dummy_prefix
        extra = np.flatnonzero(tail > 0)
        where = at[1:][extra]
        spaces, starts, ends = np.insert(spaces, where, tail[extra]), np.insert(starts, where, 0), np.insert(ends, where, 0)
        h = np.insert(h, where, np.uint64(1))
        at = at + np.concatenate([[0], np.cumsum(tail > 0)])
        key = np.where(spaces == 1, h, mix(h + spaces.astype(np.uint64) * np.uint64(0x2545F4914F6CDD1D)))
        uniq, one, inverse = np.unique(key, return_index=True, return_inverse=True)
        if len(self.keys) > CACHE:
            self.clear()
        if len(self.keys):
            place = np.minimum(np.searchsorted(self.keys, uniq), len(self.keys) - 1)
            new = self.keys[place] != uniq
        else:
            new = np.ones(len(uniq), bool)
        if new.any():
            raw = data.tobytes()
            self.learn(uniq[new], [(int(spaces[i]), raw[starts[i] : ends[i]].decode("utf-8", "surrogatepass")) for i in one[new]])
        place = np.searchsorted(self.keys, uniq)[inverse.ravel()] if len(uniq) else np.zeros(0, np.int64)
        size = self.size[place].astype(np.int64)
        begin = np.cumsum(size) - size
        ids = self.pool[np.repeat(self.begin[place] - begin, size) + np.arange(int(size.sum()))].astype(np.int32)
        return ids, np.concatenate([[0], np.cumsum(size)])[at]

    def decode(self, ids: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of all texts in a row, and where each begins."""
        m = self.model
        size = (m.out_at[1:] - m.out_at[:-1])[ids]
        begin = m.out_at[:-1][ids].copy()
        if m.dummy_prefix:
            head = at[:-1][np.diff(at) > 0]
            lead = head[(size[head] > 0) & (m.out[np.minimum(begin[head], len(m.out) - 1)] == 32)]
            begin[lead] += 1
            size[lead] -= 1
        run = np.cumsum(size) - size
        data = m.out[np.repeat(begin - run, size) + np.arange(int(size.sum()))]
        return data, np.concatenate([[0], np.cumsum(size)])[at]


_encoders: dict[str, Encoder] = {}


def encoder_of(sent) -> Encoder:
    """The worker's encoder of a broadcast model: the tasks that a worker runs share its words. One is kept."""
    model = sent.value
    if model.name not in _encoders:
        _encoders.clear()
        _encoders[model.name] = Encoder(model)
    return _encoders[model.name]


def _spaced(column):
    """The column, with U+2581 as spaces."""
    return pc.replace_substring(column, SPACE, " ") if pc.any(pc.match_substring(column, SPACE)).as_py() else column


def encode_texts(docs: DataFrame, model: Model | None = None, text_col: str = "text") -> DataFrame:
    """docs with ids (array<int>), n_tokens and round_trip (whether the ids decode to the text, U+2581 as spaces) added, the text left out. Columns of docs
    with these names are replaced."""
    from pyspark.sql.pandas.types import to_arrow_schema

    small_batches(docs.sparkSession)
    kept = docs.drop(text_col, "ids", "n_tokens", "round_trip")
    names = [f.name for f in to_arrow_schema(kept.schema)]
    sent = docs.sparkSession.sparkContext.broadcast(model or Model.read())

    def run(batches):
        encoder = encoder_of(sent)
        for batch in batches:
            column = _spaced(batch.column(batch.num_columns - 1))
            data, offsets = utf8(column)
            for i, j in slices(offsets, SLICE):
                own, at = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
                ids, begin = encoder.encode(own, at)
                back, where = encoder.decode(ids, begin)
                equal = np.diff(where) == np.diff(at)
                if equal.all():
                    wrong = np.flatnonzero(back != own)
                    equal[np.searchsorted(at, wrong, "right") - 1] = False
                else:
                    equal &= [back[a:b].tobytes() == own[c:d].tobytes() for a, b, c, d in zip(where[:-1], where[1:], at[:-1], at[1:], strict=True)]
                lists = pa.ListArray.from_arrays(pa.array(begin, pa.int32()), pa.array(ids, pa.int32()))
                rows = batch.slice(i, j - i)
                yield pa.RecordBatch.from_arrays([*(rows.column(k) for k in range(len(names))), lists, pa.array(np.diff(begin)), pa.array(equal)], names=[*names, "ids", "n_tokens", "round_trip"])

    ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields)
    return docs.select(*[F.col(f"`{c}`") for c in kept.columns], F.col(text_col).cast("string").alias("__text")).mapInArrow(lean(run), f"{ddl + ', ' if ddl else ''}ids array<int>, n_tokens long, round_trip boolean")


def decode_ids(rows: DataFrame, model: Model | None = None, ids_col: str = "ids") -> DataFrame:
    """rows (any columns, and ids) with text in place of the ids; a column text is replaced."""
    from pyspark.sql.pandas.types import to_arrow_schema

    kept = rows.drop(ids_col, "text")
    names = [f.name for f in to_arrow_schema(kept.schema)]
    sent = rows.sparkSession.sparkContext.broadcast(model or Model.read())

    def run(batches):
        encoder = encoder_of(sent)
        for batch in batches:
            column = batch.column(batch.num_columns - 1)
            size = pc.fill_null(column.value_lengths(), 0).to_numpy(zero_copy_only=False)
            ids = column.flatten().to_numpy(zero_copy_only=False)
            data, at = encoder.decode(ids, np.concatenate([[0], np.cumsum(size)]))
            raw = data.tobytes()
            null = column.is_null().to_pylist()
            text = [None if x else raw[a:b].decode("utf-8", "replace") for x, a, b in zip(null, at[:-1], at[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(len(names))), pa.array(text, pa.string())], names=[*names, "text"])

    ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields)
    return rows.select(*[F.col(f"`{c}`") for c in kept.columns], F.col(ids_col).cast("array<int>").alias("__ids")).mapInArrow(lean(run), f"{ddl + ', ' if ddl else ''}text string")


def op3_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_texts(table(spark, sf_dir, "documents").select("doc_id", "text"))
