"""Parts without Spark: hashing, prefix tree, forward-backward, GRU gradients, quantisation, HTML, WARC records, pieces."""

import itertools
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from gridjoin.llm import ann, html_extract, language_id, lm_score, ngram_join, pieces, warc
from gridjoin.llm.textnum import shingle_hashes, utf8, word_hashes

TEXTS = ["", " ", "a", "A b\tC\nd  e f", "é È É x", None, "w " * 3000, "one two three four", "one two three four five", "x" * 5000]


def words(t):
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return [w for w in re.split(r"[\x20\x09-\x0D]+", (t or "").translate(low)) if w]


def test_word_hashes_tell_words_apart():
    data, offsets = utf8(pa.array(TEXTS, pa.string()))
    h, at = word_hashes(data, offsets)
    seen = {}
    for t, a, b in zip(TEXTS, at[:-1], at[1:], strict=True):
        assert b - a == len(words(t))
        for w, x in zip(words(t), h[a:b].tolist(), strict=True):
            assert seen.setdefault(w, x) == x
    assert len(set(seen.values())) == len(seen)
    s, begin = shingle_hashes(h, at)
    for t, a, b in zip(TEXTS, begin[:-1], begin[1:], strict=True):
        w = words(t)
        full = [tuple(w[i : i + 5]) for i in range(len(w) - 4)] if len(w) >= 5 else ([tuple(w)] if w else [])
        assert b - a == len(full) and len(set(s[a:b].tolist())) == len(set(full))


def test_slices_of_arrow_columns():
    whole = pa.array(TEXTS, pa.string())
    data, offsets = utf8(whole.slice(3, 4))
    assert [data[a:b].tobytes().decode() for a, b in zip(offsets[:-1], offsets[1:], strict=True)] == [t or "" for t in TEXTS[3:7]]


def test_prefix_tree_and_blocks_equal_brute_force():
    rng = np.random.default_rng(3)
    base = np.unique(rng.integers(0, 400, 80).astype(np.uint64))
    sets = []
    for _ in range(40):
        keep = base[rng.random(len(base)) < rng.uniform(0.6, 1)]
        sets.append(np.unique(np.concatenate([keep, rng.integers(400, 2000, rng.integers(0, 20)).astype(np.uint64)])))
    sets += [np.array([7], np.uint64), base.copy(), base.copy()]
    link = lambda a, b: 100 * len(np.intersect1d(a, b)) >= 75 * len(np.union1d(a, b))
    for hub in sets:
        assert ngram_join.tree_matches(hub, sets).tolist() == [link(hub, s) for s in sets]
    marks = [np.array([1, 5], np.int64)] * len(sets)
    i, j = ngram_join.block_links(sets, marks, np.zeros(len(sets)), 75)
    assert set(zip(i.tolist(), j.tolist(), strict=True)) == {(a, b) for a, b in itertools.combinations(range(len(sets)), 2) if link(sets[a], sets[b])}
    a, b = ngram_join.forest(np.array([0, 1, 4]), np.array([1, 2, 5]), 6)
    assert sorted(zip(a.tolist(), b.tolist(), strict=True)) == [(0, 1), (0, 2), (4, 5)]


def test_posting_bounds_hold():
    """Linked sets share at least least_met() of their posted shingles, in any common order."""
    rng = np.random.default_rng(5)
    for _ in range(400):
        n = int(rng.integers(1, 120))
        a = rng.permutation(1000)[:n]
        b = np.concatenate([a[rng.random(n) < rng.uniform(0.7, 1)], 1000 + rng.permutation(500)[: rng.integers(0, 1 + n // 3)]])
        if not len(b) or 100 * len(np.intersect1d(a, b)) < 75 * len(np.union1d(a, b)):
            continue
        a, b = np.sort(a), np.sort(b)
        met = len(np.intersect1d(a[: ngram_join.posted(len(a), 75)], b[: ngram_join.posted(len(b), 75)]))
        least = int(ngram_join.least_met(np.array([len(a)]), np.array([len(b)]), 75)[0])
        assert met >= least >= 1
        skip = lambda k: min(ngram_join.DEPTH - 1, -(-75 * k // 100) - 1)
        assert max(skip(len(a)), skip(len(b))) < least


def test_forward_backward_equals_enumeration():
    rng = np.random.default_rng(0)
    e, trans, start = rng.normal(size=(6, 3)).astype(np.float32), rng.normal(size=(3, 3)).astype(np.float32), rng.normal(size=3).astype(np.float32)
    index, size = np.array([[0, 1, 2, 5], [3, 4, 0, 0]]), np.array([4, 2])
    marg, expected, logs = language_id.forward_backward(e, index, size, trans, start, pairs=True)
    want = np.zeros((3, 3))
    for b in range(2):
        paths = list(itertools.product(range(3), repeat=size[b]))
        score = np.array([start[p[0]] + sum(e[index[b, t], y] for t, y in enumerate(p)) + sum(trans[x, y] for x, y in itertools.pairwise(p)) for p in paths])
        prob = np.exp(score - score.max())
        z = prob.sum()
        assert np.isclose(logs[b], np.log(z) + score.max(), atol=1e-4)
        for t in range(size[b]):
            for y in range(3):
                assert np.isclose(marg[b, t, y], sum(q for p, q in zip(paths, prob, strict=True) if p[t] == y) / z, atol=1e-4)
        for p, q in zip(paths, prob, strict=True):
            for x, y in itertools.pairwise(p):
                want[x, y] += q / z
    assert np.allclose(expected, want, atol=1e-4)


def test_language_model_labels_code_switched_words():
    one, two = ["the cat and the dog with that", "this thing and that other thing"] * 30, ["der hund und die katze mit dem", "das ding und ein anderes ding"] * 30
    model = language_id.train(one + two, ["en"] * 60 + ["de"] * 60)
    lang, score = language_id.predict(model, pa.array(["the thing and that dog", "und das ding mit dem hund", None, "", "123 $$", "€ –", "the dog and that"], pa.string()))
    assert lang[:2] == ["en", "de"] and lang[2:6] == ["und"] * 4 and score[2] == 0 and lang[6] == "en"
    assert language_id.predict(language_id.train([], []), pa.array(["abc"]))[0] == ["und"]


def test_gru_gradients_and_normalisation():
    rng = np.random.default_rng(1)
    m = {k: v.astype(np.float64) for k, v in lm_score.fresh_model().items()}
    x, y, h = rng.integers(0, lm_score.VOCAB, (4, 3)), rng.integers(0, lm_score.VOCAB, (4, 3)), rng.normal(size=(3, lm_score.HIDDEN))
    _, g, _ = lm_score.window_loss(m, x, y, h)
    for k in m:
        at = tuple(z[0] for z in np.nonzero(g[k]))
        keep = m[k][at]
        loss = []
        for d in (1e-5, -1e-5):
            m[k][at] = keep + d
            loss.append(lm_score.window_loss(m, x, y, h)[0])
        m[k][at] = keep
        assert np.isclose((loss[0] - loss[1]) / 2e-5, g[k][at], rtol=1e-3, atol=1e-8), k
    states = np.repeat(rng.normal(size=(1, lm_score.HIDDEN)), lm_score.VOCAB, axis=0)
    assert np.isclose(np.exp(lm_score.token_logs(m, states, np.arange(lm_score.VOCAB))).sum(), 1)


def test_training_reads_the_whole_sample(monkeypatch):
    seen = []

    def window(m, inputs, targets, h):
        seen.append(inputs.size)
        return 0.0, {k: np.zeros_like(v) for k, v in m.items()}, h

    monkeypatch.setattr(lm_score, "window_loss", window)
    n = 1_000_000
    lm_score.train(np.zeros(n, np.int64), epochs=1)
    assert n - lm_score.STREAMS <= sum(seen) < n


def test_scores_do_not_depend_on_batching():
    m = lm_score.fresh_model()
    rng = np.random.default_rng(2)
    size = np.array([1, 70, 3, 33])
    ids = rng.integers(0, lm_score.VOCAB, size.sum())
    at = np.concatenate([[0], np.cumsum(size)])
    whole = lm_score.score_documents(m, ids, at, 5)
    for i in range(4):
        assert np.isclose(lm_score.score_documents(m, ids[at[i] : at[i + 1]], np.array([0, size[i]]), 5)[0], whole[i], rtol=1e-5)


def test_anisotropic_codes_lower_their_loss():
    rng = np.random.default_rng(4)
    x = rng.normal(size=(2000, 16))
    w = 4.0
    assert ann.eta(64) > 2 and ann.eta(4) == 1
    books = ann.train(x, w)
    loss = lambda codes: (lambda r: (r**2).sum() + (w - 1) * ((r * ann.units(x)).sum(axis=1) ** 2).sum())(x - books[np.arange(8), codes].reshape(len(x), -1))
    assert loss(ann.encode(x, books, w)) < loss(ann.encode(x, books, 1.0, 0))
    codes = ann.encode(x, books, w)
    est = ann.scan(ann.tables(x[:3], books), codes[:, 0::2] << 4 | codes[:, 1::2], np.zeros(len(x)))
    assert np.allclose(est, x[:3] @ books[np.arange(8), codes].reshape(len(x), -1).T, atol=1e-4)
    ids, sig = np.array([9, 3, 5, 1]), np.array([7, 7, 7, 2])
    assert sorted(ids[ann.fewest(ids, sig, 2)].tolist()) == [1, 3, 5]
    est, ids, sig = (np.array([x]) for x in ([1.0, 3.0, 1.0, 1.0, 2.0], [4, 9, 2, 3, 8], [5, 1, 5, 5, 6]))
    assert [x.tolist() for x in ann.best_of(est, ids, sig, 4, 2)] == [[[3.0, 2.0, 1.0, 1.0]], [[9, 8, 2, 3]], [[1, 6, 5, 5]]]
    half = np.array([1.5, 1.5, 2.5, 1.5])
    codes = np.array([[1, 2], [1, 2], [1, 2], [2, 1]], np.uint8)
    marks = ann.signatures(codes, half)
    assert marks[0] == marks[1] and len(set(marks.tolist())) == 3


@pytest.mark.parametrize(
    ("page", "lines"),
    [
        ("", []),
        ("plain &amp; text", [("plain & text", 1)]),
        ("<nav><ul><li>a</ul></nav><article><header><h1>T</h1></header><p>x <b>y<p>z&nbsp; w</article><footer>f</footer>", [("a", 0), ("T", 2), ("x y", 2), ("z w", 2), ("f", 0)]),
        ("<div class='sidebar'>s</div><div>body<script>if (a<b) '</p>'</script> end</div>", [("s", 0), ("body end", 1)]),
        ("<p>a<!-- x > y -->b<p hidden>c</p><p style='display: none'>d</p>", [("ab", 1), ("c", 0), ("d", 0)]),
        ("<main><p>m</p><section id=comments><p>no</p></section></main>", [("m", 2), ("no", 0)]),
        ("<table><tr><td>1<td>2<tr><td>3</table>", [("1", 1), ("2", 1), ("3", 1)]),
        ("<p title='a > b'>q</p><unclosed", [("q", 1)]),
    ],
)
def test_page_lines(page, lines):
    assert html_extract.page_lines(page) == lines


def test_differencing_deletes_shared_open_lines():
    a, b = ["menu", "story one", "tail", "tail"], ["menu", "story two", "tail"]
    assert html_extract.main_text(a, bytes([1, 1, 1, 1]), b) == ("story one\ntail", 2, 0)
    assert html_extract.main_text(a, bytes([1, 2, 1, 1]), b) == ("story one", 2, 0) and html_extract.main_text(a, bytes([2, 2, 1, 1]), b) == ("menu\nstory one", 2, 1)
    assert html_extract.main_text(a, bytes([1, 1, 1, 0]), None) == ("menu\nstory one\ntail", 0, 0)
    rng = random.Random(1)
    for _ in range(100):
        x, y = [[rng.choice("abc") for _ in range(rng.randint(0, 9))] for _ in range(2)]
        table = [[0] * (len(y) + 1) for _ in range(len(x) + 1)]
        for i in range(len(x)):
            for j in range(len(y)):
                table[i + 1][j + 1] = table[i][j] + 1 if x[i] == y[j] else max(table[i][j + 1], table[i + 1][j])
        assert len(html_extract.common_lines(x, y)) == table[-1][-1]


def test_warc_record_round_trip():
    raw = warc.record(7, "http://a.example/x y\r\n", "héllo".encode(), None)
    head, block = warc.parse(zlib.decompress(zlib.compress(raw)))
    assert head["WARC-Type"] == "response" and head["WARC-Target-URI"].endswith("x%20y%0D%0A") and block.endswith("héllo".encode())
    head, block = warc.parse(warc.record(8, None, b"", 9))
    assert head["WARC-Refers-To"] == "<urn:page:9>" and head["X-Payload-Length"] == "0" and "WARC-Target-URI" not in head
    assert warc.url_key("https://www.Example.com:81/a?b#c") == "com,example,www:81)/a?b" and warc.url_key(None) == "-"


def test_pieces_equal_the_reference_library():
    spm = pytest.importorskip("sentencepiece")
    model = pieces.Model.read()
    sp = spm.SentencePieceProcessor(model_file=pieces.MODEL_PATH)
    rng = random.Random(4)
    texts = ["", " ", "  a  ", "hello" * 30, " " * 70 + "x", "日本語 𝒳 é́", "a\tb\n", "<s> </s> <0x41>", "日" * 20, "aaaaaaaaaaaaaaaaaaaaaaaaa"]
    texts += ["".join(rng.choice("abcdefghij  ,.ÉñA日") for _ in range(rng.randint(0, 60))) for _ in range(400)]
    encoder = pieces.Encoder(model)
    data, offsets = utf8(pa.array(texts, pa.string()))
    for _ in range(2):  # the second time all words are known
        ids, at = encoder.encode(data, offsets)
        assert [ids[a:b].tolist() for a, b in zip(at[:-1], at[1:], strict=True)] == sp.encode(texts)
    back, where = encoder.decode(ids, at)
    assert [back[a:b].tobytes().decode() for a, b in zip(where[:-1], where[1:], strict=True)] == texts


def test_unigram_viterbi_equals_brute_force():
    names = ["<unk>", "<s>", "▁", "a", "b", "ab", "▁a", "ba", "bab", "▁▁"]
    scores = [0, 0, -2.0, -3.0, -3.1, -4.0, -3.5, -4.2, -5.5, -2.5]
    model = pieces.Model(names, scores, [2, 3, 1, 1, 1, 1, 1, 1, 1, 1], bpe=False)

    def best(text):
        value, back = [0.0] + [-1e9] * len(text), [None] * (len(text) + 1)
        for i in range(1, len(text) + 1):
            for k in range(1, i + 1):
                t = model.ids.get(text[i - k : i])
                s = model.score[t] if t is not None else model.unk_score if k == 1 else -1e9
                if value[i - k] + s > value[i]:
                    value[i], back[i] = value[i - k] + s, (k, t if t is not None else 0)
        out, i = [], len(text)
        while i:
            out.append(back[i][1])
            i -= back[i][0]
        return out[::-1]

    for n in range(1, 7):
        for w in itertools.product("abc", repeat=n):
            pool, begin, size = model.encode_words([(1, "".join(w))])
            assert pool[begin[0] : begin[0] + size[0]].tolist() == best("▁" + "".join(w)), w


def test_long_groups_of_postings_are_not_held(monkeypatch):
    """A group of more than LONG rows leaves in parts, marked as long; copies of few classes do not make a group long."""
    monkeypatch.setattr(ngram_join, "LONG", 50)
    digest = lambda i: i.to_bytes(16, "big")
    rows = [(1, 0, digest(0)), (2, 0, digest(1)), (2, 0, digest(2)), *[(3, 0, digest(i)) for i in range(200)], *[(4, 0, digest(i // 100)) for i in range(200)], (5, 0, digest(1)), (5, 1, digest(2)), (5, 1, digest(3))]
    table = pa.table({"h": pa.array([r[0] for r in rows], pa.int64()), "salt": pa.array([r[1] for r in rows], pa.int8()), "g": pa.array([r[2] for r in rows], pa.binary())})
    got = [(set(a["h"].tolist()), len(a["h"]), long) for a, long in ngram_join._groups(table.to_batches(max_chunksize=30), ["h", "salt"])]
    assert sum(n for h, n, long in got if h == {3}) == 200 and all(long for h, _, long in got if h == {3})
    assert max(n for _, n, _ in got) <= 110 and not any(long for h, _, long in got if 3 not in h)
    assert {2, 3, 4, 5} <= set().union(*(h for h, _, _ in got)) and 1 not in set().union(*(h for h, _, _ in got))
