"""Language identification against plain sums over all segmentations."""

import collections
import math
import zlib

import numpy as np
import public_tokenizers
import pytest

from stratacore.llm import op5_language as lang

from .helpers import ODD, documents, empty

PIECES = public_tokenizers.path("piece_bpe_32k.model")
VOCAB = {"▁": 0, "▁a": 1, "a": 2, "ab": 3, "b": 4, "▁ab": 5}


def all_segmentations(s, vocab, p):
    """(probability, pieces) of every segmentation."""
    if not s:
        return [(1.0, [])]
    out = []
    for i in range(1, len(s) + 1):
        q = p[vocab[s[:i]]] if s[:i] in vocab else lang.UNKNOWN if i == 1 else 0
        if q:
            out += [(q * x, [s[:i], *rest]) for x, rest in all_segmentations(s[i:], vocab, p)]
    return out


@pytest.mark.parametrize("plain", [lang.PLAIN, 0])
def test_sums_and_counts(monkeypatch, plain):
    monkeypatch.setattr(lang, "PLAIN", plain)
    table = np.random.default_rng(0).random((6, 2))
    model = lang.Model(VOCAB, table)
    words = ["a", "ab", "abba", "c", "bcab", "abababa"]
    got = model.log_likelihood(words)
    for w, row in zip(words, got, strict=True):
        assert np.allclose(row, [math.log(sum(x for x, _ in all_segmentations("▁" + w, VOCAB, table[:, k]))) for k in (0, 1)])
    counts = model.expected_counts(words, np.arange(1.0, 7), np.array([0, 1, 0, 1, 0, 1]))
    want = np.zeros((6, 2))
    for w, n, k in zip(words, range(1, 7), [0, 1, 0, 1, 0, 1], strict=True):
        every = all_segmentations("▁" + w, VOCAB, table[:, k])
        for x, parts in every:
            for part in parts:
                if part in VOCAB:
                    want[VOCAB[part], k] += n * x / sum(y for y, _ in every)
    assert np.allclose(counts, want)


def test_a_word_of_any_length_is_summed_whole():
    model = lang.Model({"▁": 0, "a": 1, "aa": 2}, np.array([[0.5], [1e-6], [1e-9]]))
    x = model.log_likelihood(["a" * 3000])[0, 0]
    ends = [0.0, math.log(0.5)]  # logarithms by end
    for j in range(2, 3002):
        parts = [ends[j - 1] + math.log(1e-6)] + ([ends[j - 2] + math.log(1e-9)] if j >= 3 else [])
        ends.append(max(parts) + math.log(sum(math.exp(v - max(parts)) for v in parts)))
    assert x == pytest.approx(ends[-1])
    counts = model.expected_counts(["a" * 3000], np.array([1.0]), np.array([0]))
    assert counts[1, 0] + 2 * counts[2, 0] == pytest.approx(3000)


class Plain:
    """The same method in plain loops."""

    def __init__(self, rows):
        self.vocab = lang.vocabulary(PIECES)
        words = collections.defaultdict(collections.Counter)
        number = collections.Counter()
        for i, t, x in rows:
            if x is not None and zlib.crc32(str(i).encode()) % 3 != 1:
                number[x] += 1
                words[x].update(lang.text_words(t or ""))
        self.langs = sorted(number)
        self.prior = [math.log(number[x] / sum(number.values())) for x in self.langs]
        self.p = [self.fit(words[x]) for x in self.langs]

    def parts(self, w):
        return [[(j - k, w[j - k : j]) for k in range(1, j + 1) if k == 1 or w[j - k : j] in self.vocab] for j in range(1, len(w) + 1)]

    def sums(self, w, p):
        ahead = [1.0]
        for row in self.parts(w):
            ahead.append(sum(ahead[i] * (p[self.vocab[x]] if x in self.vocab else lang.UNKNOWN) for i, x in row))
        return ahead

    def fit(self, words):
        p = [1 / len(self.vocab)] * len(self.vocab)
        for _ in range(lang.ROUNDS):
            counts = [lang.SMOOTHING] * len(p)
            for word, n in words.items():
                w = "▁" + word
                ahead, back = self.sums(w, p), [0.0] * len(w) + [1.0]
                rows = self.parts(w)
                for j in range(len(w), 0, -1):
                    for i, x in rows[j - 1]:
                        q = p[self.vocab[x]] if x in self.vocab else lang.UNKNOWN
                        if x in self.vocab:
                            counts[self.vocab[x]] += n * ahead[i] * q * back[j] / ahead[-1]
                        back[i] += q * back[j]
            whole = sum(counts)
            p = [c / whole for c in counts]
        return p

    def predict(self, text):
        words = lang.text_words(text or "")
        if not any(c.isalpha() for w in words for c in w):
            return "und", 0.0
        score = [a + sum(math.log(self.sums("▁" + w, p)[-1]) for w in words) for a, p in zip(self.prior, self.p, strict=True)]
        k = max(range(len(score)), key=lambda i: (score[i], -i))
        return self.langs[k], 1 / sum(math.exp(max(s - score[k], -700)) for s in score)


@pytest.mark.parametrize("block", [64, 1])
def test_predictions_equal_plain_loops(spark, sf_dir, block):
    some = spark.read.parquet(f"{sf_dir}/documents.parquet").selectExpr("doc_id", "substring(text, 1, 300) as text", "lang").where("doc_id < 40")
    rows = [tuple(r) for r in some.collect()] + [(1000, "nur eine Zeile der seltenen Sprache", "xx"), (1001, None, "en"), (1002, "123 ...", None), (1003, "ÀÉ ß " + "donaudampfschifffahrtsgesellschaftskapitän" * 2, None)]
    plain = Plain(rows)
    assert "xx" in plain.langs or zlib.crc32(b"1000") % 3 == 1
    got = lang.predicted(spark.createDataFrame(rows, "doc_id long, text string, lang string"), PIECES, lang_block=block).collect()
    assert len(got) == len(rows)
    texts = {i: t for i, t, _ in rows}
    for r in got:
        want, sure = plain.predict(texts[r.doc_id])
        assert r.lang_pred == want and r.score == pytest.approx(sure, abs=1e-6)


def test_the_table_of_chunks_may_overflow():
    import pyarrow as pa

    model = lang.Model(VOCAB, np.random.default_rng(1).random((6, 2)))
    texts = pa.array(["ab ba", None, "abba ab c", "b " * 5, "12", "a-b ab"])
    big, tiny = lang.ChunkScores(model), lang.ChunkScores(model, 60)
    for k in [*range(len(texts)), *range(len(texts))]:
        x, y = big.totals(texts.slice(k, 1)), tiny.totals(texts.slice(k, 1))
        assert np.allclose(x[0], y[0]) and (x[1] == y[1]).all()
    assert tiny.rows.n < big.rows.n == 7


def test_held_out_rows_of_the_given_table(spark, sf_dir):
    df = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    truth = {r.doc_id: r.lang for r in df.collect()}
    got = lang.predicted(df, PIECES).collect()
    held = [r for r in got if r.held_out]
    assert {r.doc_id for r in held} == {i for i in truth if zlib.crc32(str(i).encode()) % 3 == 1}
    assert np.mean([r.lang_pred == truth[r.doc_id] for r in held]) >= 0.9
    assert all(0 <= r.score <= 1 for r in got)


def test_odd_rows(spark):
    got = lang.predicted(documents(spark), PIECES).collect()
    assert len(got) == len(ODD) and {r.lang_pred for r in got if r.doc_id in (1, 2, 3)} == {"und"}
    assert lang.predicted(empty(spark), PIECES).count() == 0
