"""Language ID by unigrams of pieces, summed over all segmentations.

The vocabulary is that of a public piece model, whole; only the probabilities are learned. For each language, each piece
has a probability; a word's likelihood is the sum over all its segmentations of the product of piece probabilities, by
the forward algorithm, and a text's is the product over its words. Probabilities start equal and are fitted by ROUNDS of
expectation-maximisation on word counts (expected piece counts by forward and backward sums).

Fitting reads at most about DOCS_PER_LANG labelled training documents a language, picked by a hash of the id (a
documented bound; prediction covers every document and whole texts). Every label is learned, however rare; languages
are handled LANG_BLOCK at a time, so that a table has at most that many columns and the vocabulary's rows.

A text's words are looked up by the hash of the white-space chunk that holds them, in a table of about
CACHE_BYTES per task that starts anew when full. Texts are never made Python strings as a whole.

Training rows: lang not null and crc32(id as text) mod HOLD_OUT not 1. Nothing but the text enters a prediction.

Edge cases: null text, or one without a letter: `und` with score 0; null id counts as the empty text in crc32; letters
outside the vocabulary have a fixed small probability; words of any length are summed whole; ties go to the language
first in order; no labelled rows: all `und`; empty table: empty result; other columns are ignored.
"""

from __future__ import annotations

import functools
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_written, written
from .wordhash import HashTable, Words, grown, hashed, mix

DOCS_PER_LANG, HOLD_OUT, ROUNDS, LANG_BLOCK = 10_000, 3, 3, 64
SMOOTHING, UNKNOWN = 0.01, 1e-7
#: Words up to this length are summed many at a time in plain numbers (no product underflows); longer ones singly, rescaled.
PLAIN = 24
#: Numbers in one array of word edges, entries of one word count, bytes of the table of known chunks.
EDGE_CELLS, COUNTED_WORDS, CACHE_BYTES = 1 << 18, 50_000, 24 << 20
#: Bytes of text whose unknown chunks are scored together.
GROUP_BYTES = 2 << 20
MARK = "▁"
_WORD = re.compile(r"[^\W\d_]+")


@functools.lru_cache(maxsize=2)
def vocabulary(model_path: str) -> dict[str, int]:
    """Pieces made of letters and the word mark, numbered."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
    pieces = (sp.id_to_piece(i).lower() for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i)))
    kept = dict.fromkeys(p for p in pieces if p == MARK or p.removeprefix(MARK).isalpha())
    return {p: k for k, p in enumerate(kept)}


def text_words(text: str) -> list[str]:
    return _WORD.findall(text.lower())


_U, _BASE = np.uint64, np.uint64(0x9E3779B97F4A7C15)


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4").astype(_U)


def _hashes(vocab: dict[str, int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted hashes of the pieces, their numbers, and which first 20 bits occur among the hashes."""
    pieces = np.zeros(max(1, len(vocab)), _U)
    for k, x in enumerate(vocab):
        h = 0
        for c in x:
            h = h * int(_BASE) + ord(c) & (1 << 64) - 1
        pieces[k] = h
    pieces = mix(pieces)
    order, maybe = np.argsort(pieces), np.zeros(1 << 20, bool)
    maybe[pieces >> _U(44)] = True
    return pieces[order], order.astype(np.int32) if vocab else np.array([-1], np.int32), maybe


@functools.lru_cache(maxsize=2)
def _model_parts(model_path: str) -> tuple:
    """What every task of a worker needs of the vocabulary: the pieces, the longest one's length, their hashes."""
    vocab = vocabulary(model_path)
    return vocab, max(map(len, vocab)), _hashes(vocab)


def _model(model_path: str, table: np.ndarray) -> Model:
    vocab, longest, hashes = _model_parts(model_path)
    return Model(vocab, table, longest, hashes)


class Model:
    """Piece probabilities [piece, language] over a vocabulary; the last rows are the unknown letter and no piece."""

    def __init__(self, vocab: dict[str, int], table: np.ndarray, longest: int | None = None, hashes: tuple | None = None):
        self.vocab, self.unknown, self.longest = vocab, len(vocab), longest or max(map(len, vocab), default=1)
        self.hash, self.number, self.maybe = hashes or _hashes(vocab)
        self.p = np.vstack([table, np.full((1, table.shape[1]), UNKNOWN), np.zeros((1, table.shape[1]))])

    def edges(self, word: str) -> list[list[int]]:
        """For each end in the marked word, the numbers of the pieces of 1, 2, .. letters that end there (-1: none)."""
        get, w = self.vocab.get, MARK + word
        rows = [[get(w[j - k : j], -1) for k in range(1, min(j, self.longest) + 1)] for j in range(1, len(w) + 1)]
        for r in rows:
            if r[0] < 0:
                r[0] = self.unknown
        return rows

    def _numbers(self, hashes: np.ndarray) -> np.ndarray:
        """The pieces with these hashes, or -1."""
        out = np.full(hashes.shape, -1, np.int32)
        maybe = self.maybe[hashes >> _U(44)]
        some = hashes[maybe]
        at = np.minimum(np.searchsorted(self.hash, some), len(self.hash) - 1)
        out[maybe] = np.where(self.hash[at] == some, self.number[at], -1)
        return out

    def groups(self, words: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Plain words by length: (their places, numbers [word, end, letters - 1])."""
        length = np.fromiter(map(len, words), np.int64, len(words))
        for n in np.unique(length[length <= PLAIN]).tolist():
            places, wide = np.flatnonzero(length == n), min(n + 1, self.longest)
            step = max(1, EDGE_CELLS // ((n + 1) * wide))
            for a in range(0, len(places), step):
                part = places[a : a + step]
                letters = _codes("".join([MARK + words[p] for p in part.tolist()])).reshape(len(part), n + 1)
                out, value = np.full((len(part), n + 1, wide), -1, np.int32), np.zeros_like(letters)
                for k in range(wide):  # substrings of k + 1 letters, from those of k
                    value = value[:, : n + 1 - k] * _BASE + letters[:, k:]
                    out[:, k:, k] = self._numbers(mix(value))
                single = out[:, :, 0]
                single[single < 0] = self.unknown
                yield part, out

    def log_likelihood(self, words: list[str]) -> np.ndarray:
        """[word, language]: log of the summed probability of all segmentations."""
        p, out = self.p, np.zeros((len(words), self.p.shape[1]))
        for places, edges in self.groups(words):
            n = edges.shape[1]
            alpha = np.zeros((n + 1, len(places), p.shape[1]))
            alpha[0] = 1
            for j in range(n):
                for k in range(min(j + 1, edges.shape[2])):
                    alpha[j + 1] += alpha[j - k] * p[edges[:, j, k]]  # number -1 is the last row, of zeros
            out[places] = np.log(alpha[n])
        for k, w in enumerate(words):
            if len(w) > PLAIN:
                alpha, scale = self._long(self.edges(w), p)
                out[k] = np.log(alpha[-1]) + scale[-1]
        return out

    def _long(self, edges: list[list[int]], p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Forward sums [end, language] of one word, and the logarithms to add to theirs."""
        wide = self.longest
        alpha, scale = np.zeros((len(edges) + 1, p.shape[1])), np.zeros((len(edges) + 1, p.shape[1]))
        window, shift = np.zeros((wide, p.shape[1])), np.zeros(p.shape[1])  # the last ends, newest first
        window[0] = alpha[0] = 1
        for j, row in enumerate(edges):
            new = (window[: len(row)] * p[row]).sum(0)
            window = np.concatenate([new[None], window[:-1]])
            low = new < 1e-100
            if low.any():
                window[:, low] *= 1e100
                shift[low] -= 100 * np.log(10)
            alpha[j + 1], scale[j + 1] = window[0], shift
        return alpha, scale

    def expected_counts(self, words: list[str], times: np.ndarray, lang: np.ndarray) -> np.ndarray:
        """Expected piece counts [piece, language] of words that occur `times` in language `lang`."""
        p, langs = self.p, self.p.shape[1]
        total = np.zeros(p.shape[0] * langs)
        last = p.shape[0] - 1
        for places, edges in self.groups(words):
            which, n = lang[places], edges.shape[1]
            alpha, beta = np.zeros((n + 1, len(places))), np.zeros((n + 1, len(places)))
            alpha[0] = beta[n] = 1
            spans = [(j, k) for j in range(n) for k in range(min(j + 1, edges.shape[2]))]
            prob = p[edges, which[:, None, None]]
            for j, k in spans:
                alpha[j + 1] += alpha[j - k] * prob[:, j, k]
            for j, k in reversed(spans):
                beta[j - k] += beta[j + 1] * prob[:, j, k]
            weight = times[places] / alpha[n]
            number = np.where(edges < 0, last, edges) * langs + which[:, None, None]
            share = np.zeros(edges.shape)
            for j, k in spans:
                share[:, j, k] = alpha[j - k] * prob[:, j, k] * beta[j + 1] * weight
            total += np.bincount(number.ravel(), share.ravel(), len(total))
        for k, w in enumerate(words):
            if len(w) > PLAIN:
                edges, one = self.edges(w), p[:, lang[k] : lang[k] + 1]
                alpha, up = self._long(edges, one)
                back = [[edges[j + i][i] for i in range(min(self.longest, len(edges) - j)) if i < len(edges[j + i])] for j in range(len(edges))]
                beta, down = self._long(back[::-1], one)
                beta, down, whole = beta[::-1], down[::-1], np.log(alpha[-1, 0]) + up[-1, 0]
                for j, row in enumerate(edges):
                    at = j - np.arange(len(row))
                    share = alpha[at, 0] * one[row, 0] * beta[j + 1, 0] * np.exp(up[at, 0] + down[j + 1, 0] - whole)
                    np.add.at(total, np.where(np.array(row) < 0, last, row) * langs + lang[k], times[k] * share)
        return total.reshape(-1, langs)[: last - 1]


def _held_out(c):
    return F.crc32(F.coalesce(c.cast("string"), F.lit(""))) % HOLD_OUT == 1


def training_words(rows: DataFrame) -> tuple[DataFrame, list[tuple[str, int]]]:
    """(lang, word, n) of the fitting documents, and the number of labelled training rows of each language, in order."""
    train = rows.where(F.col("lang").isNotNull() & ~_held_out(F.col("id")))
    sizes = train.groupBy("lang").agg(F.count(F.lit(1)).alias("n"))
    labels = sorted((r.lang, r.n) for r in sizes.collect())  # one row for each label
    uniform = F.shiftrightunsigned(F.xxhash64(F.col("id")), 11) / float(1 << 53)
    rates = rows.sparkSession.createDataFrame([(x, min(1.0, DOCS_PER_LANG / n)) for x, n in labels], "lang string, rate double")
    sample = train.join(F.broadcast(rates), "lang").where(uniform < F.col("rate")).select("lang", "text")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([k[0] for k in seen], pa.string()), pa.array([k[1] for k in seen], pa.string()), pa.array(list(seen.values()), pa.int64())], ["lang", "word", "n"])

        seen: Counter = Counter()
        for b in batches:
            for lang, text in zip(b.column(0), b.column(1), strict=True):
                if text.is_valid:
                    seen.update((lang.as_py(), w) for w in text_words(text.as_py()))
                if len(seen) > COUNTED_WORDS:
                    yield out()
                    seen.clear()
        if seen:
            yield out()

    words = sample.mapInArrow(count, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    return written(words, "language-words"), labels


def fit(words: DataFrame, langs: list[str], model_path: str) -> np.ndarray:
    """Piece probabilities [piece, language] of some languages from (lang, word, n)."""
    vocab = vocabulary(model_path)
    some = words.where(F.col("lang").isin(langs))
    table = np.full((len(vocab), len(langs)), 1 / len(vocab))
    for _ in range(ROUNDS):
        counts = np.full_like(table, SMOOTHING)
        # One row for each piece and language of the block at most.
        for r in _expected(some, langs, table, model_path).collect():
            counts[r.piece, r.lang] += r.n
        table = counts / counts.sum(0)
    return table


def _expected(words: DataFrame, langs: list[str], table: np.ndarray, model_path: str) -> DataFrame:
    shared = words.sparkSession.sparkContext.broadcast(table)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number, model = {x: k for k, x in enumerate(langs)}, _model(model_path, shared.value)
        total = np.zeros_like(shared.value)
        for b in batches:
            lang = np.array([number[x] for x in b.column(0).to_pylist()], np.int64)
            total += model.expected_counts(b.column(1).to_pylist(), b.column(2).to_numpy().astype(float), lang)
        piece, lang = np.nonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(piece, pa.int32()), pa.array(lang, pa.int32()), pa.array(total[piece, lang])], ["piece", "lang", "n"])

    return words.mapInArrow(run, "piece int, lang int, n double").groupBy("piece", "lang").agg(F.sum("n").alias("n"))


class ChunkScores:
    """Log likelihoods of white-space chunks by their hash, in arrays of bounded size."""

    def __init__(self, model: Model, most_bytes: int = CACHE_BYTES):
        self.model, self.langs = model, model.p.shape[1]
        self.most = max(1, most_bytes // (17 + 8 * self.langs))
        self._clear()

    def _clear(self) -> None:
        self.rows, self.score, self.letter = HashTable(), np.zeros((1024, self.langs)), np.zeros(1024, bool)

    def _made(self, chunks: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        words = [text_words(c.decode("utf-8")) for c in chunks]
        known = list(dict.fromkeys(w for ws in words for w in ws))
        number, scores = {w: k for k, w in enumerate(known)}, self.model.log_likelihood(known)
        owner = np.repeat(np.arange(len(words)), [len(ws) for ws in words])
        which = np.array([number[w] for ws in words for w in ws], np.int64)
        out = np.zeros((len(chunks), self.langs))
        np.add.at(out, owner, scores[which])
        return out, np.array([any(c.isalpha() for w in ws for c in w) for ws in words], bool)

    def _known(self, parts: list[tuple[Words, np.ndarray, np.ndarray, np.ndarray]]) -> None:
        """Score the chunks of some slices that are not in the table, all at once."""
        keys, first = np.unique(np.concatenate([key for _, key, _, _ in parts]), return_index=True)
        new = self.rows.find(keys) < 0
        if self.rows.n and self.rows.n + new.sum() > self.most:
            self._clear()
            new[:] = True
        if new.any():
            chunks = [w.raw[a:b] for w, _, at, _ in parts for a, b in zip(w.start[at].tolist(), w.end[at].tolist(), strict=True)]
            at = self.rows.add(keys[new])
            self.score, self.letter = grown(self.score, self.rows.n), grown(self.letter, self.rows.n)
            self.score[at], self.letter[at] = self._made([chunks[k] for k in first[new].tolist()])

    def totals(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """([row, language], [row]): summed log likelihoods of each text, and whether it has a letter."""
        total, letter = np.zeros((len(column), self.langs)), np.zeros(len(column), bool)
        parts, size = [], 0

        def flush() -> None:
            self._known(parts)
            for w, key, _, back in parts:
                row = self.rows.find(key)[back]
                for k in range(self.langs):
                    total[w.first : w.first + w.rows, k] = np.bincount(w.text, self.score[row, k], w.rows)
                letter[w.first : w.first + w.rows] = np.bincount(w.text, self.letter[row], w.rows) > 0
            parts.clear()

        for w in hashed(column, lower=False):
            parts.append((w, *np.unique(w.hash, return_index=True, return_inverse=True)))
            size += len(w.raw)
            if size > GROUP_BYTES:
                flush()
                size = 0
        if parts:
            flush()
        return total, letter


def predicted(docs: DataFrame, model_path: str, id_column: str = "doc_id", text_column: str = "text", lang_column: str = "lang", lang_block: int = LANG_BLOCK) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row."""
    rows = docs.select(F.col(id_column).alias("id"), F.col(text_column).alias("text"), F.col(lang_column).alias("lang"))
    words, labels = training_words(rows)
    total = sum(n for _, n in labels)
    # best: the likeliest language so far and its log probability; mass: the logarithm of the sum over all languages.
    out = rows.select("id", "text", _held_out(F.col("id")).alias("held_out"), F.lit(None).cast("string").alias("best"), F.lit(None).cast("double").alias("top"), F.lit(None).cast("double").alias("mass"))
    for a in range(0, len(labels), lang_block):
        block = labels[a : a + lang_block]
        langs = [x for x, _ in block]
        prior = np.log(np.array([n for _, n in block], float) / total)
        out = _with_block(out, langs, fit(words, langs, model_path), prior, model_path)
    drop_written(words)
    return out.select(F.col("id").cast("long").alias("doc_id"), "held_out", F.coalesce("best", F.lit("und")).alias("lang_pred"), F.when(F.col("best").isNull(), 0.0).otherwise(F.least(F.exp(F.col("top") - F.col("mass")), F.lit(1.0))).alias("score"))


def _with_block(rows: DataFrame, langs: list[str], table: np.ndarray, prior: np.ndarray, model_path: str) -> DataFrame:
    model = rows.sparkSession.sparkContext.broadcast(table)
    names = rows.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scores = ChunkScores(_model(model_path, model.value))
        for b in batches:
            got, letter = scores.totals(b.column(1))
            got += prior
            first = got.argmax(1)
            top = got[np.arange(len(got)), first]
            mass = top + np.log(np.exp(got - top[:, None]).sum(1))
            best, was = np.array(langs, object)[first], b.column(4).to_numpy(zero_copy_only=False).astype(float)
            seen = letter & ~np.isnan(was)
            mass[seen] = np.logaddexp(mass[seen], b.column(5).to_numpy(zero_copy_only=False).astype(float)[seen])
            stays = seen & (was >= top)
            best[stays], top[stays] = np.array(b.column(3).to_pylist(), object)[stays], was[stays]
            hide = ~letter
            columns = [pa.array(best, pa.string(), mask=hide), pa.array(top, pa.float64(), mask=hide), pa.array(mass, pa.float64(), mask=hide)]
            yield pa.RecordBatch.from_arrays([*b.columns[:3], *columns], names)

    return rows.mapInArrow(run, rows.schema)
