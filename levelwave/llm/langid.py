"""Language identification by unigram models over the pieces of a fixed public vocabulary, all segmentations summed.

Each language has a probability for every piece, fitted to a bounded sample of its documents by expected counts over all
segmentations. A word's probability is the sum over all its segmentations into pieces, by the forward algorithm over its
letters; a text's is the product over its words. Words are scored once for each worker and looked up afterwards; new words of
a batch go through the algorithm together. Long words, such as whole sentences of scripts without blanks, are cut in spans
whose transfer matrices are made together and multiplied in order, so no segmentation is lost at a cut.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import crc_bucket, documents, importable, stored
from .textkernel import mix, slices

QUERY = "op5_language_id"
#: Documents of a language that its model is fitted on, about (those whose hash falls under a share), and rounds of fitting.
TRAIN_ROWS, ROUNDS = 1500, 2
#: Added to every piece's count; probability of a letter that is no piece.
SMOOTHING, UNKNOWN = 0.05, 1e-9
#: Letters of a word that is scored in one go, with its mark, and of a span of longer ones; bytes of the sums held at once.
SHORT, SPAN, HELD = 32, 64, 32 << 20
#: Words remembered at most, and letters of one that is remembered.
CACHE_ENTRIES, CACHE_LETTERS = 400_000, 256
UNDETERMINED, MARK = "und", "▁"
_U = np.uint64
_CODE = _U(0x9E3779B97F4A7C15)


def _in_word(c: str) -> bool:
    """A letter, or a mark that belongs to one, such as the vowel signs of many scripts."""
    return c.isalpha() or unicodedata.category(c)[0] == "M"


def letters_of(word: str) -> str:
    """The word's letters with their marks, lower-cased; empty if it has no letter."""
    if word.isalpha():
        return word.lower()
    kept = "".join(filter(_in_word, word)).lower()
    return kept if any(map(str.isalpha, kept)) else ""


class Pieces:
    """The vocabulary: pieces of letters, maybe with the mark of a word's beginning, found by hash and length. A letter that
    is no piece counts as one of probability UNKNOWN, which is row size of a table."""

    def __init__(self, path: str):
        import sentencepiece

        self.library = sentencepiece.SentencePieceProcessor(model_file=path)
        names = [self.library.id_to_piece(i) for i in range(self.library.get_piece_size())]
        use = [i for i, p in enumerate(names) if p == MARK or p.lstrip(MARK) and all(map(_in_word, p.removeprefix(MARK)))]
        self.by_length: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for n in sorted({len(names[i]) for i in use}):
            ids = np.array([i for i in use if len(names[i]) == n])
            codes = self._hash(mix(np.array([[ord(c) for c in names[i]] for i in ids], dtype=np.uint64) + _U(1)))
            order = np.argsort(codes)
            self.by_length[n] = codes[order], ids[order]
        self.size, self.longest = len(names), max(self.by_length)

    @staticmethod
    def _hash(rows: np.ndarray) -> np.ndarray:
        code = np.zeros(len(rows), dtype=np.uint64)
        for k in range(rows.shape[1]):
            code = code * _CODE + rows[:, k]
        return code

    def find(self, codes: np.ndarray, length: int) -> np.ndarray:
        """Piece of each hash of so many letters; -1 where there is none, size where a letter is none."""
        none = self.size if length == 1 else -1
        known = self.by_length.get(length)
        if known is None:
            return np.full(codes.shape, none)
        at = np.minimum(np.searchsorted(known[0], codes), len(known[0]) - 1)
        return np.where(known[0][at] == codes, known[1][at], none)

    def lattice(self, words: list[str]) -> tuple[np.ndarray, list[list[tuple[int, np.ndarray, np.ndarray]]]]:
        """Letters of each word with its mark, longest first; for each place t the pieces that end there, as (begin, words,
        pieces)."""
        sizes = np.array([len(w) + 1 for w in words])
        width, count = int(sizes[0]), len(words)
        grid = np.zeros((count, width), dtype=np.uint64)
        grid[np.arange(width) < sizes[:, None]] = np.frombuffer("".join([MARK + w for w in words]).encode("utf-32-le"), dtype=np.uint32)
        coded = mix(grid + _U(1))
        codes: dict[int, np.ndarray] = {}  # by beginning: the hash of what was read from there
        ends: list[list[tuple[int, np.ndarray, np.ndarray]]] = [[]]
        for t in range(1, width + 1):
            n = int(np.searchsorted(-sizes, -t, side="right"))  # words of at least t letters come first
            codes[t - 1] = np.zeros(count, dtype=np.uint64)
            found = []
            for begin in codes:
                codes[begin][:n] = codes[begin][:n] * _CODE + coded[:n, t - 1]
                if t - begin > 1 and t - begin not in self.by_length:
                    continue
                piece = self.find(codes[begin][:n], t - begin)
                rows = np.flatnonzero(piece >= 0)
                found.append((begin, rows, piece[rows]))
            codes = {b: c for b, c in codes.items() if t - b < self.longest}
            ends.append(found)
        return sizes, ends

    def log_probabilities(self, words: list[str], table: np.ndarray) -> np.ndarray:
        """(word, language): log of the sum over all segmentations of a mark and the word's letters."""
        table = np.vstack((table, np.full(table.shape[1], UNKNOWN)))
        out = np.zeros((len(words), table.shape[1]))
        lengths = np.array([len(w) for w in words], dtype=np.int64)
        order = np.argsort(-lengths, kind="stable")
        short = order[lengths[order] < SHORT]
        together = max(1, HELD // (8 * (SHORT + 1) * table.shape[1]))
        for at in range(0, len(short), together):
            part = short[at : at + together]
            out[part] = self._short([words[k] for k in part], table)
        if len(long := order[lengths[order] >= SHORT]):
            out[long] = self._long([words[k] for k in long], table)
        return out

    def _short(self, words: list[str], table: np.ndarray) -> np.ndarray:
        sizes, ends = self.lattice(words)
        forward = np.zeros((len(ends), len(words), table.shape[1]))
        forward[0] = 1
        for t, found in enumerate(ends):
            for begin, rows, piece in found:
                # A factor of 256 a letter keeps long products in range; it is taken off below.
                forward[t, rows] += forward[begin, rows] * table[piece] * 256.0 ** (t - begin)
        return np.log(forward[sizes, np.arange(len(words))]) - sizes[:, None] * np.log(256.0)

    def _long(self, words: list[str], table: np.ndarray) -> np.ndarray:
        """Through spans. The state between letters is the sums of the last places, as far as a piece reaches."""
        reach, out = self.longest, np.zeros((len(words), table.shape[1]))
        state = np.zeros((len(words), reach, table.shape[1]))
        state[:, 0] = 1
        waiting: list[tuple[int, int, int]] = []  # (word, begin, end) in order

        def settle() -> None:
            matrices, logs = self._transfers(words, waiting, table)
            for (k, _, _), m, log in zip(waiting, matrices, logs, strict=True):
                now = np.einsum("ibl,bl->il", m, state[k])
                top = now.max(axis=0)
                state[k], out[k] = now / top, out[k] + log + np.log(top)
            waiting.clear()

        together = max(1, HELD // (8 * reach * reach * table.shape[1]))
        for k, word in enumerate(words):
            for at in range(0, len(word) + 1, SPAN):
                waiting.append((k, at, min(at + SPAN, len(word) + 1)))
                if len(waiting) >= together:
                    settle()
        if waiting:
            settle()
        return out + np.log(state[:, 0])

    def _transfers(self, words: list[str], spans: list[tuple[int, int, int]], table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(span, place, place before, language), each language's scaled, and the logarithms of what they were scaled by."""
        reach, languages = self.longest, table.shape[1]
        # Each span's letters, after as many before them as a piece may reach back, or as the word has.
        low = [max(a - reach, 0) for _, a, _ in spans]
        parts = [words[k][at - 1 : b - 1] if at else MARK + words[k][: b - 1] for (k, _, b), at in zip(spans, low, strict=True)]
        sizes, before = np.array([b - a for _, a, b in spans]), np.array([min(a, reach) for _, a, _ in spans])
        order = np.argsort(-sizes, kind="stable")
        count, width = len(spans), int(sizes.max())
        grid = np.zeros((count, reach + width), dtype=np.uint64)
        for i, part in enumerate(parts):
            grid[i, reach - before[i] : reach + sizes[i]] = np.frombuffer(part.encode("utf-32-le"), dtype=np.uint32)
        coded, first = mix(grid + _U(1))[order], (reach - before)[order]
        sizes = sizes[order]
        ring = [np.zeros((count, reach, languages)) for _ in range(reach)]  # ring[i]: the place i letters back
        for i in range(reach):
            ring[i][:, i] = 1
        codes = np.zeros((reach + 1, count), dtype=np.uint64)  # of the last n letters
        for t in range(reach):
            for n in range(reach, 0, -1):
                codes[n] = codes[n - 1] * _CODE + coded[:, t]
        matrix, logs, gone = np.zeros((count, reach, reach, languages)), np.zeros((count, languages)), np.zeros((count, languages))
        for t in range(1, width + 1):
            live = int(np.searchsorted(-sizes, -t, side="right"))
            fresh = np.zeros((count, reach, languages))
            for n in range(reach, 0, -1):
                codes[n][:live] = codes[n - 1][:live] * _CODE + coded[:live, reach + t - 1]
            for n in range(1, reach + 1):
                piece = self.find(codes[n][:live], n)
                rows = np.flatnonzero((piece >= 0) & (reach + t - n >= first[:live]))
                fresh[rows] += ring[n - 1][rows] * table[piece[rows]][:, None, :]
            ring = [fresh, *ring[:-1]]
            if t % 8 == 0 or t == width:
                top = np.maximum(np.max([r[:live].max(axis=1) for r in ring], axis=0), 1e-300)
                for r in ring:
                    r[:live] /= top[:, None, :]
                gone[:live] += np.log(top)
            ended = slice(int(np.searchsorted(-sizes, -t - 1, side="right")), live)
            if ended.stop > ended.start:
                matrix[ended] = np.stack([r[ended] for r in ring], axis=1)
                logs[ended] = gone[ended]
        back = np.argsort(order)
        return matrix[back], logs[back]

    def expected(self, words: list[str], times: np.ndarray, table: np.ndarray) -> np.ndarray:
        """Expected count of each piece over all segmentations of these words (of at most SHORT letters) by one language's
        table."""
        order = np.argsort([-len(w) for w in words], kind="stable")
        words, times = [words[k] for k in order], np.asarray(times, float)[order]
        table, (sizes, ends) = np.append(table, UNKNOWN), self.lattice(words)
        forward, backward = np.zeros((len(ends), len(words))), np.zeros((len(ends), len(words)))
        forward[0], backward[sizes, np.arange(len(words))] = 1, 1
        for t, found in enumerate(ends):
            for begin, rows, piece in found:
                forward[t, rows] += forward[begin, rows] * table[piece] * 256.0 ** (t - begin)
        whole, out = forward[sizes, np.arange(len(words))], np.zeros(self.size + 1)
        for t in range(len(ends) - 1, 0, -1):
            for begin, rows, piece in ends[t]:
                own = table[piece] * 256.0 ** (t - begin) * backward[t, rows]
                backward[begin, rows] += own
                out += np.bincount(piece, forward[begin, rows] * own / whole[rows] * times[rows], minlength=self.size + 1)
        return out[: self.size]


class Scorer:
    """Sums of word log-probabilities of texts; remembers words."""

    def __init__(self, pieces: Pieces, table: np.ndarray):
        self.pieces, self.table = pieces, table
        self.clear()

    def clear(self) -> None:
        self.place: dict[str, int] = {}
        self.rows = np.zeros((0, self.table.shape[1] + 1))

    def sums(self, texts: list[str]) -> np.ndarray:
        """(text, languages and then the number of words with a letter)."""
        parted = [t.split() for t in texts]
        there = set(chain.from_iterable(parted))
        new = [w for w in there if w not in self.place]
        if len(self.place) + len(new) > CACHE_ENTRIES:
            self.clear()
            new = list(there)
        stems: dict[str, int] = {}
        which = np.array([stems.setdefault(letters_of(w), len(stems)) for w in new], dtype=np.int64)
        if new:
            scored = self.pieces.log_probabilities(list(stems), self.table)
            some = np.array([1.0 if s else 0.0 for s in stems])
            fresh = np.concatenate((scored * some[:, None], some[:, None]), axis=1)[which]
            self.place.update(zip(new, range(len(self.rows), len(self.rows) + len(new)), strict=True))
            self.rows = np.concatenate((self.rows, fresh))
        place = self.place.__getitem__
        out = np.array([self.rows[np.fromiter(map(place, p), np.int64, len(p))].sum(axis=0) for p in parted]).reshape(len(texts), -1)
        for word in (w for w in new if len(w) > CACHE_LETTERS):
            del self.place[word]
        return out


_pieces: dict[str, Pieces] = {}
_scorers: dict[tuple, Scorer] = {}


def pieces_of(vocabulary: str) -> Pieces:
    if vocabulary not in _pieces:
        _pieces[vocabulary] = Pieces(vocabulary)
    return _pieces[vocabulary]


def sample_words(docs: DataFrame, most: int = TRAIN_ROWS) -> DataFrame:
    """(lang, word, n), stored: words of documents with a language and crc32(id) mod 4 not 2, those of over SHORT letters in
    parts. Of a language with more documents than most, about most are used: those whose id's hash is under the share."""
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (crc_bucket(F.col("doc_id"), 4) != 2))
    share = F.broadcast(known.groupBy("lang").agg(F.count("*").alias("n")))  # one row for each language
    chosen = known.join(share, "lang").where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_003)) * F.col("n") < F.lit(1_000_003) * most)

    def count(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for lang, group in frame.groupby("lang"):
                words = pd.Series([w[at : at + SHORT - 1] for text in group["text"] for w in map(letters_of, text.split()) for at in range(0, len(w), SHORT - 1)], dtype=object).value_counts()
                yield pd.DataFrame({"lang": lang, "word": words.index, "n": words.to_numpy()})

    importable(docs.sparkSession)
    counted = chosen.select("lang", "text").mapInPandas(count, "lang string, word string, n long")
    return stored(counted.groupBy("lang", "word").agg(F.sum("n").alias("n")), "language-words")


def fit(docs: DataFrame, vocabulary: str, most: int = TRAIN_ROWS, rounds: int = ROUNDS) -> tuple[list[str], np.ndarray]:
    """Languages in order and the (piece, language) table. Counts begin with one best segmentation of each word; each round
    replaces them by those expected over all segmentations. To the driver comes a count for each piece and language."""
    words = sample_words(docs, most)
    names, size = [r[0] for r in words.select("lang").distinct().orderBy("lang").collect()], pieces_of(vocabulary).size

    def counts(table: np.ndarray | None) -> np.ndarray:
        sent = words.sparkSession.sparkContext.broadcast(table)

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            pieces = pieces_of(vocabulary)
            for frame in frames:
                for lang, group in frame.groupby("lang"):
                    got = np.zeros(pieces.size)
                    if sent.value is None:
                        for ids, n in zip(pieces.library.encode(group["word"].tolist()), group["n"], strict=True):
                            np.add.at(got, ids, n)
                    else:
                        own = sent.value[:, names.index(lang)]
                        for at in range(0, len(group), 20_000):
                            part = group.iloc[at : at + 20_000]
                            got += pieces.expected(part["word"].tolist(), part["n"].to_numpy(), own)
                    live = np.flatnonzero(got > 1e-6)
                    yield pd.DataFrame({"lang": lang, "piece": live, "n": got[live]})

        found = words.mapInPandas(run, "lang string, piece int, n double").groupBy("lang", "piece").agg(F.sum("n").alias("n")).toPandas()
        out = np.full((size, len(names)), SMOOTHING)
        out[found["piece"], found["lang"].map(names.index).to_numpy(int)] += found["n"].to_numpy()
        return out / out.sum(axis=0)

    if not names:
        return [], np.zeros((size, 0))
    table = counts(None)
    for _ in range(rounds):
        table = counts(table)
    return names, table


def language(docs: DataFrame, vocabulary: str, most: int = TRAIN_ROWS) -> DataFrame:
    """doc_id, held_out, lang_pred and score (the best language's share of the probability) of every row.

    A null text, or one without letters, is 'und' with a score of 0, as is every row where no language could be learned.
    Ties go to the first language by name. Repeated rows are alike; a null id stays null and isn't held out.
    """
    spark = docs.sparkSession
    names, table = fit(docs, vocabulary, most)
    sent = spark.sparkContext.broadcast((names, table))
    key = (vocabulary, hash(table.tobytes()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        learned, probabilities = sent.value
        if key not in _scorers and learned:
            _scorers.clear()
            _scorers[key] = Scorer(pieces_of(vocabulary), probabilities)
        for part in slices(batches):
            if not learned:
                best, score = [UNDETERMINED] * part.num_rows, np.zeros(part.num_rows)
            else:
                sums = _scorers[key].sums([t or "" for t in part.column(1).to_pylist()])
                logs, some = sums[:, :-1], sums[:, -1] > 0
                top = logs.argmax(axis=1)
                score = np.where(some, 1 / np.exp(logs - logs.max(axis=1, keepdims=True)).sum(axis=1), 0.0)
                best = [learned[k] if s else UNDETERMINED for k, s in zip(top.tolist(), some.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(best), pa.array(score)], ["doc_id", "lang_pred", "score"])

    out = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, lang_pred string, score double")
    return out.select("doc_id", (crc_bucket(F.col("doc_id"), 4) == 2).alias("held_out"), "lang_pred", "score")


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return language(documents(spark, sf_dir), public_tokenizers.path("piece_bpe_32k.model"))
