"""Language identification by segmentation-marginalised unigrams.

Every language has a unigram distribution over the pieces of one fixed public
vocabulary. The likelihood of a word is the sum over all its segmentations into
pieces, by a forward recursion; a text's log-likelihood is the sum over its
words, because no piece crosses a word. Distributions are estimated by
expectation maximisation on word counts of all training documents: one
distributed count by language and word, then each round sums expected piece
counts (forward times backward) over that table.

Words are lower-cased runs of letters, however long, with a word mark before
them. A letter that no piece holds costs a fixed probability in every language.
Recursions carry their scale apart, so that no run is too long or too unlikely.

Defined results: null texts and texts without letters are ``und`` with score 0;
equal likelihoods go to the language first by code point; training rows with
null text or lang are skipped; without training rows everything is ``und``;
repeated rows count again in training and repeat in the result; empty tables
give no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fedlake.llm.longtable import LongTable
from fedlake.llm.runtime import CACHE_WORDS, cut, slices, strings

MARK = "▁"
#: Probability of a letter outside the vocabulary, and added mass of each piece.
FOREIGN = 1e-7
SMOOTH = 0.05
#: Words and letters whose recursions run together.
WORD_ROWS = 20_000
LETTER_ROWS = 1 << 19
#: Steps of a recursion after which it is scaled.
SCALED = 8
#: Languages that the model may hold; more is an error of the labels.
MAX_LANGUAGES = 1000
LETTERS = regex.compile(r"\p{L}+")
UNKNOWN = "und"


def stretches(token: str) -> list[str]:
    """The letter runs of a whitespace token, lower-cased and marked."""
    return [MARK + run for run in LETTERS.findall(token.lower())]


def letter_pieces(pieces: list[str]) -> dict[str, int]:
    """Pieces that can occur in a marked letter run, numbered."""
    usable = [p for p in dict.fromkeys(pieces) if (body := p[1:] if p.startswith(MARK) else p) and LETTERS.fullmatch(body) and body == body.lower() or p == MARK]
    return {p: k for k, p in enumerate(usable)}


class PieceTrie:
    """Prefix tree of the pieces; walks many positions of many words at once."""

    def __init__(self, pieces: dict[str, int]):
        self.longest = max(map(len, pieces), default=1)
        nodes: dict[tuple[int, int], int] = {}
        ends = [-1]
        for text, k in pieces.items():
            at = 0
            for c in text:
                at = nodes.setdefault((at, ord(c)), len(ends))
                if at == len(ends):
                    ends.append(-1)
            ends[at] = k
        keys = np.array([(a << 21) | c for a, c in nodes], np.int64)
        self.step = LongTable(keys, np.array(list(nodes.values()), np.int32), -1)
        self.ends = np.array(ends, np.int32)

    def grid(self, words: list[str]) -> np.ndarray:
        """For words of one length: ``ids[w, i, k]`` is the piece of ``k + 1`` characters at ``i``, or -1."""
        n, size = len(words), len(words[0])
        width = min(size, self.longest)
        chars = np.frombuffer("".join(words).encode("utf-32-le"), np.uint32).astype(np.int64)
        ids = np.full((n * size, width), -1, np.int32)
        at = np.arange(n * size)
        room = size - at % size  # characters left in the word from here
        node = np.zeros(n * size, np.int64)
        for k in range(width):
            node = self.step((node << 21) | chars[at + k])
            alive = node >= 0
            at, node, room = at[alive], node[alive].astype(np.int64), room[alive]
            ids[at, k] = self.ends[node]
            more = room > k + 1
            at, node, room = at[more], node[more], room[more]
            if not len(at):
                break
        return ids.reshape(n, size, width)


@dataclass
class PieceGrid:
    """Pieces found in words of one length, and the recursions over them.

    prob: pieces + 1 (the last is the foreign letter) by languages; id -1 picks the last.
    """

    ids: np.ndarray

    @cached_property
    def lengths(self) -> list[list[int]]:
        """For each place, the lengths less one of the pieces of two characters or more that some word has there."""
        found = (self.ids >= 0).any(axis=0)
        return [(np.flatnonzero(row[1:]) + 1).tolist() for row in found]

    def log_likelihood(self, prob: np.ndarray) -> np.ndarray:
        """Log of the sum over all ways to spell each word, by language; only the last few sums are held."""
        n, size, width = self.ids.shape
        ring = np.zeros((width + 1, n, prob.shape[1]))
        ring[0] = 1
        scale = np.zeros((n, prob.shape[1]))
        ending: list[list[int]] = [[] for _ in range(size + 1)]
        for start, longer in enumerate(self.lengths):
            for k in longer:
                ending[start + k + 1].append(k)
        for end in range(1, size + 1):
            now = ring[end % (width + 1)]
            np.multiply(ring[(end - 1) % (width + 1)], prob[self.ids[:, end - 1, 0]], out=now)
            for k in ending[end]:
                ids = self.ids[:, end - k - 1, k]
                at = np.flatnonzero(ids >= 0)
                now[at] += ring[(end - k - 1) % (width + 1)][at] * prob[ids[at]]
            if end % SCALED == 0:
                most = ring.max(axis=0)
                ring /= most
                scale += np.log(most)
        return np.log(ring[size % (width + 1)]) + scale

    def _sums(self, prob: np.ndarray, forward: bool) -> tuple[np.ndarray, np.ndarray]:
        """(sums, their log scales) at every boundary for one distribution: over spellings of what lies before it, or after it."""
        n, size, width = self.ids.shape
        sums, scale = np.zeros((size + 1, n)), np.zeros((size + 1, n))
        first, step = (0, 1) if forward else (size, -1)
        sums[first] = 1
        ending: list[list[int]] = [[] for _ in range(size + 1)]
        for start, longer in enumerate(self.lengths):
            for k in longer:
                ending[start + k + 1 if forward else start].append(k)
        for done in range(1, size + 1):
            here = first + step * done
            start = here - 1 if forward else here
            sums[here] = sums[here - step] * prob[self.ids[:, start, 0]]
            for k in ending[here]:
                ids = self.ids[:, here - k - 1 if forward else here, k]
                at = np.flatnonzero(ids >= 0)
                sums[here, at] += sums[here - step * (k + 1), at] * prob[ids[at]]
            scale[here] = scale[here - step]
            if done % SCALED == 0:  # the last ``width`` sums share a scale, as later ones add them up
                last = slice(max(0, here - width), here + 1) if forward else slice(here, here + width + 1)
                most = sums[last].max(axis=0)
                sums[last] /= most
                scale[last] = scale[here] + np.log(most)
        return sums, scale

    def expected(self, prob: np.ndarray, weight: np.ndarray) -> np.ndarray:
        """Weighted expected uses of each piece (last row: foreign letters), for one distribution (one column)."""
        n, size, _ = self.ids.shape
        prob = prob[:, 0]
        alpha, before = self._sums(prob, True)
        beta, after = self._sums(prob, False)
        whole = np.log(alpha[size]) + before[size]
        out = np.zeros(len(prob))
        for start, longer in enumerate(self.lengths):
            for k in [0, *longer]:
                ids = self.ids[:, start, k]
                at = np.arange(n) if k == 0 else np.flatnonzero(ids >= 0)
                ratio = np.exp(before[start, at] + after[start + k + 1, at] - whole[at])
                uses = alpha[start, at] * prob[ids[at]] * beta[start + k + 1, at] * ratio * weight[at]
                out += np.bincount(ids[at] % len(prob), uses, len(prob))
        return out


def by_length(words: list[str], columns: int = 1) -> Iterator[list[int]]:
    """Places of words of one length, as many at a time as the recursions of ``columns`` languages may hold."""
    groups: dict[int, list[int]] = {}
    for k, w in enumerate(words):
        groups.setdefault(len(w), []).append(k)
    for size, at in groups.items():
        rows = max(1, min(WORD_ROWS, LETTER_ROWS // size, 8 * LETTER_ROWS // (24 * columns)))
        for k in range(0, len(at), rows):
            yield at[k : k + rows]


@dataclass
class LanguageModel:
    """Piece probabilities by language; the last row is the foreign letter."""


    pieces: dict[str, int]
    languages: list[str]
    prob: np.ndarray

    @cached_property
    def trie(self) -> PieceTrie:
        return PieceTrie(self.pieces)

    def word_scores(self, words: list[str]) -> np.ndarray:
        """Log-likelihood of each marked word by language."""
        out = np.zeros((len(words), len(self.languages)))
        for rows in by_length(words, len(self.languages)):
            out[rows] = PieceGrid(self.trie.grid([words[i] for i in rows])).log_likelihood(self.prob)
        return out


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 3 == 1


def count_words(training: DataFrame) -> DataFrame:
    """(lang, word, n) over all training texts; each task sums its own words before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, Counter] = {}
        held = 0

        def flush() -> Iterator[pa.RecordBatch]:
            for lang, tokens in counts.items():
                words: Counter = Counter()
                for token, n in tokens.items():
                    for w in stretches(token):
                        words[w] += n
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(words), pa.string()), pa.array(list(words)), pa.array(list(words.values()), pa.int64())], ["lang", "word", "n"]) if words else pa.RecordBatch.from_pylist([], schema=pa.schema([("lang", pa.string()), ("word", pa.string()), ("n", pa.int64())]))
            counts.clear()

        for part in slices(batches, "text"):
            for text, lang in zip(strings(part, "text"), part.column("lang").to_pylist(), strict=True):
                counts.setdefault(lang, Counter()).update(text.split())
            held = sum(map(len, counts.values()))
            if held > 400_000:
                yield from flush()
        yield from flush()

    parts = training.where("text is not null and lang is not null").select("text", "lang").mapInArrow(run, "lang string, word string, n long")
    return parts.groupBy("lang", "word").agg(F.sum("n").alias("n"))


def _expected(words: DataFrame, model: LanguageModel) -> dict[tuple[str, int], float]:
    """One E step over the distributed table; what returns is bounded by languages times pieces."""
    shared = words.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: LanguageModel = shared.value
        total = np.zeros((len(m.prob), len(m.languages)))
        place = {lang: k for k, lang in enumerate(m.languages)}
        for batch in batches:
            langs = np.array([place[x] for x in batch.column("lang").to_pylist()], np.int64)
            texts, n = batch.column("word").to_pylist(), np.asarray(batch.column("n"), dtype=float)
            for at in by_length(texts):
                rows = np.array(at)
                grid = PieceGrid(m.trie.grid([texts[i] for i in rows]))
                for lang in np.unique(langs[rows]):
                    mine = langs[rows] == lang
                    total[:, lang] += PieceGrid(grid.ids[mine]).expected(m.prob[:, [lang]], n[rows][mine])
        piece, lang = np.nonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(piece.astype(np.int32)), pa.array(lang.astype(np.int32)), pa.array(total[piece, lang])], ["piece", "lang", "uses"])

    rows = words.mapInArrow(run, "piece int, lang int, uses double").groupBy("piece", "lang").agg(F.sum("uses").alias("uses")).collect()
    return {(r.piece, r.lang): r.uses for r in rows}


def fit(training: DataFrame, pieces: list[str], rounds: int = 2) -> LanguageModel | None:
    """Distributions from (text, lang) rows; None without any word. The first round starts from equal piece probabilities."""
    words = cut(count_words(training))
    found = [r.lang for r in words.select("lang").distinct().limit(MAX_LANGUAGES + 1).collect()]
    if len(found) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages in the labels")
    if not found:
        return None
    known = letter_pieces(pieces)
    model = LanguageModel(known, sorted(found), np.full((len(known) + 1, len(found)), 1.0 / max(1, len(known))))
    model.prob[-1] = FOREIGN
    for _ in range(rounds):
        uses = np.full(model.prob.shape, SMOOTH)
        for (piece, lang), x in _expected(words, model).items():
            uses[piece, lang] += x
        prob = uses / uses[:-1].sum(axis=0)
        prob[-1] = FOREIGN
        model = LanguageModel(known, model.languages, prob)
    return model


class Places(dict):
    """Token to row number; a token not seen yet gets the next row and is noted as new."""

    def __init__(self):
        super().__init__()
        self.new: list[str] = []

    def __missing__(self, token: str) -> int:
        row = self[token] = len(self)
        self.new.append(token)
        return row

    def take_new(self) -> list[str]:
        new, self.new = self.new, []
        return new


class TextScorer:
    """Log-likelihoods of texts for one Python worker; token scores are rows of one bounded array."""

    def __init__(self, model: LanguageModel, limit: int = 2 * CACHE_WORDS):
        self.model = model
        self.place = Places()
        self.limit = limit
        self.sums = np.zeros((0, len(model.languages)))
        self.runs = np.zeros(0, np.int64)

    def _learn(self, tokens: list[str]) -> None:
        """Append the scores of tokens not seen yet."""
        runs = [stretches(t) for t in tokens]
        words = [w for r in runs for w in r]
        known = {w: k for k, w in enumerate(dict.fromkeys(words))}
        values = self.model.word_scores(list(known))
        each = np.fromiter(map(known.__getitem__, words), np.int64, len(words))
        sizes = np.fromiter(map(len, runs), np.int64, len(runs))
        owner = np.repeat(np.arange(len(runs)), sizes)
        sums = np.column_stack([np.bincount(owner, values[each, k], len(runs)) for k in range(values.shape[1])]) if len(words) else np.zeros((len(runs), values.shape[1]))
        self.sums, self.runs = np.vstack([self.sums, sums]), np.concatenate([self.runs, sizes])

    def scores(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(log-likelihood by language, number of letter runs) of each text."""
        tokens = [t.split() for t in texts]
        if len(self.place) > self.limit:
            self.place, self.sums, self.runs = Places(), self.sums[:0], self.runs[:0]
        sizes = np.fromiter(map(len, tokens), np.int64, len(tokens))
        at = np.fromiter(map(self.place.__getitem__, chain.from_iterable(tokens)), np.int64, int(sizes.sum()))
        self._learn(self.place.take_new())
        owner = np.repeat(np.arange(len(texts)), sizes)
        loglik = np.column_stack([np.bincount(owner, self.sums[at, k], len(texts)) for k in range(self.sums.shape[1])])
        return loglik, np.bincount(owner, self.runs[at], len(texts)).astype(np.int64)


def predict(docs: DataFrame, model: LanguageModel | None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, letter_runs, loglik_per_run); reads doc_id and text only."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    kept = held_out(F.col("doc_id")).alias("held_out")
    if model is None:
        return rows.select("doc_id", kept, F.lit(UNKNOWN).alias("lang_pred"), F.lit(0.0).alias("score"), F.lit(0).cast("long").alias("letter_runs"), F.lit(0.0).alias("loglik_per_run"))
    shared = docs.sparkSession.sparkContext.broadcast(model)  # languages times pieces, a bounded size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = TextScorer(shared.value)
        names = np.array(shared.value.languages, object)
        for part in slices(batches, "text"):
            loglik, n = scorer.scores(strings(part, "text"))
            best = loglik.argmax(axis=1)
            top = loglik.max(axis=1)
            score = 1 / np.exp(loglik - top[:, None]).sum(axis=1)
            none = n == 0
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id"), pa.array(np.where(none, UNKNOWN, names[best]).tolist(), pa.string()), pa.array(np.where(none, 0.0, score)), pa.array(n), pa.array(np.where(none, 0.0, top / np.maximum(n, 1)))],
                ["doc_id", "lang_pred", "score", "letter_runs", "loglik_per_run"],
            )

    out = rows.mapInArrow(run, "doc_id long, lang_pred string, score double, letter_runs long, loglik_per_run double")
    return out.select("doc_id", kept, "lang_pred", "score", "letter_runs", "loglik_per_run")


def train_and_predict(docs: DataFrame, pieces: list[str], rounds: int = 2) -> DataFrame:
    """Learn from documents that aren't held out, predict all."""
    model = fit(docs.where(~held_out(F.col("doc_id"))).select("text", "lang"), pieces, rounds)
    return predict(docs, model)


def select(docs: DataFrame, model: LanguageModel | None, least: float) -> DataFrame:
    """The documents in a learned language, found with at least ``least`` probability; all columns as they are, one pass without a join."""
    if model is None:
        return docs.limit(0)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = TextScorer(shared.value)
        for part in slices(batches, "text"):
            loglik, n = scorer.scores(strings(part, "text"))
            sure = 1 / np.exp(loglik - loglik.max(axis=1)[:, None]).sum(axis=1)
            yield part.filter(pa.array((n > 0) & (sure >= least)))

    return docs.mapInArrow(run, docs.schema)
