"""Piece encoding and decoding by vectorised merge rounds.

The vocabulary is a public byte-fallback BPE model file; only its pieces and
scores are read. A text is cut at word marks (no piece of such a vocabulary
holds a mark after another character), distinct words of a chunk are laid out
as one flat symbol array, and every round merges, in each word at once, all
leftmost non-overlapping pairs of that word's best rank. Finished words leave
the array. A word whose merge would open a better pair than the one just used
falls back to its leftmost merge for that round, so the result equals the
sequential agenda of the reference library for any vocabulary.

Defined results: a null text is an empty text; an empty text is begin and end
ids only; repeated rows and ids give repeated results; extra columns are
ignored by the query and may have any name; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.llm.longtable import LongTable
from fedlake.llm.runtime import WordCache, slices, strings

MARK = "▁"
NEVER = np.int32(2**31 - 1)
#: Symbols laid out in one merge array (a longer single word is an array of its own).
FLAT_SYMBOLS = 1 << 19
_WORD = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")


@dataclass
class Vocabulary:
    """Pieces by id with their scores; control ids decode to nothing, byte ids to one byte."""

    pieces: list[str]
    scores: list[float]
    control: set[int]
    byte_ids: dict[int, int]
    unknown: int
    begin: int
    end: int

    @classmethod
    def load(cls, path: str) -> Vocabulary:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        ids = range(model.get_piece_size())
        pieces = [model.id_to_piece(i) for i in ids]
        return cls(
            pieces,
            [model.get_score(i) for i in ids],
            {i for i in ids if model.is_control(i)},
            {int(pieces[i][3:5], 16): i for i in ids if model.is_byte(i)},
            model.unk_id(),
            model.bos_id(),
            model.eos_id(),
        )


class PieceCodec:
    """Encoder and decoder over flat arrays; one per Python worker."""

    def __init__(self, vocab: Vocabulary):
        self.vocab = vocab
        n = len(vocab.pieces)
        special = vocab.control | set(vocab.byte_ids.values()) | {vocab.unknown}
        normal = [i for i in range(n) if i not in special]
        by_text = {vocab.pieces[i]: i for i in normal}
        order = sorted(normal, key=lambda i: (-vocab.scores[i], i))
        self.rank_to_piece = np.array(order, np.int64)
        self.first_char = n  # symbol of a character that is no piece: first_char + code point
        self.char_symbol = np.arange(0x110000, dtype=np.int64) + n
        for text, i in by_text.items():
            if len(text) == 1:
                self.char_symbol[ord(text)] = i
        symbol = lambda s: by_text.get(s, self.char_symbol[ord(s)] if len(s) == 1 else -1)
        keys, ranks = [], []
        for rank, i in enumerate(order):
            text = vocab.pieces[i]
            for k in range(1, len(text)):
                left, right = symbol(text[:k]), symbol(text[k:])
                if left >= 0 and right >= 0:
                    keys.append((int(left) << 22) | int(right))
                    ranks.append(rank)
        self.ranks = LongTable(np.array(keys, np.int64), np.array(ranks, np.int32), int(NEVER))
        inner = {c for t in by_text if len(t) > 1 for c in t}
        self.newline_alone = "\n" not in inner and "\0" not in inner
        if any(MARK in t.lstrip(MARK) for t in by_text):
            raise ValueError("a piece holds a word mark after another character; words can't be encoded apart")
        self._build_decoder(n)
        self.cache = WordCache()

    def pair_rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        return self.ranks((left << 22) | right)

    # -- merge rounds ---------------------------------------------------
    def merge_words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Symbols after all merges, flat, and the end offset of each word."""
        lengths = np.fromiter(map(len, words), np.int64, len(words))
        flat = np.frombuffer("".join(words).encode("utf-32-le"), np.uint32)
        sym = self.char_symbol[flat]
        word = np.repeat(np.arange(len(words)), lengths)
        rank = np.full(len(sym), NEVER, np.int32)
        if len(sym) > 1:
            inside = np.flatnonzero(word[1:] == word[:-1])
            rank[inside] = self.pair_rank(sym[inside], sym[inside + 1])
        done_sym, done_word = [], []
        while len(sym):
            starts = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
            sizes = np.diff(np.r_[starts, len(sym)])
            best = np.minimum.reduceat(rank, starts)
            live = np.repeat(best != NEVER, sizes)
            if not live.all():
                done_sym.append(sym[~live])
                done_word.append(word[~live])
                sym, word, rank = sym[live], word[live], rank[live]
                if not len(sym):
                    break
                sizes, best = sizes[best != NEVER], best[best != NEVER]
            target = np.repeat(best, sizes)
            pick = self._leftmost(rank == target)
            sym, word, rank = self._apply(sym, word, rank, pick)
        if not done_sym:
            return np.empty(0, np.int64), np.cumsum(lengths * 0)
        all_sym, all_word = np.concatenate(done_sym), np.concatenate(done_word)
        order = np.argsort(all_word, kind="stable")
        return all_sym[order], np.cumsum(np.bincount(all_word, minlength=len(words)))

    @staticmethod
    def _leftmost(same: np.ndarray) -> np.ndarray:
        """Positions of every other candidate in each run of adjacent candidates, the first included."""
        at = np.flatnonzero(same)
        new_run = np.r_[True, np.diff(at) != 1]
        run_start = np.maximum.accumulate(np.where(new_run, at, 0))
        return at[(at - run_start) % 2 == 0]

    def _apply(self, sym, word, rank, pick):
        """Merge at the picked positions; words where that could differ from one merge at a time keep only their first."""
        while True:
            used = rank[pick]
            merged = sym.copy()
            merged[pick] = self.rank_to_piece[used]
            keep = np.ones(len(sym), bool)
            keep[pick + 1] = False
            out_sym, out_word, out_rank = merged[keep], word[keep], rank[keep]
            at = pick - np.searchsorted(pick, pick)  # each earlier pick removed one symbol
            left = at - 1
            left = left[(left >= 0)]
            left = left[out_word[left] == out_word[left + 1]]
            touched = np.union1d(left, at)
            last = touched == len(out_sym) - 1
            inner = touched[~last]
            same = out_word[inner] == out_word[inner + 1]
            out_rank[touched] = NEVER
            inner = inner[same]
            out_rank[inner] = self.pair_rank(out_sym[inner], out_sym[inner + 1])
            first = np.r_[True, word[pick[1:]] != word[pick[:-1]]]
            if first.all():
                return out_sym, out_word, out_rank
            level = np.full(int(word[-1]) + 1, NEVER, np.int32)
            level[word[pick]] = used
            bad = set(out_word[inner[out_rank[inner] < level[out_word[inner]]]].tolist())
            near = np.flatnonzero(np.r_[pick[1:] == pick[:-1] + 2, False])
            near = near[word[pick[near]] == word[pick[near + 1]]] if len(near) else near
            if len(near):  # the right neighbour as it stands before its own merge
                early = self.pair_rank(merged[pick[near]], sym[pick[near] + 2])
                bad |= set(word[pick[near[early < used[near]]]].tolist())
            again = np.isin(word[pick], list(bad)) & ~first if bad else np.zeros(len(pick), bool)
            if not again.any():
                return out_sym, out_word, out_rank
            pick = pick[~again]

    def encode_words(self, words: list[str]) -> list[bytes]:
        """Ids of each word as little-endian unsigned 32-bit integers."""
        out: list[bytes] = []
        start, held = 0, 0
        bounds = []
        for k, w in enumerate(words):
            if held and held + len(w) > FLAT_SYMBOLS:
                bounds.append((start, k))
                start, held = k, 0
            held += len(w)
        bounds.append((start, len(words)))
        for a, b in bounds:
            sym, ends = self.merge_words(words[a:b])
            plain = sym.astype("<u4").tobytes()
            foreign = np.zeros(b - a, bool)
            if len(sym):
                owner = np.repeat(np.arange(b - a), np.diff(np.r_[0, ends]))
                foreign[owner[sym >= self.first_char]] = True
            stops = ends.tolist()
            begins = [0, *stops][:-1]
            for k, (i, j) in enumerate(zip(begins, stops, strict=True)):
                out.append(self._with_bytes(sym[i:j]) if foreign[k] else plain[4 * i : 4 * j])
        return out

    def _with_bytes(self, symbols: np.ndarray) -> bytes:
        """Characters outside the vocabulary become the ids of their UTF-8 bytes."""
        ids: list[int] = []
        for s in symbols.tolist():
            if s < self.first_char:
                ids.append(s)
            else:
                ids += [self.vocab.byte_ids.get(x, self.vocab.unknown) for x in chr(s - self.first_char).encode()]
        return np.array(ids, "<u4").tobytes()

    # -- texts ----------------------------------------------------------
    def split(self, text: str) -> list[str]:
        """Words with their leading marks; a lone newline is a word of its own."""
        if not text:
            return []
        if self.newline_alone and "  " not in text and "\n " not in text and MARK not in text and "\0" not in text and text[0] != " ":
            return (MARK + text.replace(" ", "\0" + MARK).replace("\n", "\0\n\0")).split("\0")
        return _WORD.findall(MARK + text.replace(" ", MARK))

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """Ids of each text without begin and end ids, as little-endian unsigned 32-bit integers."""
        parts = [self.split(t) for t in texts]
        words = set()
        for p in parts:
            words.update(p)
        new = self.cache.missing(words)
        if len(new) < len(words):  # the cache may have been emptied just now
            new = [w for w in words if w not in self.cache]
        self.cache.update(zip(new, self.encode_words(new), strict=True))
        get = self.cache.__getitem__
        return [b"".join(map(get, p)) for p in parts]

    def encode(self, text: str, ends: bool = True) -> list[int]:
        ids = np.frombuffer(self.encode_batch([text])[0], "<u4").tolist()
        return [self.vocab.begin, *ids, self.vocab.end] if ends else ids

    # -- decoding -------------------------------------------------------
    def _build_decoder(self, n: int) -> None:
        texts = [p.replace(MARK, " ").encode() for p in self.vocab.pieces]
        for i in self.vocab.control:
            texts[i] = b""
        texts[self.vocab.unknown] = " ⁇ ".encode()
        self.is_byte = np.zeros(n, bool)
        for value, i in self.vocab.byte_ids.items():
            texts[i] = bytes([value])
            self.is_byte[i] = True
        self.piece_bytes = np.frombuffer(b"".join(texts), np.uint8)
        self.piece_size = np.fromiter(map(len, texts), np.int64, n)
        self.piece_start = np.r_[0, np.cumsum(self.piece_size)[:-1]]
        self.marked = np.array([p.startswith(MARK) for p in self.vocab.pieces])
        self.is_control = np.zeros(n, bool)
        self.is_control[list(self.vocab.control)] = True

    def decode_bytes(self, ids: np.ndarray) -> bytes:
        """UTF-8 of the decoded text; the mark put before the first piece is taken off again."""
        ids = ids.astype(np.int64)
        sizes = self.piece_size[ids]
        ends = np.cumsum(sizes)
        total = int(ends[-1]) if len(ends) else 0
        if not total:
            return b""
        where = np.arange(total) + np.repeat(self.piece_start[ids] - (ends - sizes), sizes)
        out = self.piece_bytes[where].tobytes()
        shown = ids[~self.is_control[ids]]
        if len(shown) and self.marked[shown[0]]:
            out = out[1:]
        if self.is_byte[ids].any():
            try:
                out.decode()
            except UnicodeDecodeError:
                out = self._repair(ids).encode()
        return out

    def _repair(self, ids: np.ndarray) -> str:
        """Runs of byte ids that aren't UTF-8: each stray byte becomes one replacement character."""
        text, run, first = [], bytearray(), True

        def flush() -> None:
            k = 0
            while k < len(run):
                for size in (1, 2, 3, 4):
                    try:
                        text.append(bytes(run[k : k + size]).decode())
                        k += size
                        break
                    except UnicodeDecodeError:
                        continue
                else:
                    text.append("�")
                    k += 1
            run.clear()

        for i in ids.tolist():
            piece = self.piece_bytes[self.piece_start[i] : self.piece_start[i] + self.piece_size[i]].tobytes()
            if self.is_byte[i]:
                run += piece
            elif not self.is_control[i]:
                flush()
                text.append(piece.decode()[1 if first and self.marked[i] else 0 :])
            first = first and bool(self.is_control[i])
        flush()
        return "".join(text)

    def decode(self, ids: list[int]) -> str:
        return self.decode_bytes(np.array(ids, np.int64)).decode()


SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def encode_digests(docs: DataFrame, vocab: Vocabulary, with_ids: bool = False) -> DataFrame:
    """Encode every text with begin and end ids and decode those ids again.

    Returns (doc_id, n_tokens, ids_sha256, decoded_sha256) and, on request, the
    ids themselves as ``ids array<int>``. No shuffle: one pass over the texts,
    holding a bounded chunk of them at a time.
    """
    shared = docs.sparkSession.sparkContext.broadcast(vocab)  # one model file, a fixed size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = PieceCodec(shared.value)
        head, tail = (np.array([x], "<u4").tobytes() for x in (codec.vocab.begin, codec.vocab.end))
        for part in slices(batches, "text"):
            coded = [head + x + tail for x in codec.encode_batch(strings(part, "text"))]
            ids = [np.frombuffer(x, "<u4") for x in coded]
            columns = [
                part.column("doc_id"),
                pa.array([len(x) for x in ids], pa.int64()),
                pa.array([hashlib.sha256(x).hexdigest() for x in coded]),
                pa.array([hashlib.sha256(codec.decode_bytes(x)).hexdigest() for x in ids]),
            ]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if with_ids:
                columns.append(pa.array([x.astype(np.int32) for x in ids], pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names)

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, SCHEMA + ", ids array<int>" * with_ids)


def decode_ids(coded: DataFrame, vocab: Vocabulary) -> DataFrame:
    """(doc_id, ids) to (doc_id, text); null ids give an empty text."""
    shared = coded.sparkSession.sparkContext.broadcast(vocab)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = PieceCodec(shared.value)
        for part in batches:
            texts = [codec.decode(x or []) for x in part.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

    return coded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")
