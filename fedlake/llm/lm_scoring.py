"""LM scoring by masked pseudo-likelihood.

A bidirectional window network, written and trained in numpy, predicts every
token of a text from the tokens on both sides of it; the summed conditional
log-probabilities score the document.

Tokens are the words of the text: the most frequent ones of the whole corpus by
name, all others by hash bucket and spelling: log P(bucket) from the network plus
the log-probability of the word's bytes up to its end under a model of byte pairs,
counted over all words without a name. A rare word so has a probability of its own;
those of all words of a bucket sum to at most the bucket's. The network looks
up the embeddings of the window (absent neighbours have one of their own),
passes them through a tanh layer, and predicts through a two-level softmax: a
class of 64 tokens, then the token within it. Output biases start at corpus
frequencies.

Training covers the corpus and grows with it. Every input split trains a copy
from the current parameters over its own documents, and the copies are averaged
by their number of tokens in one distributed sum of fixed-point values. Every
token is a target exactly once: one round trains on all of them, and more rounds
(``stride``) would share them out by runs of eight consecutive tokens. The driver
holds one set of parameters and the frequent words, whatever the corpus' size.
Words are looked up once: training and scoring read the coded texts, two bytes a
token, from the shared checkpoint folder.

Defined results: null, empty and blank texts have no tokens and score 0;
repeated rows train and score again; ties of word frequency go to the word first
by bytes; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import chain
from math import prod
from zlib import crc32

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.llm.runtime import CACHE_WORDS, CHUNK_BYTES, cut, one_blas_thread, slices

CLASS = 64
CLASSES = 64
TOKENS = CLASS * CLASSES
NAMED = 3072
WINDOW = 2
WIDTH = 16
HIDDEN = 24
#: Each round trains on one of every STRIDE runs of RUN consecutive tokens; the rounds cover all of them.
RUN = 8
STRIDE = 1
ROUNDS = STRIDE
BATCH = 4096
SCORED = 16384
RATE = 0.15
FIXED = 1 << 20
SEED = 17
ABSENT = TOKENS
#: The byte around a word in its spelling; words hold no white space.
END = 10


class Room(dict):
    """Named arrays used again from batch to batch: the pages of a fresh one cost more than most of what is computed into it."""

    def __call__(self, name: str, shape: tuple[int, ...], dtype: np.dtype) -> np.ndarray:
        size, held = prod(shape), self.get(name)
        if held is None or held.size < size or held.dtype != dtype:
            held = self[name] = np.empty(size, dtype)
        return held[:size].reshape(shape)

    def __reduce__(self):
        return Room, ()

    def product(self, name: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.matmul(a, b, out=self(name, (len(a), b.shape[1]), a.dtype))

    def rows(self, name: str, table: np.ndarray, at: np.ndarray) -> np.ndarray:
        """The table's rows at these places, all of which it has (``clip`` spares a buffer)."""
        return table.take(at, axis=0, out=self(name, (len(at), *table.shape[1:]), table.dtype), mode="clip")


@dataclass
class WindowNet:
    """Parameters by name; ``flat`` and ``load`` move them as one vector."""

    parts: dict[str, np.ndarray] = field(default_factory=dict)
    room: Room = field(default_factory=Room, repr=False, compare=False)

    @classmethod
    def start(cls, frequency: np.ndarray, seed: int = SEED) -> WindowNet:
        """Random weights and output biases at the log frequencies of the tokens."""
        r = np.random.default_rng(seed)
        p = (frequency + 1.0).reshape(CLASSES, CLASS)
        by_class = p.sum(axis=1)
        normal = lambda *s: (r.standard_normal(s) / np.sqrt(s[-2])).astype(np.float32)
        return cls(
            {
                "embed": (r.standard_normal((TOKENS + 1, WIDTH)) * 0.1).astype(np.float32),
                "hidden": normal(2 * WINDOW * WIDTH, HIDDEN),
                "hidden_bias": np.zeros(HIDDEN, np.float32),
                "class": normal(HIDDEN, CLASSES) * 0.1,
                "class_bias": np.log(by_class / by_class.sum()).astype(np.float32),
                "token": normal(CLASSES, HIDDEN, CLASS) * 0.1,
                "token_bias": np.log(p / by_class[:, None]).astype(np.float32),
            }
        )

    def flat(self) -> np.ndarray:
        return np.concatenate([x.ravel() for x in self.parts.values()])

    def load(self, values: np.ndarray) -> WindowNet:
        out, at = {}, 0
        for name, x in self.parts.items():
            out[name] = values[at : at + x.size].reshape(x.shape).astype(np.float32)
            at += x.size
        return WindowNet(out)

    def forward(self, context: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(window embeddings, hidden values), valid until the next call."""
        p = self.parts
        seen = self.room.rows("seen", p["embed"], context.ravel()).reshape(len(context), -1)
        h = self.room.product("h", seen, p["hidden"])
        h += p["hidden_bias"]
        return seen, np.tanh(h, out=h)

    def logits(self, h: np.ndarray, cls: np.ndarray, spans: list[tuple[int, slice]]) -> tuple[np.ndarray, np.ndarray]:
        """(of the classes, of the tokens in each row's class), valid until the next call."""
        p = self.parts
        classes, tokens = self.room.product("classes", h, p["class"]), self.room.rows("tokens", p["token_bias"], cls)
        classes += p["class_bias"]
        for c, rows in spans:
            tokens[rows] += h[rows] @ p["token"][c]
        return classes, tokens

    def log_probs(self, context: np.ndarray, target: np.ndarray) -> np.ndarray:
        """log P(target | both sides) of each row."""
        safe = self.bounded
        order = np.argsort((target // CLASS).astype(np.uint8), kind="stable")  # a class is then a slice
        target = target[order]
        cls = target // CLASS
        _, h = self.forward(context.take(order, axis=0))
        classes, tokens = self.logits(h, cls, _spans(cls))
        out = np.empty(len(target), h.dtype)
        out[order] = _log_softmax(classes, cls, safe) + _log_softmax(tokens, target % CLASS, safe)
        return out

    @property
    def bounded(self) -> bool:
        """Whether no logit can leave the range of single-precision exponentials (hidden values lie in [-1, 1])."""
        p = self.parts
        most = max((np.abs(p[k]).sum(axis=-2) + np.abs(p[k + "_bias"])).max() for k in ("class", "token"))
        return bool(most < 70)

    def gradients(self, context: np.ndarray, target: np.ndarray) -> dict[str, np.ndarray]:
        """Of the mean negative log-probability; valid until the next call."""
        p, safe, n, room = self.parts, self.bounded, len(target), self.room
        g = {k: room("d " + k, v.shape, v.dtype) for k, v in p.items()}
        order = np.argsort((target // CLASS).astype(np.uint8), kind="stable")  # a class is then a slice
        context, target = context.take(order, axis=0), target[order]
        cls = target // CLASS
        spans = _spans(cls)
        seen, h = self.forward(context)
        classes, tokens = self.logits(h, cls, spans)
        one = np.ones(n, h.dtype)
        d = _softmax_error(classes, cls, n, safe)
        np.matmul(h.T, d, out=g["class"])
        np.matmul(one, d, out=g["class_bias"])
        back = room.product("back", d, p["class"].T)
        d = _softmax_error(tokens, target % CLASS, n, safe)
        g["token"].fill(0)
        g["token_bias"].fill(0)
        for c, rows in spans:
            mine = d[rows]
            np.matmul(h[rows].T, mine, out=g["token"][c])
            np.matmul(one[rows], mine, out=g["token_bias"][c])
            back[rows] += mine @ p["token"][c].T
        np.multiply(h, h, out=h)
        back *= np.subtract(1, h, out=h)
        np.matmul(seen.T, back, out=g["hidden"])
        np.matmul(one, back, out=g["hidden_bias"])
        into = room.product("into", back, p["hidden"].T).reshape(-1, WIDTH)
        key = context.ravel().astype(np.uint16)
        order = np.argsort(key, kind="stable")  # by radix
        key = key[order]
        starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        g["embed"].fill(0)
        ordered = room.rows("ordered", into, order)
        pairs = ordered.view(np.result_type(ordered.dtype, np.complex64))  # two components an addition
        g["embed"][key[starts]] = np.add.reduceat(pairs, starts, axis=0).view(ordered.dtype)
        return g


def _spans(cls: np.ndarray) -> list[tuple[int, slice]]:
    """The classes that occur among rows in order of class, with their rows."""
    edges = np.searchsorted(cls, np.arange(CLASSES + 1)).tolist()
    return [(c, slice(edges[c], edges[c + 1])) for c in range(CLASSES) if edges[c + 1] > edges[c]]


def _log_softmax(logits: np.ndarray, at: np.ndarray, bounded: bool = False) -> np.ndarray:
    """Log-probability of one column per row; ``bounded`` logits can't overflow and need no shift. The logits are used up."""
    if not bounded:
        logits -= logits.max(axis=1)[:, None]
    picked = logits[np.arange(len(at)), at]
    np.exp(logits, out=logits)
    return picked - np.log(logits @ np.ones(logits.shape[1], logits.dtype))


def _softmax_error(logits: np.ndarray, at: np.ndarray, n: int, bounded: bool) -> np.ndarray:
    """Derivatives of the mean negative log-probability over n rows, in place of the logits."""
    if not bounded:
        logits -= logits.max(axis=1)[:, None]
    np.exp(logits, out=logits)
    logits *= (logits.dtype.type(1 / n) / (logits @ np.ones(logits.shape[1], logits.dtype)))[:, None]
    logits[np.arange(len(at)), at] -= logits.dtype.type(1 / n)
    return logits


class Trainer:
    """Adagrad over batches of positions; one per input split."""

    def __init__(self, net: WindowNet, rate: float = RATE):
        self.net, self.rate = net.load(net.flat().copy()), rate
        self.square = {k: np.full_like(v, 1e-4) for k, v in net.parts.items()}

    def step(self, context: np.ndarray, target: np.ndarray) -> None:
        for k, g in self.net.gradients(context, target).items():
            s = self.square[k]
            move = np.multiply(g, g, out=self.net.room("move", g.shape, g.dtype))
            s += move
            np.divide(g, np.sqrt(s, out=move), out=move)
            move *= self.rate
            self.net.parts[k] -= move


class TokenIds(dict):
    """Words to token ids for one Python worker: named ones by rank, the others by hash bucket, kept up to a limit."""

    def __init__(self, named: list[bytes], limit: int = 2 * CACHE_WORDS):
        super().__init__((w, k) for k, w in enumerate(named))
        self.limit = limit
        self[None] = ABSENT  # stands between texts

    def __missing__(self, word: bytes) -> int:
        token = bucket(word)
        if len(self) < self.limit:
            self[word] = token
        return token


def bucket(word: bytes) -> int:
    """The token of a word without a name."""
    return NAMED + crc32(word) % (TOKENS - NAMED)


def buckets(words: list[bytes]) -> np.ndarray:
    """``bucket`` of each word."""
    return NAMED + np.fromiter(map(crc32, words), np.int64, len(words)) % (TOKENS - NAMED)


def spell(words: list[bytes], pairs: np.ndarray) -> np.ndarray:
    """Log-probability of each word's bytes up to its end; pairs: flat, 256 by 256."""
    end = bytes([END])
    raw = np.frombuffer(end + end.join(words) + end, np.uint8).astype(np.int32)
    starts = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    return np.add.reduceat(pairs.take(raw[:-1] * 256 + raw[1:]), np.r_[0, starts[:-1]])


def stream(texts: list[bytes]) -> tuple[list[bytes | None], np.ndarray]:
    """(words of all texts with absent neighbours around each, words per text)."""
    words, gap = [t.split() for t in texts], [None] * WINDOW
    return list(chain(gap, chain.from_iterable(chain(ws, gap) for ws in words))), np.fromiter(map(len, words), np.int64, len(words))


def places(sizes: np.ndarray) -> np.ndarray:
    """Positions of the words in the stream."""
    starts = WINDOW + np.cumsum(np.r_[0, sizes[:-1] + WINDOW]) if len(sizes) else sizes
    return np.repeat(starts - np.r_[0, np.cumsum(sizes)[:-1]], sizes) + np.arange(int(sizes.sum())) if len(sizes) else sizes


def lay_out(ids: TokenIds, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(flat ids with absent neighbours around every text, positions of tokens, tokens per text)."""
    words, sizes = stream(texts)
    return np.fromiter(map(ids.__getitem__, words), np.int32, len(words)), places(sizes), sizes


def target_places(at: np.ndarray, residue: int, stride: int) -> np.ndarray:
    """One of every ``stride`` runs of consecutive tokens."""
    return at[np.arange(len(at)) // RUN % stride == residue] if stride > 1 else at


def training_rows(ids: TokenIds, texts: list[bytes], residue: int, stride: int) -> tuple[np.ndarray, np.ndarray]:
    """(contexts, targets) of one round."""
    flat, at, _ = lay_out(ids, texts)
    return windows(flat, target_places(at, residue, stride))


def windows(flat: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(contexts, targets) of the tokens at these places."""
    return flat[at[:, None] + OFFSETS], flat[at]


def shuffled(at: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """The places in a random order of runs, whose neighbours stay together in memory; the last, shorter run comes last."""
    whole = len(at) // RUN * RUN
    return np.concatenate([at[:whole].reshape(-1, RUN)[rng.permutation(whole // RUN)].ravel(), at[whole:]])


OFFSETS = np.array([k for k in range(-WINDOW, WINDOW + 1) if k])


def split_words(part: pa.RecordBatch) -> pa.Array:
    """The texts' pieces between ASCII white space, a list a text, by the same white space as ``bytes.split``; outer white space leaves empty pieces, which are no words."""
    return pc.ascii_split_whitespace(pc.fill_null(part.column("text"), ""))


def tally(counts: pa.Table) -> pa.Table:
    """(word, n) with the counts of equal words summed."""
    return counts.group_by("word", use_threads=False).aggregate([("n", "sum")]).rename_columns(["word", "n"])


def counted_words(docs: DataFrame) -> DataFrame:
    """(word, n) of all documents: exact counts, summed per split first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []
        for part in slices(batches, "text", 2 * CHUNK_BYTES):
            word, n = split_words(part).flatten().value_counts().flatten()
            held.append(pa.table({"word": word.cast(pa.binary()), "n": n}).filter(pc.greater(pc.binary_length(word), 0)))
            if sum(t.num_rows for t in held) > 400_000:
                held = [tally(pa.concat_tables(held))]
            if held[0].num_rows > 400_000:
                yield from held.pop().combine_chunks().to_batches()
            pa.default_memory_pool().release_unused()  # workers live on into the next stages
        if held:
            yield from tally(pa.concat_tables(held)).combine_chunks().to_batches()

    return cut(docs.select(F.col("text").cast("string").alias("text")).mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")))


def corpus_tokens(docs: DataFrame) -> tuple[list[bytes], np.ndarray]:
    """The most frequent words of all documents, and how often each token occurs."""
    return token_counts(counted_words(docs))


def token_counts(words: DataFrame) -> tuple[list[bytes], np.ndarray]:
    """The most frequent of the counted words, and how often each token occurs."""
    # every partition sends its best to the driver, so only words about as frequent as the last named one take part
    levels = words.groupBy(F.length(F.bin("n")).alias("bits")).agg(F.count("*").alias("words")).orderBy(F.col("bits").desc()).collect()  # at most 64 rows
    upto = np.cumsum([r.words for r in levels])
    least = levels[min(int(np.searchsorted(upto, NAMED)), len(levels) - 1)].bits if levels else 1
    rows = words.where(F.length(F.bin("n")) >= least).orderBy(F.col("n").desc(), "word").limit(NAMED).collect()
    named = [bytes(r.word) for r in rows]
    frequency = np.zeros(TOKENS)
    frequency[: len(rows)] = [r.n for r in rows]
    total = words.sparkSession.sparkContext.broadcast(set(named))

    def others(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            token = np.fromiter((bucket(w) if w not in total.value else -1 for w in batch.column("word").to_pylist()), np.int64, batch.num_rows)
            sums = np.bincount(token[token >= 0], np.asarray(batch.column("n"))[token >= 0], TOKENS)
            at = np.flatnonzero(sums)
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(sums[at].astype(np.int64))], ["token", "n"])

    for r in words.mapInArrow(others, "token int, n long").groupBy("token").agg(F.sum("n").alias("n")).collect():  # at most TOKENS rows
        frequency[r.token] = r.n
    return named, frequency


def byte_pairs(words: DataFrame, named: list[bytes]) -> np.ndarray:
    """Log-probabilities of each byte after each other, over the words without a name; END stands around a word."""
    known = words.sparkSession.sparkContext.broadcast(set(named))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rare = [(w, n) for w, n in zip(batch.column("word").to_pylist(), batch.column("n").to_pylist(), strict=True) if w not in known.value]
            if not rare:
                continue
            end = bytes([END])
            raw = np.frombuffer(end + end.join(w for w, _ in rare) + end, np.uint8).astype(np.int64)
            times = np.repeat([n for _, n in rare], [len(w) + 1 for w, _ in rare])
            sums = np.bincount(raw[:-1] * 256 + raw[1:], times, 65536)
            at = np.flatnonzero(sums)
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(sums[at].astype(np.int64))], ["pair", "n"])

    counts = np.ones(65536)
    for r in words.mapInArrow(run, "pair int, n long").groupBy("pair").agg(F.sum("n").alias("n")).collect():  # at most 65,536 rows
        counts[r.pair] += r.n
    counts = counts.reshape(256, 256)
    return np.log(counts / counts.sum(axis=1)[:, None])


class Spelling:
    """Log-probability of a word's bytes; nothing for words with a name."""

    def __init__(self, named: list[bytes], pairs: np.ndarray):
        self.named, self.pairs = set(named), pairs.ravel()

    def __getitem__(self, word: bytes) -> float:
        return 0.0 if word in self.named else float(spell([word], self.pairs)[0])


def code(docs: DataFrame, named: list[bytes], pairs: np.ndarray | None = None) -> DataFrame:
    """(doc_id, tokens, spelled): the token of every word in 16 bits each, and the summed spelling of the words without a name."""
    shared = docs.sparkSession.sparkContext.broadcast((named, pairs))  # fixed sizes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        named, pairs = shared.value
        known = pa.array(named, pa.binary())
        for part in slices(batches, "text", 2 * CHUNK_BYTES):
            words = split_words(part)
            sizes, pieces = np.asarray(pc.list_value_length(words)).astype(np.int64), words.flatten().dictionary_encode()
            distinct, at = pieces.dictionary.cast(pa.binary()), np.asarray(pieces.indices)
            token = np.asarray(pc.fill_null(pc.index_in(distinct, known), -1)).astype(np.int32)
            spelled = np.zeros(len(token))
            rare = np.flatnonzero(token < 0)
            if len(rare):
                texts = distinct.take(pa.array(rare)).to_pylist()
                token[rare] = buckets(texts)
                spelled[rare] = 0 if pairs is None else spell(texts, pairs.ravel())
            empty = np.asarray(pc.equal(pc.binary_length(distinct), 0))
            if empty.any():
                word = ~empty[at]
                sizes = np.diff(np.r_[0, np.cumsum(word)][np.r_[0, np.cumsum(sizes)]])
                at = at[word]
            ends = np.cumsum(sizes)
            tokens, spelled = token[at].astype("<u2"), np.r_[0.0, np.cumsum(spelled[at])]
            cells = [tokens[b - n : b].tobytes() for b, n in zip(ends.tolist(), sizes.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(cells, pa.binary()), pa.array(spelled[ends] - spelled[ends - sizes])], ["doc_id", "tokens", "spelled"])
            pa.default_memory_pool().release_unused()  # workers live on into the next stages

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, tokens binary, spelled double")


def coded_stream(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(flat ids with absent neighbours around every text, positions of tokens, tokens per text) of coded texts."""
    cells = part.column("tokens").to_pylist()
    sizes = np.fromiter(map(len, cells), np.int64, len(cells)) // 2
    at = places(sizes)
    flat = np.full(int(sizes.sum()) + WINDOW * (len(cells) + 1), ABSENT, np.int32)
    flat[at] = np.frombuffer(b"".join(cells), "<u2")
    return flat, at, sizes


def train_round(docs: DataFrame, named: list[bytes], net: WindowNet, residue: int, stride: int = STRIDE) -> WindowNet:
    """One round over all documents: local training in every split, then the average weighted by tokens."""
    return train_coded(code(docs, named), net, residue, stride)


def train_coded(coded: DataFrame, net: WindowNet, residue: int, stride: int = STRIDE) -> WindowNet:
    shared = coded.sparkSession.sparkContext.broadcast(net)  # a fixed size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one_blas_thread()
        trainer, used = Trainer(shared.value), 0
        for part in slices(batches, "tokens", CHUNK_BYTES):
            flat, at, _ = coded_stream(part)
            at = shuffled(target_places(at, residue, stride), np.random.default_rng(SEED + residue))
            for k in range(0, len(at), BATCH):
                trainer.step(*windows(flat, at[k : k + BATCH]))
            used += len(at)
        if used:
            values = np.rint(trainer.net.flat().astype(np.float64) * FIXED).astype(np.int64) * used
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(-1, len(values), dtype=np.int32)), pa.array(np.r_[used, values])], ["cell", "value"])

    whole = F.sum(F.col("value").cast("decimal(38,0)"))  # exact in any order and at any number of tokens
    sums = coded.select("tokens").mapInArrow(run, "cell int, value long").groupBy("cell").agg(whole.alias("value"))
    cells = sums.select("cell", F.col("value").cast("double").alias("value")).toArrow()  # one row a parameter
    if not cells.num_rows:
        return net
    order = np.argsort(np.asarray(cells.column("cell")))
    values = np.asarray(cells.column("value"))[order]
    return net.load(values[1:] / values[0] / FIXED)


def train(docs: DataFrame, rounds: int = ROUNDS, stride: int = STRIDE) -> tuple[list[bytes], WindowNet, np.ndarray]:
    """(named words, network, spelling) of all documents."""
    named, pairs, net, _ = _trained(docs, rounds, stride)
    return named, net, pairs


def _trained(docs: DataFrame, rounds: int, stride: int) -> tuple[list[bytes], np.ndarray, WindowNet, DataFrame]:
    words = counted_words(docs)
    named, frequency = token_counts(words)
    pairs = byte_pairs(words, named)
    coded = cut(code(docs, named, pairs))  # about a third of the texts' size; the rounds and the scores read this
    net = WindowNet.start(frequency)
    for k in range(rounds):
        net = train_coded(coded, net, k % stride, stride)
    return named, pairs, net, coded


def score(docs: DataFrame, named: list[bytes], net: WindowNet, pairs: np.ndarray | None = None) -> DataFrame:
    """(doc_id, n_tokens, pseudo_loglik, per_token): every token of every text is predicted, and with ``pairs`` spelled where it has no name."""
    return score_coded(code(docs, named, pairs), net)


def score_coded(coded: DataFrame, net: WindowNet) -> DataFrame:
    shared = coded.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one_blas_thread()
        for part in slices(batches, "tokens", CHUNK_BYTES // 4):
            flat, at, sizes = coded_stream(part)
            each = [shared.value.log_probs(*windows(flat, at[k : k + SCORED])) for k in range(0, len(at), SCORED)]
            owner = np.repeat(np.arange(len(sizes)), sizes)
            total = np.asarray(part.column("spelled")) + np.bincount(owner, np.concatenate(each) if each else None, len(sizes))
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(sizes), pa.array(total), pa.array(total / np.maximum(sizes, 1))], ["doc_id", "n_tokens", "pseudo_loglik", "per_token"])

    return coded.mapInArrow(run, "doc_id long, n_tokens long, pseudo_loglik double, per_token double")


def train_and_score(docs: DataFrame) -> DataFrame:
    *_, net, coded = _trained(docs, ROUNDS, STRIDE)
    return score_coded(coded, net)
