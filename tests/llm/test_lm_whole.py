"""Language-model scoring uses the whole corpus."""

from collections import Counter

import numpy as np

from fedlake.llm import lm_scoring


def test_rounds_train_every_token_once():
    texts = [b" ".join(b"w%d" % (k * 37 + i) for i in range(k % 23)) for k in range(200)]
    ids = lm_scoring.TokenIds([])
    targets = [lm_scoring.training_rows(ids, texts, k % lm_scoring.STRIDE, lm_scoring.STRIDE)[1] for k in range(lm_scoring.ROUNDS)]
    flat, at, _ = lm_scoring.lay_out(ids, texts)
    assert np.array_equal(np.sort(np.concatenate(targets)), np.sort(flat[at]))


def test_rare_words_of_a_bucket_differ_by_their_spelling(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet").limit(40)
    named, net, pairs = lm_scoring.train(docs)
    assert lm_scoring.NAMED >= 3072 and np.allclose(np.exp(pairs).sum(axis=1), 1)
    buckets = {}
    for k in range(100_000):
        word = b"zq" * (k % 9) + b"%d" % k
        other = buckets.setdefault(lm_scoring.TokenIds([])[word], word)
        if len(other) != len(word):
            break
    texts = [other.decode(), word.decode()]
    rows = lm_scoring.score(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), named, net, pairs).orderBy("doc_id").collect()
    spelling = lm_scoring.Spelling(named, pairs)
    assert rows[0].pseudo_loglik != rows[1].pseudo_loglik
    assert np.isclose(rows[0].pseudo_loglik - rows[1].pseudo_loglik, spelling[other] - spelling[word], atol=1e-4)


ODD = [None, "", "  \t\n", " a  b\x0bc\x0c d\r\n", "one two\x1cthree\x00four five   x", " ", "w" * 5000, "b a b", "Ünï çode ünï"]


def test_words_are_those_of_bytes_split(spark):
    """Counts, tokens and spellings of texts with all kinds of white space."""
    docs = spark.createDataFrame(list(enumerate(ODD)), "doc_id long, text string").coalesce(1)
    words = [(t or "").encode().split() for t in ODD]
    counts = Counter(w for ws in words for w in ws)
    assert {bytes(r.word): r.n for r in lm_scoring.counted_words(docs).collect()} == counts
    named, pairs = [b"a", b"b"], np.log(np.random.default_rng(1).random((256, 256)))
    ids, spelling = lm_scoring.TokenIds(named), lm_scoring.Spelling(named, pairs)
    for r in lm_scoring.code(docs, named, pairs).collect():
        assert np.frombuffer(bytes(r.tokens), "<u2").tolist() == [ids[w] for w in words[r.doc_id]]
        assert np.isclose(r.spelled, sum(spelling[w] for w in words[r.doc_id]))


def test_kernel_arrays_are_used_again():
    """A second step makes no large arrays, and what it computes doesn't depend on the first."""
    r = np.random.default_rng(5)
    net = lm_scoring.WindowNet.start(r.integers(1, 100, lm_scoring.TOKENS).astype(float))
    batch = lambda n: (r.integers(0, lm_scoring.TOKENS + 1, (n, 2 * lm_scoring.WINDOW)), r.integers(0, lm_scoring.TOKENS, n))
    first, second = batch(lm_scoring.BATCH), batch(500)
    alone = {k: g.copy() for k, g in net.gradients(*second).items()}
    net.gradients(*first)
    held = {k: x.ctypes.data for k, x in net.room.items()}
    assert all(np.array_equal(g, alone[k]) for k, g in net.gradients(*second).items())
    assert held == {k: x.ctypes.data for k, x in net.room.items()}
