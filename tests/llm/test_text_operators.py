"""The text operators against brute force, round trips and held-out accuracy, and on awkward rows."""

from __future__ import annotations

import hashlib
import random
import re
from collections import Counter
from zlib import crc32

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from fedlake.llm import chat_format, language_id, license_scan, lm_scoring, mixing, piece_codec, quality_classifier, quality_rules, simhash, vector_join
from fedlake.llm import queries as Q

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, hash long, fp long, row string, _first long"


@pytest.fixture(scope="module")
def awkward(spark):
    """Nulls everywhere, blanks, long texts, repeats, clashing extra columns."""
    long_text = "lorem ipsum dolor sit amet " * 8000
    texts = [None, "", "  \n\t ", "word", "one two", "the cat the cat", long_text, "x" * 5000, "été ▁▁ 日本語 \x00 \\ <|im_end|>", "the cat the cat", "Released under the MIT License."]
    rows = [(k, t, "en" if k % 2 else None, f"s{k % 3}" if k % 4 else None, len(t or ""), k, k, k, "r", k) for k, t in enumerate(texts)]
    rows += [(None, "no id here", "en", "s1", 1, None, None, None, None, None), rows[5], rows[5]]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def documents(spark, folder):
    return spark.read.parquet(f"{folder}/documents.parquet")


@pytest.fixture(scope="module")
def vocab():
    return Q.vocabulary()


def operators(spark, vocab):
    labels = spark.createDataFrame([(k, k % 2, int(k % 5 == 0)) for k in range(11)] + [(None, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    return {
        "lm": lambda d: lm_scoring.train_and_score(d),
        "license": lambda d: license_scan.scan_documents(d),
        "language": lambda d: language_id.train_and_predict(d, vocab.pieces),
        "codec": lambda d: piece_codec.encode_digests(d, vocab, True),
        "rules": lambda d: quality_rules.judge(d),
        "mix": lambda d: mixing.mix_documents(d),
        "classifier": lambda d: quality_classifier.score(d, quality_classifier.fit(d, labels)),
        "simhash": lambda d: simhash.near_groups(d),
    }


@pytest.mark.parametrize("name", ["lm", "license", "language", "codec", "rules", "mix", "classifier", "simhash"])
def test_awkward_rows_keep_their_number(name, spark, vocab, awkward, empty):
    op = operators(spark, vocab)[name]
    assert op(awkward).count() == awkward.count()
    assert op(empty).count() == 0


def test_selections_keep_columns(spark, vocab, awkward, empty):
    labels = spark.createDataFrame([(1, 1, 0)], "doc_id long, quality int, toxic int")
    for d in (awkward, empty):
        model = quality_classifier.fit(d, labels)
        for out in (quality_classifier.select(d, model), language_id.select(d, language_id.fit(d, vocab.pieces), 0.5), simhash.one_per_group(d), mixing.apply_mix(d), quality_rules.keep(d)):
            assert sorted(out.columns) == sorted(d.columns)
            out.count()


# -- language -------------------------------------------------------------
def test_forward_is_the_sum_over_segmentations(vocab):
    pieces = language_id.letter_pieces(vocab.pieces)
    prob = np.random.default_rng(0).random((len(pieces) + 1, 2)) / 100
    prob[-1] = 1e-7
    model = language_id.LanguageModel(pieces, ["a", "b"], prob)

    def brute(word, lang):
        if not word:
            return 1.0
        total = 0.0
        for k in range(1, len(word) + 1):
            if word[:k] in pieces:
                total += prob[pieces[word[:k]], lang] * brute(word[k:], lang)
            elif k == 1:
                total += prob[-1, lang] * brute(word[k:], lang)
        return total

    for w in ("▁thing", "▁schön", "▁a", "▁the字x"):
        assert np.allclose(np.exp(model.word_scores([w]))[0], [brute(w, 0), brute(w, 1)])
    grid = language_id.PieceGrid(model.trie.grid(["▁thing"]))
    uses = grid.expected(prob[:, [0]], np.array([2.0]))
    spelled = sum(uses[k] * len(p) for p, k in pieces.items() if uses[k]) + uses[-1]
    assert abs(spelled - 2 * len("▁thing")) < 1e-6


def test_held_out_language_accuracy(documents, vocab):
    rows = language_id.train_and_predict(documents, vocab.pieces).join(documents.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert all(crc32(str(r.doc_id).encode()) % 3 == 1 and 0 <= r.score <= 1 for r in rows)
    assert sum(r.lang == r.lang_pred for r in rows) >= 0.97 * len(rows)


def test_no_letters_is_undetermined(spark, vocab):
    d = spark.createDataFrame([(1, "the and of", "en"), (2, "123 !!", "en"), (3, None, "en")], "doc_id long, text string, lang string")
    got = {r.doc_id: (r.lang_pred, r.score) for r in language_id.train_and_predict(d, vocab.pieces).collect()}
    assert got[2] == got[3] == ("und", 0.0) and got[1][0] == "en"


# -- pieces ---------------------------------------------------------------
def test_codec_equals_the_library(vocab, documents):
    import public_tokenizers
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(Q.VOCABULARY))
    codec = piece_codec.PieceCodec(vocab)
    r = random.Random(1)
    texts = ["", " ", "  a  b ", "a\n\nb", "▁x", " \tabc", "\x00", "😀é▁▁ b", "<s>hi</s> <0x41>", "ａ ﬁ ①\r\n", "a" * 300]
    texts += ["".join(r.choice("abthe in▁\n  éß=-/0189 ") for _ in range(r.randint(0, 60))) for _ in range(400)]
    texts += ["".join(r.choice("ab=-_ ") for _ in range(300)) for _ in range(40)]
    texts += [x.text for x in documents.limit(60).collect()]
    for t in texts:
        ids = library.encode(t, add_bos=True, add_eos=True)
        assert codec.encode(t) == ids
        assert codec.decode(ids) == library.decode(ids)


def test_broken_byte_runs_become_replacement_characters(vocab):
    codec = piece_codec.PieceCodec(vocab)
    ids = [vocab.byte_ids[0xE9], vocab.byte_ids[0x41]]
    assert codec.decode(ids) == "�A"


def test_ids_decode_in_spark(awkward, vocab):
    coded = piece_codec.encode_digests(awkward, vocab, True)
    back = {(r.doc_id, r.text) for r in piece_codec.decode_ids(coded, vocab).collect()}
    assert back == {(r.doc_id, (r.text or "").replace("▁", " ")) for r in awkward.collect()}


# -- quality rules --------------------------------------------------------
def brute_stats(text):
    words = WORD.findall(text)
    windows = Counter(tuple(words[i : i + 5]) for i in range(len(words) - 4))
    inside = {j for i in range(len(words) - 4) if windows[tuple(words[i : i + 5])] > 1 for j in range(i, i + 5)}
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, len(inside)


def test_statistics_by_brute_force(documents, awkward):
    for d in (documents, awkward):
        texts = d.select("text").collect()
        got = Counter(tuple(r[k] for k in quality_rules.STATS) for r in quality_rules.statistics(d).collect())
        assert got == Counter(brute_stats(r.text or "") for r in texts)


def test_robust_estimate_ignores_outliers(spark):
    r = np.random.default_rng(3)
    n, names = 600, quality_rules.NAMES
    good = r.multivariate_normal([1.5, 0.3, 0.4, 0.2], np.diag([0.3, 0.2, 0.3, 0.1]) ** 2 * 4, n)
    bad = r.multivariate_normal([6, 5, 5, 5], np.eye(4) * 0.01, n // 5)
    rows = spark.createDataFrame([("c", *map(float, x)) for x in np.vstack([good, bad])], "cell string, " + ", ".join(f"{k} double" for k in names))
    m = quality_rules.robust_models(rows).first()
    assert np.abs(np.array([m[f"m{k}"] for k in range(4)]) - good.mean(0)).max() < 0.15
    assert abs(quality_rules.chi2_quantile(0.95, 1) - 3.841459) < 1e-5 and abs(quality_rules.chi2_quantile(0.975, 4) - 11.143287) < 1e-5


def test_clean_documents_stay(documents, spark, folder):
    labels = spark.read.parquet(f"{folder}/labels.parquet").where("quality = 1")
    rows = quality_rules.judge(documents).join(labels, "doc_id").where("not base_failed").collect()
    assert sum(r.kept for r in rows) >= 0.95 * len(rows)


# -- mixing ---------------------------------------------------------------
def test_mix_meets_its_targets(documents):
    rows = mixing.mix_documents(documents).join(documents.select("doc_id", "source"), "doc_id").collect()
    for source in {r.source for r in rows}:
        mine = [r for r in rows if r.source == source]
        taken, target, most = sum(r.taken for r in mine), mine[0].target, max(r.size for r in mine)
        assert abs(taken - target) <= most and all(r.taken <= 2 * r.size for r in mine)
        assert target <= 2 * mine[0].source_size + 1e-6
    assert abs(sum({r.source: r.target for r in rows}.values()) - 1.5 * sum(r.size for r in rows)) < 1e-6 * sum(r.size for r in rows)


def test_water_level_equals_repeated_resharing(spark):
    sizes = {"0a": 10, "0b": 500, "0c": 3, "0d": 900, "1": 40}
    weights = dict(zip(sorted(sizes), [5, 2, 1, 5, 2], strict=True))
    left, capped, total = dict(sizes), {}, 1.5 * sum(sizes.values())
    while True:
        rest = total - sum(capped.values())
        open_ = {s: rest * weights[s] / sum(weights[t] for t in left) for s in left}
        over = [s for s in left if open_[s] > 2 * sizes[s]]
        if not over:
            break
        for s in over:
            capped[s] = 2.0 * sizes[s]
            del left[s]
    want = capped | open_
    got = {r.source_key: r.target for r in mixing.source_targets(spark.createDataFrame(list(sizes.items()), "source_key string, source_size long")).collect()}
    assert all(abs(got[s] - want[s]) < 1e-6 for s in want)


def test_applied_mix_repeats_rows(documents):
    counts = {(r.doc_id): r["count"] for r in mixing.apply_mix(documents).groupBy("doc_id").count().collect()}
    for r in mixing.mix_documents(documents).where("size > 0").collect():
        assert counts.get(r.doc_id, 0) * r.size == r.taken


# -- classifier -----------------------------------------------------------
def test_ordinal_fit_recovers_order():
    r = np.random.default_rng(0)
    rows, grades = [], []
    for _ in range(900):
        g = int(r.integers(3))
        rows.append(np.array([10 + g, 50, *r.integers(1000, 4000, 5)], np.int32))
        grades.append(g)
    m = quality_classifier.fit_ordinal(np.concatenate(rows), np.array([len(x) for x in rows]), np.array(grades), 3, bits=13)
    assert (np.diff(m.thresholds) > 0).all()
    w = m.dense()
    assert w[10] < w[11] < w[12]
    tails = m.tails(np.array([w[10], w[11], w[12]], float))
    assert (np.diff(tails, axis=1) <= 0).all() and tails[2, 1] > 0.6 and tails[0, 0] < 0.4


def test_toxic_rows_are_rejected_and_clean_ones_kept(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    rows = quality_classifier.score(docs.join(labels.select("doc_id"), "doc_id", "left_semi"), quality_classifier.fit(docs, labels)).join(labels, "doc_id").collect()
    toxic, clean = [r for r in rows if r.toxic], [r for r in rows if not r.toxic and r.quality]
    assert sum(r.kept for r in toxic) <= 0.06 * len(toxic)
    assert sum(r.kept for r in clean) >= 0.98 * len(clean)


# -- vectors --------------------------------------------------------------
def test_search_equals_brute_force_with_ties(spark):
    r = np.random.default_rng(5)
    base = r.standard_normal((300, 16)).astype(np.float32)
    base[100:200] = base[100]  # a very common vector
    rows = [(k, base[k].tolist()) for k in range(300)]
    rows += [(900, None), (901, []), (902, [0.0] * 16), (903, [float("nan")] * 16), (904, [1.0, None] + [0.0] * 14), (None, [1.0] * 16), (905, [1.0, 2.0]), (950, [2.0, 4.0]), (5, base[5].tolist()), (7, base[8].tolist())]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(5)
    got = {(x.query_id, x["rank"]): (x.vec_id, x.score) for x in vector_join.nearest(frame, F.col("vec_id") % 50 == 0, query_block=3).collect()}
    vec = {}
    for k, v in rows:
        if k is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v):
            vec.setdefault(k, []).append(np.array(v, np.float64))
    for q in [k for k in vec if k % 50 == 0]:
        a = min(vec[q], key=lambda v: v.tolist())
        scored = sorted((-max(float(vector_join.running_dot(a[None], b[None])[0] / (np.sqrt(vector_join.running_dot(a[None], a[None])[0]) * np.sqrt(vector_join.running_dot(b[None], b[None])[0]))) for b in bs if len(b) == len(a)), k) for k, bs in vec.items() if k != q and any(len(b) == len(a) for b in bs))[:5]
        for rank, (s, k) in enumerate(scored, 1):
            assert got[(q, rank)] == (k, -s)
    assert vector_join.nearest(frame.limit(0), F.col("vec_id") % 50 == 0).count() == 0


def test_bounds_hold():
    r = np.random.default_rng(2)
    a, b = vector_join.Codes(r.standard_normal((40, 64))), vector_join.Codes(r.standard_normal((50, 64)))
    near, off = vector_join.tile_bounds(a, b)
    exact = (a.vectors / a.norms[:, None]) @ (b.vectors / b.norms[:, None]).T
    assert (np.abs(near - exact) <= off).all()


# -- simhash --------------------------------------------------------------
def test_fingerprint_by_definition():
    text = "The quick  brown\tFOX jumps é over the lazy dog the quick brown fox"
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text))
    hashes = [xxhash.xxh64_intdigest(" ".join(words[i : i + 3]).encode(), 42) for i in range(len(words) - 2)]
    want = sum(1 << k for k in range(64) if sum(h >> k & 1 for h in hashes) * 2 > len(hashes))
    assert simhash.fingerprint(simhash.shingle_hashes(text.encode(), 3)) == want
    assert simhash.fingerprint(simhash.shingle_hashes(b"One two", 3)) == xxhash.xxh64_intdigest(b"one two", 42)
    assert simhash.fingerprint([]) == 0


def components(values, radius=2):
    n = len(values)
    root = list(range(n))

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(n):
        for j in range(i):
            if bin(int(values[i]) ^ int(values[j])).count("1") <= radius:
                a, b = top(i), top(j)
                root[max(a, b)] = min(a, b)
    return [top(i) for i in range(n)]


def test_links_connect_what_all_pairs_connect(spark):
    r = np.random.default_rng(7)
    values = [int(x) for x in r.integers(0, 2**63, 40)]
    for v in values[:25]:  # chains and stars of near fingerprints, in any bytes
        for _ in range(6):
            v ^= (1 << int(r.integers(64))) | (1 << int(r.integers(64)))
            values.append(v)
    values = list(dict.fromkeys(values))
    signed = [v - (1 << 64) if v >= 1 << 63 else v for v in values]
    links = simhash.fingerprint_links(spark.createDataFrame([(v,) for v in signed], "fp long"))
    from fedlake.llm.components import connected_components

    got = {x.u: x.root for x in connected_components(links).collect()}
    want = components(values)
    groups = {}
    for v, c in zip(signed, want, strict=True):
        groups.setdefault(c, set()).add(got.get(v, v))
    assert all(len(g) == 1 for g in groups.values()) and len({min(g) for g in groups.values()}) == len(groups)


def test_long_lists_equal_short_ones():
    r = np.random.default_rng(1)
    values = np.unique(r.integers(0, 2**16, 900).astype(np.uint64))
    assert len(values) > simhash.DENSE_LIST
    pairs = simhash.list_links(values, 2, 6)
    root = list(range(len(values)))
    for a, b in pairs:
        assert np.bitwise_count(values[a] ^ values[b]) <= 2
    import itertools

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        x, y = top(a), top(b)
        assert x != y
        root[max(x, y)] = min(x, y)
    assert len({top(i) for i in range(len(values))}) == len(set(components(values)))
    del itertools


def test_groups_of_documents(documents, awkward):
    for d in (documents, awkward):
        rows = simhash.near_groups(d).collect()
        comp = components([int(r.fingerprint, 16) for r in rows])
        first = {}
        for r, c in zip(rows, comp, strict=True):
            first[c] = min(x for x in (first.get(c), r.doc_id) if x is not None) if r.doc_id is not None or c in first else None
        assert all(r.component_id == first[c] for r, c in zip(rows, comp, strict=True))


# -- chats ----------------------------------------------------------------
CHAT = "conv_id long, turn long, role string, text string"


def test_chats_read_back(spark):
    texts = [chat_format.PROBE, "<\\|x", "<\\\\|", "a\n\nb\\", None, "", "<|" * 5, "\\<|", "日本 <|im_start|>user\n"]
    rows = [(k, 0, "user", t) for k, t in enumerate(texts)] + [(k, 1, "assistant", t) for k, t in enumerate(texts)] + [(None, 0, None, "x"), (77, 1, "odd\nrole\\n<|", "y")]
    frame = spark.createDataFrame(rows, CHAT)
    formatted = chat_format.format_chats(frame)
    back = {r.conv_id: [(x.role, x.text) for x in r.b] for r in formatted.select("conv_id", chat_format.read_back(F.col("formatted")).alias("b")).collect()}
    for k, t in enumerate(texts):
        assert back[k] == [("user", t or ""), ("assistant", t or "")]
    assert back[None] == [("", "x")] and back[77] == [("odd\nrole\\n<|", "y")]
    got = {r.conv_id: r for r in chat_format.chat_digests(frame).collect()}
    for k, t in enumerate(texts):
        t = t or ""
        assert got[k].turns_sha256 == hashlib.sha256(f"user\n{t}\nassistant\n{t}\n".encode()).hexdigest()
        assert got[k].loss_sha256 == hashlib.sha256(t.encode()).hexdigest() and got[k].loss_chars == len(t) and got[k].valid
    assert not got[77].valid and chat_format.chat_digests(frame.limit(0)).count() == 0


def test_machine_orders(spark):
    cases = {"user,assistant": True, "system,user,assistant": True, "assistant": False, "user,user": False, "user,assistant,user": False, "user,tool,assistant": True, "user,assistant,system": False}
    rows = [(k, j, role, "t") for k, order in enumerate(cases) for j, role in enumerate(order.split(","))]
    got = {r.conv_id: r.valid for r in chat_format.format_chats(spark.createDataFrame(rows, CHAT)).collect()}
    assert got == dict(enumerate(cases.values()))


# -- licences and scores --------------------------------------------------
def test_license_wordings():
    scanner = license_scan.Scanner()
    for name, text in license_scan.TEMPLATES:
        found = scanner.match("Some first line.\n" + text + "\nand a last one")
        assert name in {f[0] for f in found} and any(f[2].verdict == "exact" for f in found)
    modified = scanner.match("Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction, including the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.")
    assert modified[0][0] == "MIT" and modified[0][2].verdict == "modified" and modified[0][2].missing > 0
    assert scanner.match("we got a license to drive and a permission slip") == []


def test_license_blocks(spark, awkward):
    rows = [r for r in license_scan.scan_blocks(awkward).collect() if r.license]
    assert [(r.doc_id, r.license, r.verdict) for r in rows] == [(10, "MIT", "exact")]


def test_window_net_gradient_and_normalisation():
    r = np.random.default_rng(0)
    net = lm_scoring.WindowNet.start(r.integers(0, 100, lm_scoring.TOKENS).astype(float))
    net = lm_scoring.WindowNet({k: v.astype(np.float64) for k, v in net.parts.items()})
    context, target = r.integers(0, lm_scoring.TOKENS + 1, (50, 2 * lm_scoring.WINDOW)), r.integers(0, lm_scoring.TOKENS, 50)
    for k, g in net.gradients(context, target).items():
        at = np.unravel_index(np.abs(g).argmax(), g.shape)
        held = net.parts[k][at]
        net.parts[k][at] = held + 1e-5
        up = -net.log_probs(context, target).mean()
        net.parts[k][at] = held - 1e-5
        down = -net.log_probs(context, target).mean()
        net.parts[k][at] = held
        assert abs((up - down) / 2e-5 - g[at]) < 1e-6
    whole = np.exp(net.log_probs(np.repeat(context[:1], lm_scoring.TOKENS, 0), np.arange(lm_scoring.TOKENS))).sum()
    assert abs(whole - 1) < 1e-9


def test_training_raises_the_likelihood(documents):
    named, frequency = lm_scoring.corpus_tokens(documents)
    counts = Counter(w for r in documents.select("text").collect() for w in r.text.encode().split())
    assert [counts[w] for w in named] == sorted(counts.values(), reverse=True)[: len(named)]
    assert frequency.sum() == sum(counts.values())
    start = lm_scoring.WindowNet.start(frequency)
    per_token = lambda net: lm_scoring.score(documents, named, net).agg((F.sum("pseudo_loglik") / F.sum("n_tokens")).alias("x")).first().x
    assert per_token(lm_scoring.train_round(documents, named, start, 0, 2)) > per_token(start)
    assert lm_scoring.score(documents, named, start).agg(F.sum("n_tokens")).first()[0] == sum(counts.values())
