"""Language scores of long and unlikely runs, against plain sums over all segmentations in exact arithmetic."""

from fractions import Fraction

import numpy as np

from fedlake.llm import language_id as L
from fedlake.llm import queries as Q


def model(scale, languages=2):
    pieces = L.letter_pieces(Q.vocabulary().pieces)
    prob = np.random.default_rng(4).random((len(pieces) + 1, languages)) * scale
    return pieces, L.LanguageModel(pieces, [f"l{k}" for k in range(languages)], prob)


def exact(word, pieces, prob, lang):
    """Sums for every boundary, as fractions."""
    sums = [Fraction(1)]
    for end in range(1, len(word) + 1):
        total = Fraction(0)
        for start in range(max(0, end - 20), end):
            piece = word[start:end]
            if piece in pieces:
                total += sums[start] * Fraction(prob[pieces[piece], lang])
            elif end - start == 1:
                total += sums[start] * Fraction(prob[-1, lang])
        sums.append(total)
    top = sums[-1]
    shift = top.numerator.bit_length() - top.denominator.bit_length()
    return float(np.log(float(top / Fraction(2) ** shift)) + shift * np.log(2))


def test_runs_longer_than_any_stretch_and_tiny_probabilities():
    for scale in (1e-2, 1e-12):
        pieces, m = model(scale)
        for word in (L.MARK + "donaudampfschifffahrtsgesellschaftskapitaensmuetzenabzeichenverordnung", L.MARK + "thequickbrownfoxjumps" * 12, L.MARK + "日本語の文" * 30):
            got = m.word_scores([word])[0]
            want = [exact(word, pieces, m.prob, k) for k in (0, 1)]
            assert np.allclose(got, want, rtol=1e-10)


def test_unlikely_letters_still_differ():
    pieces = {L.MARK: 0, "a": 1, "b": 2}
    prob = np.array([[0.5, 0.5], [5e-12, 1e-11], [0.4, 0.4], [1e-7, 1e-7]])
    got = L.LanguageModel(pieces, ["x", "y"], prob).word_scores([L.MARK + "a" * 400])[0]
    assert abs(got[1] - got[0] - 400 * np.log(2)) < 1e-6


def test_expected_uses_spell_long_words():
    pieces, m = model(1e-9, 1)
    word = L.MARK + "thequickbrownfox" * 40
    uses = L.PieceGrid(m.trie.grid([word])).expected(m.prob, np.array([3.0]))
    spelled = sum(uses[k] * len(p) for p, k in pieces.items()) + uses[-1]
    assert abs(spelled / (3 * len(word)) - 1) < 1e-9


def test_one_run_of_many_letters_is_scored_whole(spark):
    text = "zug" * 20_000
    docs = spark.createDataFrame([(1, "der zug und das haus zug", "de"), (2, "the train and the house", "en"), (3, text, "de"), (5, text, None)], "doc_id long, text string, lang string")
    got = {r.doc_id: r for r in L.train_and_predict(docs, Q.vocabulary().pieces).collect()}
    assert got[5].lang_pred == "de" and got[5].letter_runs == 1
