"""Expected moves of the random field against all label sequences, and moves that the fit learns."""

from itertools import product

import numpy as np

from levelindex.llm.crf_toxicity import BLOCK, Chain, CrfSettings, fit


def test_expected_moves_against_all_sequences():
    draw = np.random.default_rng(3)
    move, start = np.exp(draw.normal(size=(2, 2))), np.array([0.7, 0.4])
    chain = Chain({}, 0.0, move, start, np.zeros(4))
    sizes = (1, 5, 3)
    scores = [draw.normal(size=n) for n in sizes]
    first = np.concatenate([[True] + [False] * (n - 1) for n in sizes])
    marginals, moves = chain.walk(np.concatenate(scores), first, moves=True)
    want, each = np.zeros((2, 2)), []
    for e in scores:
        total, pairs, ones = 0.0, np.zeros((2, 2)), np.zeros(len(e))
        for labels in product((0, 1), repeat=len(e)):
            weight = start[labels[0]] * np.prod([move[a, b] for a, b in zip(labels, labels[1:])]) * np.exp(np.dot(labels, e))
            total += weight
            ones += weight * np.array(labels)
            for a, b in zip(labels, labels[1:]):
                pairs[a, b] += weight
        want += pairs / total
        each.append(ones / total)
    assert np.allclose(moves, want) and np.allclose(marginals, np.concatenate(each))


def test_moves_over_block_ends_sum_to_words_inside_texts():
    n = 2 * BLOCK + 7
    first = np.zeros(n, bool)
    first[[0, 1, BLOCK, BLOCK + 50]] = True
    chain = Chain({}, 0.0, np.array([[0.9, 0.1], [0.4, 0.6]]), np.array([0.5, 0.5]), np.zeros(4))
    m, moves = chain.walk(np.linspace(-3, 3, n), first, moves=True)
    assert np.isclose(moves.sum(), n - first.sum())
    assert np.allclose(moves.sum(axis=0)[1], m[~first].sum())


def test_fit_changes_moves():
    draw = np.random.default_rng(4)
    text = lambda: " ".join(f"w{i}" for i in draw.integers(0, 5000, 30)).encode()  # noqa: E731  no copies of one another
    toxic = [text() + b" vile vile vile vile " + text() for _ in range(60)]
    clean = [text() + b" " + text() for _ in range(120)]
    model = fit(toxic + clean, [1] * 60 + [0] * 120, CrfSettings())
    assert model.move[1, 1] / model.move[1, 0] > model.move[0, 1] / model.move[0, 0]
    score = model.scores(model.evidence([text() + b" vile vile vile vile " + text(), text()])[0])
    assert score[0] > 0.7 > score[1]
