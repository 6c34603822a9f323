"""The training that a block of text gets."""

import numpy as np

from subweight.llm import lm


def test_steps_of_a_block():
    """A step for each 8,192 tokens or fewer: a block is not passed in a few large ones."""
    words = [b"w%d" % i for i in np.random.default_rng(5).integers(0, 500, 100_000)]
    tokens = lm.Tokens([b" ".join(words)])
    of = np.zeros((2, lm.CELLS), np.int64)
    of[0] = np.bincount(tokens.cells, minlength=lm.CELLS)
    trainer = lm.Trainer(lm.new_weights(of))
    seen = []
    trainer._step = lambda t, *rest: seen.append(t)
    trainer.learn(tokens)
    assert seen.count(0) == seen.count(1) >= len(tokens.cells) / 8192


def test_sums_of_short_and_long_segments():
    """Bit for bit what reduceat gives, for segments of any length."""
    rng = np.random.default_rng(21)
    size = np.concatenate([rng.integers(1, 12, 300), [200, 1, 9, 8]])
    first = np.cumsum(size) - size
    values = rng.normal(size=(int(size.sum()), 16)).astype(np.float32)
    assert np.array_equal(lm._sums(values, first), np.add.reduceat(values, first, axis=0))
    ones = values[:5]
    assert np.array_equal(lm._sums(ones, np.arange(5)), ones)
    assert lm.FEW >= 2
