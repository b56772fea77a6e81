"""What the driver holds while it fits a model."""

import tracemalloc

import numpy as np

from codedreg.llm import toxicity


def test_training_holds_no_copies_of_the_coordinates():
    draw = np.random.default_rng(1)
    texts, each, size = 3000, 5, 16
    symbols = draw.integers(1, 27, texts * each * size).astype(np.uint8)
    label = (np.arange(texts) % 3 == 0).astype(int)
    symbols.reshape(texts, each, size)[label == 1, 0, 4:12] = np.arange(1, 9)
    sample = toxicity.Sample(symbols, np.full(texts * each, size), np.repeat(np.arange(texts), each), label)
    tracemalloc.start()
    model = toxicity.train(sample, 0.3)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    margin = sample.margins(model.table) + model.offset
    best = margin.reshape(texts, each).max(1)
    assert best[label == 1].min() > best[label == 0].mean()
    assert peak < 80e6
