import tracemalloc

import numpy as np

from depmine.llm import bigru


def test_outputs_equal_states_and_hold_less():
    """The predicting pass gives what the training pass gives, within rounding, and keeps no states: half the memory of it."""
    net = bigru.Network(list("abcd"))
    rng = np.random.default_rng(3)
    text, filled = rng.integers(0, 256, (200, 500)).astype(np.uint8), rng.integers(1, 201, 500)
    peaks, found = [], []
    for mask in (None, (np.arange(200)[:, None] < filled).astype(np.float32)):
        for run in (lambda: net._pass(text, mask)[2], lambda: net.position_probabilities(text, mask)):
            tracemalloc.start()
            found.append(run())
            peaks.append(tracemalloc.get_traced_memory()[1])
            tracemalloc.stop()
        assert np.abs(found[-1] - found[-2]).max() < 1e-5
        assert peaks[-1] < 0.6 * peaks[-2]
