import numpy as np

from purchase_planner.llm import syncmers


def test_likeness_of_copies_with_inserted_sentences():
    """The estimate stays near the exact Jaccard similarity of the anchors when passages are inserted."""
    rng = np.random.default_rng(3)
    for length, inserts in ((300, 1), (2000, 1), (2000, 4)):
        words = [f"w{x}" for x in rng.integers(0, 5000, length)]
        near = list(words)
        for k in range(inserts, 0, -1):
            at = k * length // (inserts + 1)
            near[at:at] = [f"new{x}" for x in rng.integers(0, 5000, 10)]
        cps = [np.array([ord(c) for c in " ".join(w)], np.uint32) for w in (words, near)]
        one, two = (set(syncmers.anchors(x, 24, 10)[1].tolist()) for x in cps)
        sketches = [syncmers.sketch(x, np.array([0, len(x)]), 24, 10, 64)[0] for x in cps]
        exact = len(one & two) / len(one | two)
        assert abs(syncmers.likeness(*sketches, 64) - exact) < 0.15, (length, inserts)
