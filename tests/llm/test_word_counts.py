import numpy as np
import pytest

from purchase_planner.llm import _text as tx
from purchase_planner.llm import masked_lm


def test_rare_words_keep_their_counts(spark, monkeypatch):
    """Words outside the vocabulary that share an entry are told apart by their counts; probabilities sum to one."""
    monkeypatch.setattr(masked_lm, "VOCABULARY", 2)
    times = {f"w{i}": 1 + i % 5 for i in range(600)}
    docs = spark.createDataFrame([(i, " ".join([w] * c)) for i, (w, c) in enumerate(times.items())], "doc_id long, text string")
    counts = masked_lm.settle(masked_lm.word_counts(docs))
    lex = masked_lm.lexicon(counts)
    rows = [*enumerate([*times, "never"]), (601, None), (0, "w0")]
    scored = masked_lm.score(spark.createDataFrame(rows, "doc_id long, text string"), lex, masked_lm.start(), counts=counts).collect()
    got = {r["doc_id"]: r["mean"] for r in scored}
    data = np.frombuffer(" ".join(times).encode(), np.uint8)
    starts, ends, _ = tx.words(data, np.array([0, len(data)]))
    rest: dict[int, list] = {}
    for i, (e, c) in enumerate(zip(lex.encode(tx.span_hashes(data, starts, ends)).tolist(), times.values(), strict=True)):
        rest.setdefault(e, []).append(got[i] - np.log(c))
    assert max(len(x) for x in rest.values()) > 1 and all(np.ptp(x) < 1e-4 for x in rest.values())
    assert sum(np.exp(got[i]) for i in range(len(times))) == pytest.approx(1, abs=1e-3)
    assert got[601] is None and len(scored) == len(rows)
