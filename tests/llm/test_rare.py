"""Words of less than a millionth of a class's counts still tell the classes apart."""

import numpy as np
import pyarrow as pa

from skewjoin.llm import toxicity, wordhash


def test_rare_words_are_not_left_out(spark):
    """A word of nine toxic texts, and its bigram with a common one, among 20 and 10 million other counts."""
    rng = np.random.default_rng(2)
    words = np.array([a + b + c for a in "abcdefghij" for b in "klmnopqr" for c in "stuvwxyz"])
    rows = [("aaaa " + " ".join(rng.choice(words, 99, replace=False)), int(i % 3 == 0), 1000 * toxicity.UNIT, i % 5 == 0) for i in range(300)]
    rows += [("aaaa zzvile", 1, toxicity.UNIT, i % 3 == 0) for i in range(9)]
    w, n, _, total, pairs, b = toxicity.counted(spark.createDataFrame(rows, "text string, y int, weight long, held boolean").repartition(4))
    assert (total @ toxicity._ALL).min() > 9e6
    common, rare = toxicity._tokens(*wordhash.buffers(pa.array(["aaaa zzvile"])))[0]
    at = np.flatnonzero(w == rare)
    assert len(at) == 1 and (n[at[0]] @ toxicity._ALL).tolist() == [0, 9]
    at = np.flatnonzero((pairs[0] == common) & (pairs[1] == rare))
    assert len(at) == 1 and (b[at[0]] @ toxicity._ALL).tolist() == [0, 9]
