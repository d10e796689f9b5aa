"""Vectors of texts: grams counted in the tasks, as their md5 says."""

import hashlib

import numpy as np

from vecspark.sources import tables as T


def test_grams_of_any_letters(spark):
    texts = ["a", "ab", "abcabc", "äöü" * 3, "𝔘𝔫𝔦code 𝔘𝔫𝔦", "".join(map(chr, range(0x4E00, 0x4E00 + 600))), "x\0y\0z"]
    want = np.zeros((len(texts), 128), int)
    for i, t in enumerate(texts):
        for j in range(max(1, len(t) - 2)):
            want[i, int(hashlib.md5(t[j : j + 3].encode()).hexdigest()[:8], 16) % 128] += 1
    counter = T.Grams(128)
    for _ in range(2):
        assert (counter.count([[t] for t in texts]) == want).all()
    assert (counter.count([texts]) == want.sum(axis=0)).all()
    frame = spark.createDataFrame([(1, "abc"), (1, "abd"), (2, ""), (3, None)], "k long, t string")
    out = T.text_vectors(frame, ["k"], "t")
    assert "Generate" not in out._jdf.queryExecution().executedPlan().toString()
    assert [r["k"] for r in out.collect()] == [1]
