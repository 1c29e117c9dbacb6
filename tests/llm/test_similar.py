"""Pairs by shared shingles against brute force."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from ranksort.llm import similar


def brute(texts, share):
    sets = [set(similar.shingle_set(t.encode(), 3).tolist()) for t in texts]
    part, whole = share
    return {(i, j) for i in range(len(sets)) for j in range(i + 1, len(sets)) if sets[i] and sets[j] and len(sets[i] & sets[j]) * whole >= len(sets[i] | sets[j]) * part}


@pytest.mark.parametrize("share,words", [((4, 5), 40), ((1, 2), 4), ((1, 1), 3)])
def test_links_against_brute_force(spark, share, words):
    """Few words, so that shingles are frequent; texts of all lengths; repeated rows."""
    rng, texts = random.Random(words), ["", "a", "a b", "A b", "a b c"]
    for _ in range(60):
        text = [f"w{rng.randrange(words)}" for _ in range(rng.choice([3, 8, 20, 60]))]
        texts += [" ".join(text), " ".join(text[:-1]), " ".join(w if rng.random() > 0.03 else "x" for w in text)]
    texts = list(dict.fromkeys(texts))
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] * 2, "unit long, text string")
    roots = df.select("unit", F.col("unit").alias("node"), F.col("unit").alias("root")).distinct()
    found = {(min(r.a, r.b), max(r.a, r.b)) for r in similar.links(df, roots, share=share, shingle=3).collect()}
    assert found == brute(texts, share) and found
    one = roots.withColumn("root", F.lit(7).cast("long"))
    assert similar.links(df, one, share=share, shingle=3).count() == 0


def test_meetings_of_a_large_group():
    """A token that all have: no pair whose sizes fit is left out."""
    n = 400
    size, unit = np.arange(n) // 4 + 1, np.arange(n)
    zero = np.zeros(n, np.int64)
    found = {tuple(p[:2]) for some in similar.meetings(zero, size, zero, unit, unit, (4, 5)) for p in some.tolist()}
    assert found == {(i, j) for i in range(n) for j in range(i + 1, n) if size[j] * 4 <= size[i] * 5}
