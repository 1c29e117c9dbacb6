import random
import re
from collections import Counter

import numpy as np

from ranksort.llm import quality

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute_longest(words):
    n, out = len(words), []
    for i in range(n):
        best = 0
        for j in range(n):
            k = 0
            while i != j and max(i, j) + k < n and words[i + k] == words[j + k]:
                k += 1
            best = max(best, k)
        out.append(best)
    return out


def longest_by_grams(words):
    """The same for longer texts: words by their k-grams, which are told apart further as long as some repeat."""
    n, out, k = len(words), [0] * len(words), 0
    classes, live = [0] * n, range(n)
    while True:
        seen = Counter((classes[i], words[i + k]) for i in live if i + k < n)
        live = [i for i in live if i + k < n and seen[classes[i], words[i + k]] > 1]
        if not live:
            return out
        number = {}
        fresh = {i: number.setdefault((classes[i], words[i + k]), len(number)) for i in live}
        for i, c in fresh.items():
            classes[i], out[i] = c, k + 1
        k += 1


def verdict(text, limits=quality.Limits()):
    """Kept or not, by base rule and both limits."""
    n, _, _, _, repeat = base(text)
    longest, covered = longest_by_grams(WORD.findall(text)), set()
    for i, k in enumerate(longest):
        if k >= limits.min_repeat:
            covered.update(range(i, i + k))
    return n >= 50 and 100 * repeat <= 50 * n and len(covered) <= limits.max_covered * n and max(longest, default=0) <= limits.max_longest


def base(text):
    words = WORD.findall(text)
    windows = Counter(zip(words, words[1:], words[2:]))
    repeat = {i + k for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for k in range(3)}
    lines = [x for x in text.split("\n") if WORD.search(x)]
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(repeat)


def test_suffix_array_against_brute_force():
    rng = random.Random(5)
    texts = [[rng.choice("abc") for _ in range(rng.randrange(30))] for _ in range(60)] + [[], ["a"] * 40, list("abcabcabc"), list("xyz") + list("abc")]
    starts = np.cumsum([0, *map(len, texts)])
    found = quality.longest_repeats(np.array([ord(w) for t in texts for w in t]), starts)
    assert found.tolist() == [x for t in texts for x in brute_longest(t)]


def test_counts_and_verdict(spark):
    rng = random.Random(6)
    alphabet = ["a", "b", "Ça", "#", "x|y", " ", "\x1c", "𝒳"]
    texts = ["".join(rng.choice(alphabet) + rng.choice([" ", "\n", "\t", "  "]) for _ in range(rng.randrange(90))) for _ in range(80)]
    fresh = " ".join(f"w{i}" for i in range(300))
    line = " ".join(f"r{i}" for i in range(40))
    texts += ["", "one", fresh, "\n".join([line] * 9), f"{line} {fresh} {line}", " ".join([fresh[:1400]] * 2 + [f"v{i}" for i in range(900)])]
    df = spark.createDataFrame([*enumerate(texts), (-1, None)], "doc_id long, text string").selectExpr("*", "7 as quality")
    rows = {r.doc_id: r for r in quality.assess(df).select("doc_id", "quality.*", quality.base_failed().alias("failed"), quality.kept().alias("kept")).collect()}
    for i, text in enumerate(texts):
        r = rows[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == base(text)
        assert r.failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words)
    n = len(texts)
    assert [rows[i].kept for i in range(n - 6, n)] == [False, False, True, False, True, False]
    assert rows[-1].n_words == 0 and not rows[-1].kept
    assert rows[n - 2].longest_repeat == 40 and rows[n - 2].covered_words == 80 and rows[n - 2].n_maximal_repeats == 2
    assert quality.assess(df.limit(0)).count() == 0


def test_a_very_long_text():
    text = (" ".join(f"p{i}" for i in range(500)) + " ").encode() * 40
    found = quality.measure([b"", text, b"a b c"], quality.Limits())
    assert found["covered_words"].tolist() == [0, 20_000, 0] and found["longest_repeat"][1] == 19_500


def test_one_very_long_text():
    """Memory is bounded by the words, not by how far they repeat."""
    import subprocess
    import sys
    from pathlib import Path

    code = """
import resource
from ranksort.llm import quality
found = quality.measure([b"word " * 2_000_000 + b" ".join(b"w%d" % (i % 1000) for i in range(2_000_000))], quality.Limits())
print({k: int(x[0]) for k, x in found.items()}, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss // 1024)
"""
    done = subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).resolve().parents[2], capture_output=True, text=True, timeout=200)
    counts, _, peak = done.stdout.strip().rpartition(" ")
    assert "'n_words': 4000000" in counts and "'covered_words': 4000000" in counts and "'longest_repeat': 1999999" in counts, done.stderr
    assert int(peak) < 700


def test_grams_and_brute_force_agree():
    rng = random.Random(11)
    for _ in range(60):
        words = [rng.choice("abc") for _ in range(rng.randrange(30))]
        assert longest_by_grams(words) == brute_longest(words)
