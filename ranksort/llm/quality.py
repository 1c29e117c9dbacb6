"""Quality rules: word and line counts, and repetition within a text by a suffix array over its words.

Texts of a batch share one suffix array whose first sort key is the text, so no repeat spans two.
Prefix doubling sorts only what is not yet unique.  The longest common prefix of neighbours is found
by halving steps on two polynomial hashes modulo 31-bit primes, so memory is some 60 bytes a word,
however long the repeats.  Neighbours in the array bound the LCP intervals: the deepest interval
around a suffix has the larger of its two neighbour LCPs, and a span that the one before it contains
is not left-maximal.  The spans' union is the covered part.

The method rejects a text if repeats of ``min_repeat`` words or more cover over ``max_covered`` of
its words, or if one repeat is longer than ``max_longest`` words.

Defined results: a null or empty text has no words and fails the base rule; repeated rows give
repeated rows; extra columns pass through, but for one with the result's name, which is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .words import joined, lines_of, pieces, sums, words_of

_SYMBOLS = b"#*$%&|<>"
#: Bytes of text that share a suffix array; a longer text has its own.
_PIECE = 2 << 20
_RESULT = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "covered_words", "longest_repeat", "n_maximal_repeats"]


@dataclass(frozen=True)
class Limits:
    """Thresholds of the method; the base rule's are fixed."""

    min_repeat: int = 10
    max_covered: float = 0.45
    max_longest: int = 200


def suffix_order(words: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """All suffixes of all texts in order, text by text; a suffix ends with its text."""
    n = len(words)
    place = np.int32 if n < 1 << 31 else np.int64
    lengths = np.diff(starts)
    stop = np.repeat(starts[1:].astype(place), lengths)
    key = np.repeat(np.arange(len(lengths)), lengths) * (int(words.max()) + 1) + words
    order = np.argsort(key, kind="stable").astype(place)
    key, slots, held = key[order], np.arange(n, dtype=place), order.copy()
    rank, step = np.empty(n, place), 1
    while True:
        fresh = np.empty(len(held), bool)
        fresh[0], fresh[1:] = True, key[1:] != key[:-1]
        del key
        group = np.flatnonzero(fresh).astype(place)
        member = np.cumsum(fresh, dtype=place) - 1
        rank[held] = slots[group][member]
        order[slots] = held
        shared = (np.diff(np.append(group, len(held))) > 1)[member]
        del fresh, group, member
        if not shared.any():
            return order
        slots, held = slots[shared], held[shared]
        ahead = held.astype(np.int64) + step
        after = np.where(ahead < stop[held], rank[np.minimum(ahead, n - 1)], -1)
        del ahead, shared
        key = rank[held].astype(np.int64) * (n + 1) + after + 1
        del after
        sort = np.argsort(key, kind="stable")
        key, held = key[sort], held[sort]
        del sort
        step *= 2


class _Hashes:
    """Polynomial hashes of all stretches of a sequence, modulo two primes."""

    primes = (2_147_483_647, 2_147_483_629)

    def __init__(self, words: np.ndarray, seed: int = 11):
        rng = np.random.default_rng(seed)
        n, self.powers, self.sums = len(words), [], []
        for prime in self.primes:
            power, base = np.ones(n + 1, np.uint64), int(rng.integers(1 << 20, prime))
            filled = 1
            while filled <= n:  # twice as many powers each time
                more = min(filled, n + 1 - filled)
                power[filled : filled + more] = power[:more] * np.uint64(pow(base, filled, prime)) % np.uint64(prime)
                filled += more
            values = rng.integers(1, prime, int(words.max()) + 1, dtype=np.uint64)
            total = np.zeros(n + 1, np.uint64)
            np.cumsum(power[:-1] * values[words] % np.uint64(prime), out=total[1:])
            self.powers.append(power.astype(np.uint32))
            self.sums.append((total % np.uint64(prime)).astype(np.uint32))

    def equal(self, low: np.ndarray, high: np.ndarray, length: np.ndarray) -> np.ndarray:
        """Whether stretches of a length from two places, low <= high, are equal."""
        same = np.ones(len(low), bool)
        for prime, power, sums_ in zip(self.primes, self.powers, self.sums):
            p = np.uint64(prime)
            first = (sums_[low + length].astype(np.uint64) + p - sums_[low]) % p * power[high - low] % p
            same &= first == (sums_[high + length].astype(np.uint64) + p - sums_[high]) % p
        return same


#: Neighbours whose common prefixes are searched at once.
_PAIRS = 1 << 20


def longest_repeats(words: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """For each word's suffix, the most words that it shares with another suffix of the same text."""
    n = len(words)
    longest = np.zeros(n, np.int32 if n < 1 << 31 else np.int64)
    if n < 2:
        return longest
    order, hashes = suffix_order(words, starts), _Hashes(words)
    text_of = np.repeat(np.arange(len(starts) - 1, dtype=np.int32), np.diff(starts))
    stops = starts[1:]
    for at in range(0, n - 1, _PAIRS):
        a, b = order[at : at + _PAIRS + 1][:-1].astype(np.int64), order[at + 1 : at + _PAIRS + 1].astype(np.int64)
        near = np.flatnonzero((words[a] == words[b]) & (text_of[a] == text_of[b]))
        a, b = a[near], b[near]
        if not len(a):
            continue
        low, high = np.minimum(a, b), np.maximum(a, b)
        room = stops[text_of[high]] - high
        common = np.zeros(len(a), np.int64)
        for level in range(int(room.max()).bit_length() - 1, -1, -1):
            longer = common + (1 << level)
            fits = np.flatnonzero(longer <= room)
            good = fits[hashes.equal(low[fits], high[fits], longer[fits])]
            common[good] = longer[good]
        # a place is in two pairs, the one before it and the one after
        longest[a] = np.maximum(longest[a], common)
        longest[b] = np.maximum(longest[b], common)
    return longest


def _covered(begin: np.ndarray, length: np.ndarray, n: int) -> np.ndarray:
    """Which of n words lie in one of the spans; each begins at another word."""
    edge = np.zeros(n + 1, np.int32)
    edge[begin] += 1
    np.subtract.at(edge, begin + length, 1)
    return np.cumsum(edge[:-1], dtype=np.int32) > 0


def measure(texts: list[bytes], limits: Limits) -> dict[str, np.ndarray]:
    """The counts of each text."""
    raw, begins = joined(texts)
    spans, first_byte = words_of(raw, begins)
    starts, n = spans.starts, len(spans.stops)
    edges = np.concatenate(([0], spans.stops))[starts]
    letters = [int(np.count_nonzero((spans.data[a:b] & 0xC0) != 0x80)) for a, b in zip(edges, edges[1:])]
    lines, first_of_line = lines_of(raw, begins)
    spoken = np.flatnonzero(np.diff(np.searchsorted(first_byte, np.append(first_of_line, len(raw)))))
    number = lines.numbers()[0][spoken].astype(np.int64)
    owner = np.searchsorted(lines.starts, spoken, "right") - 1
    distinct = np.unique(owner * (len(lines.stops) + 1) + number) // (len(lines.stops) + 1)
    repeated_lines = np.bincount(owner, minlength=len(texts)) - np.bincount(distinct, minlength=len(texts))
    del lines, first_of_line, spoken, number, owner, distinct, raw, first_byte
    words = spans.numbers()[0]
    del spans
    longest = longest_repeats(words, starts)
    three = np.flatnonzero(longest >= 3)
    long_enough = np.flatnonzero(longest >= limits.min_repeat)
    covered = _covered(long_enough, longest[long_enough], n)
    first = np.zeros(n, bool)
    first[starts[:-1][np.diff(starts) > 0]] = True
    before = np.concatenate((longest[:1] * 0, longest[:-1]))
    maximal = (longest >= limits.min_repeat) & (first | (before <= longest))
    top = np.zeros(len(texts), np.int64)
    full = np.flatnonzero(np.diff(starts) > 0)
    if len(full):
        top[full] = np.maximum.reduceat(longest, starts[:-1][full])
    return {
        "n_words": np.diff(starts),
        "word_chars": np.array(letters, np.int64),
        "n_symbols": np.array([len(t) - len(t.translate(None, _SYMBOLS)) for t in texts], np.int64),
        "n_dup_lines": repeated_lines,
        "n_repeat_words": sums(_covered(three, np.full(len(three), 3), n), starts),
        "covered_words": sums(covered, starts),
        "longest_repeat": top,
        "n_maximal_repeats": sums(maximal, starts),
    }


def assess(df: DataFrame, *, text: str = "text", result: str = "quality", limits: Limits = Limits()) -> DataFrame:
    """Adds ``result``, a struct of the counts."""

    def counts(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            found = [measure(part, limits) for part in pieces(texts, _PIECE)]
            columns = [np.concatenate([f[c] for f in found]) if found else np.empty(0, np.int64) for c in _RESULT]
            yield pa.StructArray.from_arrays([pa.array(c, pa.int64()) for c in columns], _RESULT)

    udf = F.arrow_udf(counts, ", ".join(f"{c} long" for c in _RESULT))
    return df.withColumn(result, udf(F.col(text)))


def base_failed(quality: str = "quality") -> Column:
    """The fixed rule: under 50 words, or over half of them in repeated 3-word windows."""
    words = F.col(f"{quality}.n_words")
    return (words < 50) | (100 * F.col(f"{quality}.n_repeat_words") > 50 * words)


def kept(quality: str = "quality", limits: Limits = Limits()) -> Column:
    """Passes the base rule and both limits of the method."""
    return ~base_failed(quality) & (F.col(f"{quality}.covered_words") <= limits.max_covered * F.col(f"{quality}.n_words")) & (F.col(f"{quality}.longest_repeat") <= limits.max_longest)
