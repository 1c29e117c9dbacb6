"""All pairs of texts that agree in a share of their shingles or more, without a loss.

A text is the set of its distinct shingles, by their 64-bit hashes.  Two sets that agree in the share have
``_MEETINGS`` common shingles among the first few of each in any one order of all shingles: of n shingles the
first n - ceil(share * n) + _MEETINGS are enough (of small sets fewer, see ``needed``).  These are shuffled by
shingle.  A meeting is dropped where the sizes, or what is left of both after it, cannot reach the share, and
a pair that meets less often than it must is dropped too.  What remains is compared set by set, so nothing
is found that is below the share either.

Any order gives the same pairs.  To keep the groups of a shingle small, shingles that are frequent in a
sixteenth of the texts come last; the others go by their hashes.  Pairs that are linked already are not
looked at again, so large groups of near copies that another method has found do not pair up.

Defined results: a text of fewer words than a shingle is one shingle; texts without words are in no pair.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import materialize, release
from .words import pieces

#: How often two texts must meet; more drop more pairs before sets are compared, and shuffle as many more shingles a text.
_MEETINGS = 6
#: Shingles that come last at most, and one of so many texts is looked at to find them.
_FREQUENT, _LOOKED_AT = 200_000, 16
#: Bytes of text whose shingles a task holds at once.
_PIECE = 1 << 20
#: Rows that a task joins at once, and more where a group has more; pairs that it returns at once.
_TOGETHER, _RETURNED = 200_000, 100_000
#: Units that are broadcast; more are shuffled.
_BROADCAST = 100_000


def shingle_set(text: bytes, shingle: int, seed: int = 42) -> np.ndarray:
    """The distinct XXH64 values of a text's shingles, ascending."""
    from .simhash import shingle_hashes

    return np.unique(shingle_hashes(text, shingle, seed))


def needed(size: np.ndarray, share: tuple[int, int]) -> np.ndarray:
    """How often the smaller of two texts, of so many shingles, must meet the other: at most as often as they have shingles in common."""
    part, whole = share
    return np.minimum(_MEETINGS, (part * size + whole - 1) // whole)


def _by_piece(df: DataFrame, schema: str, columns: Callable[[list[bytes]], dict[str, pa.Array]]) -> DataFrame:
    """(unit, ...): a batch of rows for each piece of texts, as sets take more room than their texts."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = 0
            for some in pieces(batch["text"], _PIECE):
                found = columns(some)
                yield pa.RecordBatch.from_arrays([batch["unit"].slice(at, len(some)), *found.values()], ["unit", *found])
                at += len(some)

    return df.select("unit", "text").mapInArrow(each, f"unit long, {schema}")


def _sets(df: DataFrame, shingle: int) -> DataFrame:
    """(unit, grams): all of each text's distinct shingles."""
    return _by_piece(df, "grams array<long>", lambda some: {"grams": _lists([shingle_set(t, shingle) for t in some])})


def _lists(found: list[np.ndarray]) -> pa.ListArray:
    ends = np.cumsum([0, *(len(x) for x in found)])
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate([np.empty(0, np.uint64), *found]).view(np.int64)))


def _firsts(df: DataFrame, shingle: int, share: tuple[int, int], frequent: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(unit, size, grams): how many shingles a text has, and the first of them that a pair must share one of."""
    sent, (part, whole) = df.sparkSession.sparkContext.broadcast(frequent), share

    def first(text: bytes) -> tuple[int, np.ndarray]:
        own, (known, counts) = shingle_set(text, shingle), sent.value
        if not len(own):
            return 0, own
        often = np.zeros(len(own), np.int64)
        if len(known):
            at = np.minimum(np.searchsorted(known, own), len(known) - 1)
            often = np.where(known[at] == own, counts[at], 0)
        enough = len(own) - (part * len(own) + whole - 1) // whole + int(needed(len(own), share))
        return len(own), own[np.argsort(often, kind="stable")[:enough]]

    def columns(some: list[bytes]) -> dict[str, pa.Array]:
        found = [first(t) for t in some]
        return {"size": pa.array([n for n, _ in found], pa.int32()), "grams": _lists([x for _, x in found])}

    return _by_piece(df, "size int, grams array<long>", columns)


def _frequent(df: DataFrame, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that several of some texts have, ascending, and how many; the order alone depends on them."""
    some = df.where(F.pmod("unit", F.lit(_LOOKED_AT)) == 0)  # with copies: texts need not be shuffled to put shingles in order
    counted = _sets(some, shingle).select(F.explode("grams").alias("gram")).groupBy("gram").agg(F.count("*").alias("n")).where("n > 1")
    found = counted.orderBy(F.desc("n"), "gram").limit(_FREQUENT).toArrow()
    grams = found["gram"].to_numpy().view(np.uint64)
    order = np.argsort(grams)
    return grams[order], found["n"].to_numpy()[order]


def meetings(token: np.ndarray, size: np.ndarray, place: np.ndarray, root: np.ndarray, unit: np.ndarray, share: tuple[int, int]) -> Iterator[np.ndarray]:
    """(a, b, need): units a < b of different roots that meet in a token and may reach the share, and how often they must.

    Found distance by distance in order of size.
    """
    part, whole = share
    order = np.lexsort((unit, size, token))
    token, size, place, root, unit = (x[order] for x in (token, size.astype(np.int64), place.astype(np.int64), root, unit))
    start = np.flatnonzero(np.concatenate(([True], token[1:] != token[:-1]))) if len(token) else np.empty(0, np.int64)
    if not len(start):
        return
    long = np.diff(np.append(start, len(token)))
    apart = np.repeat(np.minimum.reduceat(root, start) != np.maximum.reduceat(root, start), long)
    stop = np.repeat(np.append(start[1:], len(token)), long)
    i, step = np.flatnonzero(apart), 0
    while len(i):
        step += 1
        i = i[i + step < stop[i]]
        i = i[size[i + step] * part <= size[i] * whole]  # sizes ascend: a row that has no partner here has none further on
        j = i + step
        need = needed(size[i], share)
        left = np.minimum(size[i] - place[i], size[j] - place[j]) + need - 1  # this meeting may be the last that counts
        near = (root[i] != root[j]) & (left * (part + whole) >= part * (size[i] + size[j]))
        if near.any():
            a, b = unit[i[near]], unit[j[near]]
            yield np.stack([np.minimum(a, b), np.maximum(a, b), need[near]], 1)


def _candidates(rows: DataFrame, share: tuple[int, int]) -> DataFrame:
    """(a, b) of rows (token, size, place, root, unit): pairs that meet as often as they must."""
    names = ["token", "size", "place", "root", "unit"]

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def solve(table: pa.Table) -> Iterator[pa.RecordBatch]:
            held, n = [], 0
            for pairs in meetings(*(table[c].to_numpy() for c in names), share):
                held.append(pairs)
                n += len(pairs)
                if n >= _RETURNED:
                    yield _batch(held)
                    held, n = [], 0
            if n:
                yield _batch(held)

        held, rows, enough = [], 0, _TOGETHER
        for batch in batches:  # a group may run over into the next batch: the last one waits
            if not batch.num_rows:
                continue
            held.append(batch)
            rows += batch.num_rows
            if rows < enough:
                continue
            table = pa.Table.from_batches(held)
            token = table["token"].to_numpy()
            other = np.flatnonzero(token != token[-1])
            cut = int(other[-1]) + 1 if len(other) else 0
            yield from solve(table.slice(0, cut))
            held, rows = table.slice(cut).combine_chunks().to_batches(), table.num_rows - cut
            enough = max(_TOGETHER, 2 * rows)
        if held:
            yield from solve(pa.Table.from_batches(held))

    sorted_groups = rows.select(*names).repartition("token").sortWithinPartitions("token")
    met = sorted_groups.mapInArrow(join, "a long, b long, need long, n long").groupBy("a", "b").agg(F.sum("n").alias("n"), F.min("need").alias("need"))
    return met.where("n >= need").select("a", "b")


def _batch(held: list[np.ndarray]) -> pa.RecordBatch:
    pairs, n = np.unique(np.concatenate(held), axis=0, return_counts=True)
    return pa.RecordBatch.from_arrays([*map(pa.array, (pairs[:, 0], pairs[:, 1], pairs[:, 2], n))], ["a", "b", "need", "n"])


def links(texts: DataFrame, roots: DataFrame, *, share: tuple[int, int], shingle: int = 3) -> DataFrame:
    """(a, b): the nodes of every two texts of different roots that agree in ``share`` (part, whole) of their shingles or more.

    texts: (unit, text), in which equal texts have equal units and may repeat; roots: (unit, node, root), a
    row a unit.  The result is a table in the shared folder.
    """
    part, whole = share
    if not 0 < part <= whole:
        raise ValueError("the share is over 0 and at most 1")
    once = _firsts(texts, shingle, share, _frequent(texts, shingle)).where("size > 0").groupBy("unit").agg(F.first("size").alias("size"), F.first("grams").alias("grams"))
    rows = once.join(roots.select("unit", "root"), "unit").select("unit", "root", "size", F.posexplode("grams").alias("place", "token"))
    pairs = materialize(_candidates(rows, share), "similar-pairs")
    wanted = materialize(pairs.select("a").union(pairs.select("b")).distinct().withColumnRenamed("a", "unit"), "similar-units")
    few = wanted.limit(_BROADCAST + 1).count() <= _BROADCAST
    own = texts.join(F.broadcast(wanted) if few else wanted, "unit", "left_semi").dropDuplicates(["unit"])
    sets = materialize(_sets(own, shingle).join(roots.select("unit", "node"), "unit"), "similar-sets")
    a, b = (sets.select(F.col("unit").alias(k), F.col("node").alias(f"node_{k}"), F.col("grams").alias(f"grams_{k}")) for k in "ab")
    common = F.size(F.array_intersect("grams_a", "grams_b"))
    enough = common * (part + whole) >= (F.size("grams_a") + F.size("grams_b")) * part
    found = materialize(pairs.join(a, "a").join(b, "b").where(enough).select(F.col("node_a").alias("a"), F.col("node_b").alias("b")).distinct(), "similar-links")
    release(pairs, wanted, sets)
    return found
