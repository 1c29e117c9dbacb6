"""SimHash near-duplicates by a self-join of binary tries.

The distinct fingerprints are dealt into ``budget + 1`` blocks of bits: two that differ in at most
``budget`` bits agree on one block whole, so every pair meets in the group of some block's value.
A group is a binary trie in sorted order: a node is a range of the sorted array and its children are
split by the next bit's prefix count.  The self-join walks pairs of nodes down together, adds one to
their error when they take different bits and drops a pair beyond the budget; all pairs of a level, of
all groups of a task, are worked on at once.

One word of 64 bits tells a similarity of 0.8 from less only coarsely: such texts differ in 9.7 bits of
5-word shingles on average, and blocks of so large a budget would be too short.  ``lanes`` makes a
fingerprint of that many words, dealt into blocks of ``width`` bits; links are again what differs in at
most ``budget`` bits of all lanes, among pairs that agree on a block.  A pair that differs in a share p of
its bits agrees on one of b blocks with probability 1 - (1 - (1 - p)^width)^b, which is 0.98 for a
similarity of 0.85 at 8 lanes and 16 bits.  Groups hold n / 2^width fingerprints on average: beyond some
10^9 documents take wider blocks and more lanes.

A group of very many fingerprints is dealt again by parts of its other bits (with lanes: by its other
blocks), of which a link leaves one whole too, so no task gets a hot group alone.  A task keeps of its
links a spanning forest, found chunk by chunk, which connects the same fingerprints, and the components
of all forests are found by alternating star contractions over tables in the shared folder.  Copies
share a fingerprint and are joined back at the end; they never pair up.

Defined results: words are runs without ASCII blanks; a text with fewer words than a shingle is one
shingle, one without words (or null) has the fingerprint zero, which links like any other; repeated
rows are in the same component; a null id can be no component's name unless all are null; no rows give
no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import similar
from .storage import materialize, release
from .words import lower, pieces

BITS = 64
#: Node pairs that are walked down at once, more are cut in two and walked one part after the other; and node pairs
#: that are compared leaf by leaf at once.
_FRONTIER, _COMPARED = 1 << 17, 1 << 14
#: Keys of hot groups that are broadcast; more are shuffled.
_HOT_BROADCAST = 100_000
#: Parts that a hub's neighbours are dealt over.
_SALTS = 16
#: A node pair with at most so many leaf pairs is compared leaf by leaf.
_LEAVES = 16
#: Copies of a fingerprint from which on its component is sent to where its documents are.
_MANY_COPIES = 10_000
#: Rows that a task joins at once, and more where a group has more.
_TOGETHER = 100_000


_STEP, _MIX1, _MIX2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def _lanes(hashes: np.ndarray, lanes: int) -> np.ndarray:
    """A row a hash: the hash itself, and for each further lane another number that it gives."""
    out = hashes[:, None] + np.arange(lanes, dtype=np.uint64) * _STEP
    if lanes > 1:
        rest = out[:, 1:]
        rest = (rest ^ (rest >> np.uint64(30))) * _MIX1
        rest = (rest ^ (rest >> np.uint64(27))) * _MIX2
        out[:, 1:] = rest ^ (rest >> np.uint64(31))
    return out


def shingle_hashes(text: bytes, shingle: int = 3, seed: int = 42) -> np.ndarray:
    """XXH64 of each of a text's shingles, repeats included."""
    from xxhash import xxh64_intdigest

    words = lower(text).split()
    if not words:
        return np.empty(0, np.uint64)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    width = min(shingle, len(words))
    stops = ends[width - 1 :].tolist()
    begins = [0, *(ends[: len(words) - width] + 1).tolist()]
    view = memoryview(joined)
    return np.fromiter(map(xxh64_intdigest, map(view.__getitem__, map(slice, begins, stops)), repeat(seed)), np.uint64, len(stops))


def fingerprint(text: bytes, shingle: int = 3, seed: int = 42, lanes: int = 1) -> np.ndarray:
    """The SimHash of a text, a word a lane: each bit is set if it is in over half of the shingles' XXH64 values."""
    hashes = shingle_hashes(text, shingle, seed)
    if not len(hashes):
        return np.zeros(lanes, np.uint64)
    votes = np.zeros(BITS * lanes, np.int64)
    part = max(1, (1 << 16) // lanes)
    for at in range(0, len(hashes), part):
        votes += np.unpackbits(_lanes(hashes[at : at + part], lanes).astype(">u8").view(np.uint8), axis=1).sum(0, dtype=np.int64)
    return np.packbits(2 * votes > len(hashes)).view(">u8").astype(np.uint64)


def fingerprints(df: DataFrame, *, text: str = "text", result: str = "fingerprint", shingle: int = 3, seed: int = 42, lanes: int = 1) -> DataFrame:
    """Adds ``result``: the fingerprint's 64 bits as a signed long, or an array of ``lanes`` longs."""

    def each(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            found = [fingerprint(t, shingle, seed, lanes) for some in pieces(texts) for t in some]
            flat = pa.array(np.concatenate([np.empty(0, np.uint64), *found]).view(np.int64), pa.int64())
            yield flat if lanes == 1 else pa.ListArray.from_arrays(pa.array(np.arange(0, lanes * (len(texts) + 1), lanes), pa.int32()), flat)

    return df.withColumn(result, F.arrow_udf(each, "long" if lanes == 1 else "array<long>")(F.col(text)))


def _popcount(values: np.ndarray) -> np.ndarray:
    return np.bitwise_count(values).astype(np.int64)


def trie_pairs(values: np.ndarray, groups: np.ndarray, budget: int) -> Iterator[np.ndarray]:
    """Index pairs (i < j) of one group whose values differ in at most ``budget`` bits, chunk by chunk.

    values: uint64, a row a fingerprint and a column a lane, sorted and distinct within each group;
    groups: where each group starts, and the end of the last.
    """
    begin, end = groups[:-1], groups[1:]
    big = end - begin > 1
    zero = np.zeros(int(big.sum()), np.int64)
    lanes = values.shape[1]
    stack = [(lanes * BITS - 1, np.stack([begin[big], end[big], begin[big], end[big], zero], 1))]
    ones: dict[int, np.ndarray] = {}

    def count(bit: int) -> np.ndarray:
        if bit not in ones:
            ones.clear() if len(ones) > 4 else None
            lane = values[:, lanes - 1 - bit // BITS]
            ones[bit] = np.concatenate(([0], np.cumsum((lane >> np.uint64(bit % BITS)) & np.uint64(1), dtype=np.int64)))
        return ones[bit]

    while stack:
        bit, pairs = stack.pop()
        if not len(pairs):
            continue
        if len(pairs) > _FRONTIER:
            stack += [(bit, pairs[len(pairs) // 2 :]), (bit, pairs[: len(pairs) // 2])]
            continue
        small = ((pairs[:, 1] - pairs[:, 0]) * (pairs[:, 3] - pairs[:, 2]) <= _LEAVES) | (bit < 0)
        if small.any():
            yield from _compare(values, pairs[small], budget)
            pairs = pairs[~small]
        if not len(pairs):
            continue
        before = count(bit)
        a, b, c, d, error = pairs.T
        middle = b - (before[b] - before[a])
        other = d - (before[d] - before[c])
        own = a == c
        after = [
            np.stack([a, middle, c, other, error], 1),
            np.stack([middle, b, other, d, error], 1),
            np.stack([a, middle, other, d, error + 1], 1),
            np.stack([middle, b, c, other, error + 1], 1)[~own],
        ]
        joined = np.concatenate(after)
        stack.append((bit - 1, joined[(joined[:, 4] <= budget) & (joined[:, 1] > joined[:, 0]) & (joined[:, 3] > joined[:, 2])]))


def _compare(values: np.ndarray, pairs: np.ndarray, budget: int) -> Iterator[np.ndarray]:
    """All leaf pairs of small node pairs, compared lane by lane."""
    for at in range(0, len(pairs), _COMPARED):
        a, b, c, d, _ = pairs[at : at + _COMPARED].T
        wide, high = d - c, (b - a) * (d - c)
        which = np.repeat(np.arange(len(a)), high)
        inner = np.arange(int(high.sum())) - np.repeat(np.cumsum(high) - high, high)
        i, j = a[which] + inner // wide[which], c[which] + inner % wide[which]
        near = np.flatnonzero(i < j)
        i, j, error = i[near], j[near], np.zeros(len(near), np.int64)
        for lane in range(values.shape[1]):
            error += _popcount(values[i, lane] ^ values[j, lane])
            near = np.flatnonzero(error <= budget)
            i, j, error = i[near], j[near], error[near]
        if len(i):
            yield np.stack([i, j], 1)


class Forest:
    """A spanning forest of links among n nodes, which come chunk by chunk."""

    def __init__(self, n: int):
        self.root = np.arange(n)
        self.kept = [np.empty((0, 2), np.int64)]

    def add(self, links: np.ndarray) -> None:
        while len(links):
            a, b = self.root[links[:, 0]], self.root[links[:, 1]]
            apart = a != b
            links, low, high = links[apart], np.minimum(a, b)[apart], np.maximum(a, b)[apart]
            if not len(links):
                return
            order = np.lexsort((low, high))  # of each higher root one link is kept, to the least that it meets
            first = order[np.flatnonzero(np.diff(high[order], prepend=-1))]
            self.kept.append(links[first])
            self.root[high[first]] = low[first]
            while True:
                further = self.root[self.root]
                if (further == self.root).all():
                    break
                self.root = further

    def links(self) -> np.ndarray:
        return np.concatenate(self.kept)


def block_bounds(budget: int) -> list[tuple[int, int]]:
    """First bit and width of each of the budget + 1 blocks."""
    cuts = [BITS * k // (budget + 1) for k in range(budget + 2)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:])]


def _bits(value: Column, first: int, width: int) -> Column:
    """``width`` bits from bit ``first`` on, wrapping around."""
    first %= BITS
    turned = value if not first else F.call_function("shiftrightunsigned", value, F.lit(first)).bitwiseOR(F.call_function("shiftleft", value, F.lit(BITS - first)))
    return turned.bitwiseAND(F.lit((1 << width) - 1 if width < BITS else -1).cast("long"))


def _dealt(distinct: DataFrame, budget: int, lanes: int, width: int, hot_group: int) -> DataFrame:
    """(block, own, part, rest, node, value): a row for each block of each fingerprint.

    Groups of over ``hot_group`` fingerprints are dealt again, one lane by the bits outside the block, in
    budget + 1 parts, on one of which two that link agree whole, several by the other blocks; the other
    groups have part -1.
    """
    lane = lambda k: F.get("value", F.lit(k))
    if lanes == 1:
        bounds = [(0, first, size) for first, size in block_bounds(budget)]
    else:
        bounds = [(k, first, width) for k in range(lanes) for first in range(0, BITS, width)]
    keyed = [F.struct(F.lit(k).alias("block"), _bits(lane(at), first, size).alias("own")) for k, (at, first, size) in enumerate(bounds)]
    rows = distinct.select(F.explode(F.array(*keyed)).alias("key"), "node", "value").select("key.block", "key.own", "node", "value")
    hot = rows.groupBy("block", "own").agg(F.count("*").alias("n")).where(F.col("n") > hot_group).drop("n")
    hot = materialize(hot, "simhash-hot")
    n_hot = hot.limit(_HOT_BROADCAST + 1).count()
    if not n_hot:
        return rows.select("block", "own", F.lit(-1).alias("part"), F.lit(0).cast("long").alias("rest"), "node", "value")
    if n_hot <= _HOT_BROADCAST:
        hot = F.broadcast(hot)
    marked = rows.join(hot.withColumn("hot", F.lit(True)), ["block", "own"], "left")
    split = F.lit(None).cast("array<struct<part:int,rest:bigint>>")
    for k, (at, first, size) in enumerate(bounds):
        if lanes == 1:
            left = BITS - size
            cuts = [left * i // (budget + 1) for i in range(budget + 2)]
            others = [_bits(lane(0), first + size + a, b - a) for a, b in zip(cuts, cuts[1:])]
        else:
            others = [_bits(lane(other), start, wide) for i, (other, start, wide) in enumerate(bounds) if i != k]
        split = F.when(F.col("block") == k, F.array(*(F.struct(F.lit(i).alias("part"), rest.alias("rest")) for i, rest in enumerate(others)))).otherwise(split)
    whole = F.array(F.struct(F.lit(-1).alias("part"), F.lit(0).cast("long").alias("rest")))
    each = F.explode(F.when(F.col("hot"), split).otherwise(whole)).alias("x")
    return marked.select("block", "own", each, "node", "value").select("block", "own", "x.part", "x.rest", "node", "value")


def links(distinct: DataFrame, *, fingerprint: str = "fingerprint", node: str | None = None, budget: int = 2, lanes: int = 1, width: int = 16, hot_group: int = 1_000_000) -> DataFrame:
    """(a, b): links among distinct fingerprints that differ in at most ``budget`` bits, a forest of each task's.

    a and b are values of ``node``, by default the fingerprint.
    """
    if not (0 <= budget < 16 if lanes == 1 else 0 <= budget < BITS * lanes // 2) or BITS % width:
        raise ValueError("the budget is from 0 to 15 bits, or to under half of all lanes' bits, and the width divides 64")
    keys = ["block", "own", "part", "rest"]
    value = F.array(F.col(fingerprint)) if lanes == 1 else F.col(fingerprint)
    named = distinct.select(F.col(node or fingerprint).alias("node"), value.alias("value"))
    sorted_groups = _dealt(named, budget, lanes, width, hot_group).repartition(*keys).sortWithinPartitions(*keys)

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def solve(table: pa.Table) -> pa.RecordBatch:
            block, own, part, rest, nodes = (table[c].to_numpy() for c in (*keys, "node"))
            values = table["value"].combine_chunks().flatten().to_numpy().view(np.uint64).reshape(-1, lanes)
            order = np.lexsort((*(values[:, k] for k in range(lanes - 1, -1, -1)), rest, part, own, block))
            values, nodes = values[order], nodes[order]
            edge = np.flatnonzero(np.logical_or.reduce([np.diff(x[order]) != 0 for x in (block, own, part, rest)])) + 1
            names, number = np.unique(nodes, return_inverse=True)
            found = Forest(len(names))
            for pairs in trie_pairs(values, np.concatenate(([0], edge, [len(values)])), budget):
                found.add(number[pairs])
            kept = names[found.links()]
            return pa.RecordBatch.from_arrays([pa.array(kept[:, 0]), pa.array(kept[:, 1])], ["a", "b"])

        rows, enough = 0, _TOGETHER
        for batch in batches:  # a group may run over into the next batch: the last one waits
            if not batch.num_rows:
                continue
            held.append(batch)
            rows += batch.num_rows
            if rows < enough:
                continue
            table = pa.Table.from_batches(held)
            other = np.flatnonzero(np.logical_or.reduce([(x := table[c].to_numpy()) != x[-1] for c in keys]))
            cut = int(other[-1]) + 1 if len(other) else 0
            if cut:
                yield solve(table.slice(0, cut))
            held, rows = table.slice(cut).combine_chunks().to_batches(), table.num_rows - cut
            enough = max(_TOGETHER, 2 * rows)
        if held:
            yield solve(pa.Table.from_batches(held))

    return sorted_groups.mapInArrow(join, "a long, b long")


def components(edges: DataFrame, rows: int | None = None) -> DataFrame:
    """(node, root): every node of the edges (a, b) with the smallest of its component.

    Rounds of large-star and small-star, until a round changes nothing; each is an aggregate and a join.
    A hub's neighbours are dealt over ``_SALTS`` copies of its row, so no task gets them all.  rows: about how
    many edges there are, where that is known.
    """
    both = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    now = materialize(both, "star", rows)
    state = _digest(now)
    while True:
        around = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = around.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = _with_least(around.where("v > u"), least).select(F.col("v").alias("u"), F.col("m").alias("v"))
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = _with_least(large, low).where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        last, now = now, materialize(small.distinct(), "star", state[0])
        release(last)
        after = _digest(now)
        if after == state:
            break
        state = after
    return now.select(F.col("u").alias("node"), F.col("v").alias("root"))


def _with_least(rows: DataFrame, least: DataFrame) -> DataFrame:
    """Rows (u, v) with the m of their u, by u and a part of v."""
    dealt = rows.withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(_SALTS)).cast("int"))
    copies = least.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(_SALTS - 1))))
    return dealt.join(copies, ["u", "salt"])


def _digest(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def near_duplicates(df: DataFrame, *, id: str = "doc_id", text: str = "text", budget: int = 2, shingle: int = 3, lanes: int = 1, width: int = 16, share: tuple[int, int] | None = None) -> DataFrame:
    """One row a document: id, fingerprint (signed long, or an array of them), component_id (the smallest id that links reach).

    With several lanes a fingerprint goes by its 64-bit hash where documents are joined to their components.
    share: (part, whole); all texts that agree in this share of their distinct shingles or more are linked too,
    whatever their fingerprints (``similar.links``), where fingerprints alone miss some of them.
    """
    unit = F.xxhash64(F.coalesce(F.col(text), F.lit("")))
    marked = fingerprints(df.select(F.col(id).alias("id"), F.col(text).alias("text"), unit.alias("unit")), shingle=shingle, lanes=lanes)
    marked = marked.select("id", "fingerprint", *(["unit"] if share else []))
    node = F.col("fingerprint") if lanes == 1 else F.xxhash64("fingerprint")
    marked = materialize(marked.withColumn("node", node), "simhash")
    print_ = F.first("fingerprint").alias("fingerprint")
    distinct = materialize(marked.groupBy("node").agg(F.min("id").alias("first"), print_, F.count("*").alias("copies")), "simhash-distinct")
    edges = materialize(links(distinct, node="node", budget=budget, lanes=lanes, width=width), "simhash-links")
    groups = components(edges, edges.count())
    if share:
        roots = marked.select("unit", "node").distinct().join(groups, "node", "left").select("unit", "node", F.coalesce("root", "node").alias("root"))
        roots = materialize(roots, "simhash-roots", marked.count())
        further = similar.links(df.select(unit.alias("unit"), F.col(text).alias("text")), roots, share=share, shingle=shingle)
        n_further = further.count()
        if n_further:
            groups = components(edges.unionByName(further), edges.count() + n_further)
        release(roots, further)
    rooted = distinct.select("node", "first", "copies").join(groups, "node", "left").withColumn("root", F.coalesce("root", "node"))
    least = rooted.groupBy("root").agg(F.min("first").alias("component_id"))
    named = materialize(rooted.join(least, "root").select("node", "component_id", "copies"), "simhash-named", distinct.count())
    release(distinct, edges)
    often = named.where(F.col("copies") > _MANY_COPIES).drop("copies")
    n_often = often.limit(_HOT_BROADCAST + 1).count()
    if 0 < n_often <= _HOT_BROADCAST:  # a fingerprint of many copies is no single task's
        here = marked.join(F.broadcast(often), "node", "left")
        found = here.where("component_id is not null").unionByName(here.where("component_id is null").drop("component_id").join(named.drop("copies"), "node").select(*here.columns))
    else:
        found = marked.join(named.drop("copies"), "node")
    return found.select(F.col("id").alias(id), "fingerprint", "component_id")
