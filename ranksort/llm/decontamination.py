"""Benchmark decontamination by spaced seeds.

A seed is a fixed mask over token positions; the hash of a window takes only the positions marked 1,
so a substitution at a 0 leaves it alone.  Hashes of all windows of the texts are joined with those of
the benchmark's; each hit sets a diagonal (text position less item position) on which the tokens are
then compared one by one.  The best segment scores 1 a match and -3 a mismatch, so it has three
quarters equal at least; it is evidence if ``min_identity`` of it is equal and it has ``min_tokens``
equal tokens, or ``min_share`` of the item where the item is shorter than that.  An item with fewer
tokens than the shortest mask is its own seed, whole: it matches verbatim.

A benchmark of up to about ``block_tokens`` tokens is one sorted array that is sent to the workers, and
the texts are searched where they are.  A larger one is joined in a shuffle: a filter of bounded size
keeps the windows of the texts that may be seeds, their hashes and places meet the seeds', dealt by the
text so that a frequent seed is no single task's, and the diagonals meet the tokens of item and text.
Both ways give the same matches.

Defined results: tokens are runs of letters, digits and underscores, lower-cased; null texts and
items are empty; an item without tokens never matches; repeated items or rows give repeated matches; no
rows on either side give none; ties between segments go to the first; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import materialize, unused
from .words import pieces

#: The masks, weight six each.
MASKS = ("1110111", "110100111", "1011001011", "1100101011")
_TOKEN = re.compile(r"\w+")
_MATCH = "item long, matched long, segment long, item_tokens long, text_start long, item_start long"


@dataclass(frozen=True)
class Evidence:
    """When an aligned segment counts as an overlap."""

    min_tokens: int = 12
    min_identity: float = 0.8
    min_share: float = 0.8

    def holds(self, matched: int, segment: int, item_tokens: int) -> bool:
        return matched >= self.min_identity * segment and matched >= min(self.min_tokens, math.ceil(self.min_share * item_tokens))


def tokens(text: str) -> list[str]:
    return _TOKEN.findall(text.lower())


def best_segment(equal: np.ndarray) -> tuple[int, int]:
    """First and one past the last of the segment with the highest score."""
    gain = np.where(equal, 1, -3)
    total = np.concatenate(([0], np.cumsum(gain)))
    low = np.minimum.accumulate(total)[:-1]
    end = int(np.argmax(total[1:] - low)) + 1
    begin = int(np.flatnonzero(total[:end] == low[end - 1])[-1])
    return begin, end


def window_hashes(ids: np.ndarray, offsets: np.ndarray, places: np.ndarray) -> np.ndarray:
    """The hash of what a mask leaves of the windows at some places."""
    value = np.zeros(len(places), np.uint64)
    for at in offsets:
        value = (value ^ ids[places + at].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        value ^= value >> np.uint64(29)
    return value


class Seeds:
    """The masks as offsets, and after them for items too short for any, one of each length that is all ones."""

    def __init__(self, masks: tuple[str, ...] = MASKS):
        self.least = min(map(len, masks))
        self.offsets = [np.flatnonzero(np.frombuffer(m.encode(), np.uint8) == ord("1")) for m in masks]
        self.offsets += [np.arange(n) for n in range(1, self.least)]
        self.spans = [*map(len, masks), *range(1, self.least)]

    def of_item(self, ids: np.ndarray, k: int) -> np.ndarray:
        """The hashes of all windows of an item that the k-th mask is for."""
        own = (self.spans[k] == len(ids)) if len(ids) < self.least else (self.spans[k] >= self.least)
        windows = len(ids) - self.spans[k] + 1 if own else 0
        return window_hashes(ids, self.offsets[k], np.arange(max(0, windows)))


def verify(equal: np.ndarray, n_item: int, evidence: Evidence) -> tuple[int, int, int] | None:
    """Matched tokens, begin and end of the best segment, if it is evidence."""
    begin, end = best_segment(equal)
    matched = int(equal[begin:end].sum())
    return (matched, begin, end) if evidence.holds(matched, end - begin, n_item) else None


class SeedIndex:
    """The seed hashes of some items, sorted."""

    def __init__(self, items: list[tuple[int, list[str]]], masks: tuple[str, ...] = MASKS, evidence: Evidence = Evidence()):
        self.evidence, self.seeds = evidence, Seeds(masks)
        self.vocabulary: dict[str, int] = {}
        self.items = [(i, np.array([self.vocabulary.setdefault(t, len(self.vocabulary) + 1) for t in found], np.int64)) for i, found in items]
        self.hashes, self.where = [], []
        for k in range(len(self.seeds.spans)):
            each = [self.seeds.of_item(ids, k) for _, ids in self.items]
            hashes = np.concatenate([np.empty(0, np.uint64), *each])
            where = np.stack([np.repeat(np.arange(len(each)), [len(x) for x in each]), np.concatenate([np.empty(0, np.int64), *(np.arange(len(x)) for x in each)])], 1)
            order = np.argsort(hashes, kind="stable")
            self.hashes.append(hashes[order])
            self.where.append(where[order])

    def search(self, texts: list[list[str]]) -> list[list[tuple[int, int, int, int, int, int]]]:
        """Of each text, the evidence: (item, matched, segment, item tokens, text start, item start), best of each item."""
        starts = np.zeros(len(texts) + 1, np.int64)
        np.cumsum([len(t) for t in texts], out=starts[1:])
        ids = np.empty(starts[-1], np.int64)
        for found, at in zip(texts, starts):
            ids[at : at + len(found)] = np.fromiter(map(self.vocabulary.get, found, repeat(0)), np.int64, len(found))
        known, found = ids > 0, [np.empty((0, 3), np.int64)]
        for k, (offsets, span) in enumerate(zip(self.seeds.offsets, self.seeds.spans)):
            windows = len(ids) - span + 1
            if windows <= 0 or not len(self.hashes[k]):
                continue
            all_known = known[offsets[0] : offsets[0] + windows].copy()
            for at in offsets[1:]:
                all_known &= known[at : at + windows]
            places = np.flatnonzero(all_known)
            value = window_hashes(ids, offsets, places)
            left = np.searchsorted(self.hashes[k], value)
            hit = np.flatnonzero(self.hashes[k][np.minimum(left, len(self.hashes[k]) - 1)] == value)
            times = np.searchsorted(self.hashes[k], value[hit], "right") - left[hit]
            inner = np.arange(int(times.sum())) - np.repeat(np.cumsum(times) - times, times)
            seeds = self.where[k][np.repeat(left[hit], times) + inner]
            place = np.repeat(places[hit], times)
            found.append(np.unique(np.stack([np.searchsorted(starts, place, "right") - 1, seeds[:, 0], place - seeds[:, 1]], 1), axis=0))
        diagonals = np.unique(np.concatenate(found), axis=0)
        best: list[dict[int, tuple]] = [{} for _ in texts]
        for text, number, shift in diagonals.tolist():
            item, own = self.items[number]
            a, b = max(shift, int(starts[text])), min(shift + len(own), int(starts[text + 1]))
            if b <= a:
                continue
            good = verify(ids[a:b] == own[a - shift : b - shift], len(own), self.evidence)
            if good and good[0] > best[text].get(number, (0, 0))[1]:
                matched, begin, end = good
                best[text][number] = (item, matched, end - begin, len(own), a + begin - int(starts[text]), a + begin - shift)
        return [list(found.values()) for found in best]


def _searcher(index: Broadcast):
    """The search as a column function."""
    names = [c.split()[0] for c in _MATCH.split(", ")]

    def search(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        kind = pa.list_(pa.struct([(c, pa.int64()) for c in names]))
        for texts in batches:
            rows = []
            for some in pieces(texts):
                rows += index.value.search([tokens(t.decode("utf-8", "replace")) for t in some])
            yield pa.array([[dict(zip(names, m)) for m in r] for r in rows], kind)

    return F.arrow_udf(search, f"array<struct<{_MATCH.replace(' long', ':long')}>>")


def find_overlaps(
    df: DataFrame, benchmark: DataFrame, *, text: str = "text", item_id: str = "item_id", item_text: str = "text",
    result: str = "overlaps", masks: tuple[str, ...] = MASKS, evidence: Evidence = Evidence(), block_tokens: int = 1_000_000,
) -> DataFrame:
    """Adds ``result``: an array of (item, matched, segment, item_tokens, text_start, item_start), empty for a clean text."""
    items = benchmark.select(F.col(item_id).cast("long").alias("item"), F.coalesce(F.col(item_text), F.lit("")).alias("said"))
    letters = items.agg(F.sum(F.length("said"))).first()[0] or 0
    if letters / 2 > block_tokens:  # a token has a character and a gap at least
        return _by_join(df, items, text, result, masks, evidence)
    part = items.orderBy("item", "said").collect()  # within the bound
    index = df.sparkSession.sparkContext.broadcast(SeedIndex([(r["item"], tokens(r["said"])) for r in part], masks, evidence))
    return df.withColumn(result, _searcher(index)(F.col(text)))


# --- a benchmark of any size ---

#: Bits of the filter a seed, at most so many in all, and probes of each.
_BITS_A_SEED, _MOST_BITS, _PROBES = 32, 1 << 30, 4
#: Copies of the benchmark's side that hot keys are dealt over; and rows of matched texts that are broadcast.
_SALTS, _BROADCAST = 8, 1_000_000


def token_hashes(text: str) -> np.ndarray:
    from xxhash import xxh64_intdigest

    return np.fromiter((xxh64_intdigest(t.encode()) for t in tokens(text)), np.uint64)


def _probes(hashes: np.ndarray, bits: int) -> list[np.ndarray]:
    first, second = hashes & np.uint64(bits - 1), (hashes >> np.uint64(32)) | np.uint64(1)
    return [(first + np.uint64(i) * second) & np.uint64(bits - 1) for i in range(_PROBES)]


def _list(values: list[np.ndarray]) -> pa.ListArray:
    ends = np.cumsum([0, *map(len, values)])
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate([np.empty(0, np.uint64), *values]).view(np.int64)))


def _by_join(df: DataFrame, items: DataFrame, text: str, result: str, masks: tuple[str, ...], evidence: Evidence) -> DataFrame:
    context, seeds = df.sparkSession.sparkContext, Seeds(masks)

    def tokenized(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for said in batches:
            yield _list([token_hashes(t.decode("utf-8", "replace")) for some in pieces(said) for t in some])

    numbered = materialize(items.select("item", F.arrow_udf(tokenized, "array<long>")("said").alias("own")).withColumn("number", F.monotonically_increasing_id()), "seed-items")

    def of_items(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for number, own in zip(batch["number"].to_pylist(), batch["own"]):
                ids = own.values.to_numpy().view(np.uint64)
                for k in range(len(seeds.spans)):
                    found = seeds.of_item(ids, k)
                    if len(found):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(found), k), pa.int32()), pa.array(found.view(np.int64)), pa.array(np.full(len(found), number)), pa.array(np.arange(len(found)))], ["mask", "hash", "number", "begin"])

    sown = materialize(numbered.select("number", "own").mapInArrow(of_items, "mask int, hash long, number long, begin long"), "seed-hashes")
    sown_masks = sorted(r["mask"] for r in sown.select("mask").distinct().collect())  # a row a mask
    bits = 1 << max(10, min(_MOST_BITS, _BITS_A_SEED * max(1, sown.count())).bit_length())
    set_bits = context.broadcast(_filter(sown, bits))

    def hits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.struct([("mask", pa.int32()), ("hash", pa.int64()), ("place", pa.int64())])
        for batch in batches:
            for at, said in enumerate(t for some in pieces(batch["said"]) for t in some):
                ids, found = token_hashes(said.decode("utf-8", "replace")), []
                for k in sown_masks:
                    places = np.arange(max(0, len(ids) - seeds.spans[k] + 1))
                    value = window_hashes(ids, seeds.offsets[k], places)
                    keep = None
                    for probe in _probes(value, bits):
                        good = (set_bits.value[(probe >> np.uint64(3)).astype(np.int64)] >> (probe & np.uint64(7)).astype(np.uint8)) & 1 == 1
                        keep = good if keep is None else keep & good
                    value, places = value[keep], places[keep]
                    found.append((np.full(len(value), k), value, places))
                mask, value, place = (np.concatenate(x) for x in zip(*found))
                if len(value):
                    cells = pa.StructArray.from_arrays([pa.array(mask, pa.int32()), pa.array(value.view(np.int64)), pa.array(place, pa.int64())], fields=list(kind))
                    row = [batch["k1"].slice(at, 1), batch["k2"].slice(at, 1), _list([ids]), pa.ListArray.from_arrays(pa.array([0, len(value)], pa.int32()), cells)]
                    yield pa.RecordBatch.from_arrays(row, ["k1", "k2", "ids", "hits"])

    said = F.coalesce(F.col(text), F.lit(""))
    keys = [F.xxhash64(F.lit(1), said).alias("k1"), F.xxhash64(F.lit(2), said).alias("k2")]
    near = df.select(*keys, said.alias("said")).mapInArrow(hits, "k1 long, k2 long, ids array<long>, hits array<struct<mask:int,hash:long,place:long>>")
    near = materialize(near.dropDuplicates(["k1", "k2"]), "seed-texts")
    salt, salted = F.pmod("k1", F.lit(_SALTS)).cast("int").alias("salt"), F.explode(F.sequence(F.lit(0), F.lit(_SALTS - 1))).alias("salt")
    places = near.select("k1", "k2", salt, F.explode("hits").alias("h")).select("k1", "k2", "salt", "h.*")
    met = places.join(sown.select("*", salted), ["salt", "mask", "hash"]).select("k1", "k2", "salt", "number", (F.col("place") - F.col("begin")).alias("shift"))
    shifts = met.groupBy("k1", "k2", "salt", "number").agg(F.collect_set("shift").alias("shifts"))
    wanted = F.struct("number", "item", "own", "shifts")
    both = shifts.join(numbered.select("*", salted), ["salt", "number"]).groupBy("k1", "k2").agg(F.collect_list(wanted).alias("wanted")).join(near.select("k1", "k2", "ids"), ["k1", "k2"])
    names = [c.split()[0] for c in _MATCH.split(", ")]

    def compared(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
        for texts, wanted in batches:
            out = []
            for ids, each in zip(texts, wanted):
                ids, rows = ids.values.to_numpy(), []
                for w in sorted(each, key=lambda w: (w["item"].as_py() is not None, w["item"].as_py(), w["number"].as_py())):
                    own, best = w["own"].values.to_numpy(), None
                    for shift in sorted(w["shifts"].as_py()):
                        a, b = max(shift, 0), min(shift + len(own), len(ids))
                        good = verify(ids[a:b] == own[a - shift : b - shift], len(own), evidence) if b > a else None
                        if good and (best is None or good[0] > best[1]):
                            best = (w["item"].as_py(), good[0], good[2] - good[1], len(own), a + good[1], a + good[1] - shift)
                    if best:
                        rows.append(dict(zip(names, best)))
                out.append(rows)
            yield pa.array(out, pa.list_(pa.struct([(n, pa.int64()) for n in names])))

    kind = f"array<struct<{_MATCH.replace(' long', ':long')}>>"
    found = both.select("k1", "k2", F.arrow_udf(compared, kind)("ids", "wanted").alias("all")).where(F.size("all") > 0)
    found = materialize(found, "seed-found")
    if found.limit(_BROADCAST + 1).count() <= _BROADCAST:
        found = F.broadcast(found)
    one, two, all_ = (unused(df.columns, n) for n in ("k1", "k2", "all"))
    marked = df.withColumns({one: keys[0], two: keys[1]}).join(found.toDF(one, two, all_), [one, two], "left")
    none = F.lit([]).cast(found.schema["all"].dataType)
    return marked.select(*(c for c in df.columns if c != result), F.coalesce(all_, none).alias(result))


def _filter(sown: DataFrame, bits: int) -> np.ndarray:
    """The bits of all seeds' probes, eight a byte; gathered as distinct words, of which there are bits / 64 at most."""

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for place in _probes(batch["hash"].to_numpy().view(np.uint64), bits):
                yield pa.RecordBatch.from_arrays([pa.array((place >> np.uint64(6)).astype(np.int64)), pa.array((np.uint64(1) << (place & np.uint64(63))).view(np.int64))], ["word", "bits"])

    table = sown.select("hash").mapInArrow(probe, "word long, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toArrow()
    out = np.zeros(bits // 64, np.int64)
    out[table["word"].to_numpy()] = table["bits"].to_numpy()
    return out.view(np.uint8)
