"""Interpolated modified Kneser-Ney n-gram model (order 2 and up), counted in Spark, scored from mapped arrays.

Words are 64-bit hashes.  A task adds up the n-grams of its texts before anything is shuffled and
packs them, sorted and compressed, into one row a bucket; a bucket holds whole contexts (all n-grams
with the same words before the last), so its contexts' sums need no other.  Contexts of any length
that are seen more than ``hot_tokens`` times (and the empty one) are dealt over all buckets by the
n-gram's last word, and their sums added up afterwards.  Every distinct n-gram of an order gives one
continuation count to its tail, an n-gram of the order below.

A bucket's n-grams are written as arrays sorted by a hash of context and word, keys and counts, and
its contexts likewise, keys and sums.  Some buckets share a file, a *volume*, which ends in an index of
its arrays; the model lists the volumes, and one that is listed and missing is an error.  Workers map
volumes into memory, a bounded number at a time, and look up all n-grams of a batch of texts, sorted,
at once.

    p_k(w | c) = max(count(c w) - D, 0) / count(c .) + gamma(c) * p_(k-1)(w | shorter c)

with D of 1, 2 and 3 or more from the counts of counts, each order's own; order 1 backs off to the
uniform 1 / (V + 1) over known tokens and one unknown.  Contexts never seen give all to the shorter.

Defined results: tokens are runs without ASCII blanks, A-Z lower-cased, then one end, counted as a
token; null and empty texts are one end; contexts at the start are filled up with a start mark; with
no training text every token has p = 1; counts of counts that are zero give a discount of half its
count at most; repeated rows are training data and scored like any other; extra columns are ignored.
"""

from __future__ import annotations

import json
import math
import mmap
import shutil
import sys
import tempfile
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import Files, materialize, release, scratch
from .warc import file_system
from .words import joined, pieces, sums, words_of

#: Hashes of the end token and the start mark; no word has them but by chance of 2^-63.
END, START = np.uint64(0x5DEECE66D1234567), np.uint64(0xC2B2AE3D27D4EB4F)
_MIX = np.uint64(0x9E3779B97F4A7C15)
#: Bytes of text that are numbered at once; counts that a task holds; n-grams that a bucket holds on average;
#: buckets of a volume at most; and volumes that a worker maps at once.
_PIECE = 8 << 20
_HELD = 2_000_000
_IN_BUCKET = 1_000_000
_IN_VOLUME = 8
_MAPPED = 4_000


def mix(value: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads them."""
    value = (value ^ (value >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    value = (value ^ (value >> np.uint64(29))) * _MIX
    return value ^ (value >> np.uint64(32))


def chain(context: np.ndarray, word: np.ndarray) -> np.ndarray:
    """The hash of a context with a word after it."""
    return mix(context * _MIX + word)


@dataclass(frozen=True)
class Numbered:
    """Texts as numbers of their distinct tokens.

    hashes: of the distinct tokens, in ascending order; tokens: the number of each token, ends included;
    starts: where each text starts; start: the number of the start mark, which no text has.
    """

    hashes: np.ndarray
    tokens: np.ndarray
    starts: np.ndarray
    start: int

    def before(self, back: int) -> np.ndarray:
        """The token ``back`` places before each; the start mark where there is none."""
        place = np.arange(len(self.tokens)) - np.repeat(self.starts[:-1], np.diff(self.starts))
        out = np.full(len(self.tokens), self.start, np.int64)
        has = np.flatnonzero(place >= back)
        out[has] = self.tokens[has - back]
        return out


def number(texts: list[bytes]) -> Numbered:
    from xxhash import xxh64_intdigest

    spans, _ = words_of(*joined(texts, lowered=True))
    words, distinct = spans.numbers()
    hashes = np.append(np.fromiter(map(xxh64_intdigest, distinct.to_pylist()), np.uint64, len(distinct)), [END, START])
    order = np.argsort(hashes)
    rank = np.empty(len(hashes), np.int64)
    rank[order] = np.arange(len(hashes))
    starts = spans.starts + np.arange(len(texts) + 1)
    tokens = np.full(starts[-1], rank[-2], np.int64)
    inside = np.ones(starts[-1], bool)
    inside[starts[1:] - 1] = False
    tokens[inside] = rank[words]
    return Numbered(hashes[order], tokens, starts, int(rank[-1]))


def add_up(columns: list[np.ndarray], counts: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """Distinct rows in sorted order, the first column's first, and their counts' sums."""
    if not len(counts):
        return columns, counts
    order = np.lexsort(columns[::-1])
    columns, counts = [c[order] for c in columns], counts[order]
    fresh = np.ones(len(counts), bool)
    fresh[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in columns])
    at = np.flatnonzero(fresh)
    return [c[at] for c in columns], np.add.reduceat(counts, at)


def pack(columns: list[np.ndarray], counts: np.ndarray) -> bytes:
    """Sorted rows as bytes: differences of the first column, then bytes plane by plane, compressed."""
    from zstandard import ZstdCompressor

    first = np.diff(columns[0], prepend=np.uint64(0))
    planes = [np.ascontiguousarray(c.view(np.uint8).reshape(-1, 8).T).tobytes() for c in (first, *columns[1:], counts.astype(np.uint64))]
    return len(counts).to_bytes(8, "little") + ZstdCompressor(3).compress(b"".join(planes))


def unpack(data: bytes, width: int) -> tuple[list[np.ndarray], np.ndarray]:
    from zstandard import ZstdDecompressor

    n = int.from_bytes(data[:8], "little")
    raw = np.frombuffer(ZstdDecompressor().decompress(data[8:], max_output_size=max(1, (width + 1) * n * 8)), np.uint8).reshape(width + 1, 8, n)
    columns = [np.ascontiguousarray(raw[k].T).view(np.uint64).reshape(n) for k in range(width + 1)]
    return [np.cumsum(columns[0], dtype=np.uint64), *columns[1:-1]], columns[-1].astype(np.int64)


def discounts(counts_of_counts: list[int]) -> tuple[float, float, float]:
    """D of 1, 2 and 3 or more, from how many n-grams have the counts 1 to 4."""
    n1, n2, n3, n4 = counts_of_counts
    if not n1 or not n2:
        return 0.5, 1.0, 1.5
    y = n1 / (n1 + 2 * n2)
    raw = (1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3 if n3 else 1.5)
    return tuple(min(max(d, 0.05 * k), 0.95 * k) for k, d in enumerate(raw, 1))


def _discount(counts: np.ndarray, d: tuple[float, float, float]) -> np.ndarray:
    """What is taken from each count; nothing from a count of zero."""
    return np.array([0.0, *d])[np.minimum(counts, 3)]


@dataclass(frozen=True)
class Model:
    """Where the arrays are, and the numbers that all workers need.

    hot: sums (total, n1, n2, n3) of the contexts that are dealt over all buckets, by order and context.
    volumes: the files that were written, by kind.
    """

    folder: str
    order: int
    buckets: int
    in_volume: int
    volumes: dict[str, frozenset[int]]
    n_tokens: int
    n_types: int
    dealt: tuple[int, ...]
    d: dict[int, tuple[float, float, float]]
    hot: dict[int, dict[int, tuple[int, int, int, int]]]


def bucket_of(context: np.ndarray, word: np.ndarray, buckets: int, hot: np.ndarray) -> np.ndarray:
    """By context; by context and word for the hot ones."""
    spread = np.where(np.isin(context, hot), chain(context, word), mix(context)) if len(hot) else mix(context)
    return (spread % np.uint64(buckets)).astype(np.int64)


def by_bucket(bucket: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """An order by bucket that keeps that within each, and where each bucket starts in it."""
    order = np.argsort(bucket.astype(np.uint16) if buckets <= 1 << 16 else bucket, kind="stable")
    return order, np.concatenate(([0], np.cumsum(np.bincount(bucket, minlength=buckets))))


def context_hash(words: list[np.ndarray], n: int) -> np.ndarray:
    """The hash of the words of a context, in order; an empty one is zero."""
    out = np.zeros(n, np.uint64)
    for w in words:
        out = chain(out, w)
    return out


# --- counting ---


def _unigrams(texts: DataFrame, text: str) -> DataFrame:
    """(word, n): counts of tokens."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0

        def emit() -> pa.RecordBatch:
            (words,), counts = add_up([np.concatenate([h[0] for h in held])], np.concatenate([h[1] for h in held]))
            return pa.RecordBatch.from_arrays([pa.array(words.view(np.int64)), pa.array(counts)], ["word", "n"])

        for batch in batches:
            for some in pieces(batch.column(0), _PIECE):
                found = number(some)
                counts = np.bincount(found.tokens, minlength=len(found.hashes))
                seen = np.flatnonzero(counts)
                held.append((found.hashes[seen], counts[seen]))
                rows += len(seen)
                if rows >= _HELD:
                    yield emit()
                    held, rows = [], 0
        if held:
            yield emit()

    return texts.select(text).mapInArrow(count, "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))


def _packed(texts: DataFrame, text: str, order: int, buckets: int, hot: np.ndarray) -> DataFrame:
    """(bucket, data): n-grams of the texts, added up piece by piece and packed."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for some in pieces(batch.column(0), _PIECE):
                found = number(some)
                if order == 2:  # two numbers make one key, and numbers are in the order of the hashes
                    keys, counts = np.unique(found.before(1) * len(found.hashes) + found.tokens, return_counts=True)
                    columns = [found.hashes[keys // len(found.hashes)], found.hashes[keys % len(found.hashes)]]
                else:
                    columns = [found.hashes[found.before(back)] for back in range(order - 1, 0, -1)]
                    columns, counts = add_up([*columns, found.hashes[found.tokens]], np.ones(len(found.tokens), np.int64))
                yield from pack_by_bucket(columns, counts, buckets, hot)

    return texts.select(text).mapInArrow(count, "bucket int, data binary")


def pack_by_bucket(columns: list[np.ndarray], counts: np.ndarray, buckets: int, hot: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Sorted rows, dealt into packed buckets."""
    bucket = bucket_of(context_hash(columns[:-1], len(counts)), columns[-1], buckets, hot)
    order, edges = by_bucket(bucket, buckets)
    for b in np.flatnonzero(np.diff(edges)).tolist():
        own = order[edges[b] : edges[b + 1]]
        yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([pack([c[own] for c in columns], counts[own])], pa.binary())], ["bucket", "data"])


def _hot_contexts(texts: DataFrame, text: str, order: int, hot_words: np.ndarray, bound: float) -> np.ndarray:
    """Contexts of two words up to order - 1 that are seen over ``bound`` times: all their words are hot, so only such are counted."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for some in pieces(batch.column(0), _PIECE):
                found = number(some)
                hot, all_hot = np.isin(found.hashes, hot_words), np.ones(len(found.tokens), bool)
                before = []
                for back in range(1, order):
                    before.insert(0, found.before(back))
                    all_hot &= hot[before[0]]
                    if back > 1 and all_hot.any():
                        at = np.flatnonzero(all_hot)
                        (keys,), counts = add_up([context_hash([found.hashes[w[at]] for w in before], len(at))], np.ones(len(at), np.int64))
                        yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(counts)], ["context", "n"])

    counted = texts.select(text).mapInArrow(count, "context long, n long").groupBy("context").agg(F.sum("n").alias("n"))
    return np.array([r["context"] for r in counted.where(F.col("n") > bound).collect()], np.int64).view(np.uint64)  # tokens / bound for each length


_MERGED = "kind string, bucket int, data binary, context long, a long, b long, c long, d long"


def _by_volume(rows: DataFrame, buckets: int, in_volume: int) -> DataFrame:
    """Rows by volume, a volume a task, buckets in turn."""
    volume = F.floor(F.col("bucket") / in_volume).cast("int")
    return rows.withColumn("volume", volume).repartitionById(-(-buckets // in_volume), F.col("volume")).drop("volume").sortWithinPartitions("bucket")


def _each_bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, pa.Table]]:
    """Bucket by bucket, all its rows."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        buckets = batch["bucket"].to_numpy()
        cuts = [0, *(np.flatnonzero(np.diff(buckets)) + 1).tolist(), len(buckets)]
        for a, b in zip(cuts, cuts[1:]):
            if a == b:
                continue
            if held and held[-1]["bucket"][0].as_py() != buckets[a]:
                yield held[0]["bucket"][0].as_py(), pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
    if held:
        yield held[0]["bucket"][0].as_py(), pa.Table.from_batches(held)


def _merged(packed: DataFrame, order: int, folder: str, buckets: int, in_volume: int, hot: np.ndarray) -> DataFrame:
    """Adds up each bucket and stores its arrays: contexts, their sums, n-grams' keys and counts.

    Rows by kind: ``volume``, a file that was written; ``order``, how many n-grams have the counts 1 to 4
    (a to d); ``hot``, the bucket's part of a hot context's sums; ``tails``, packed counts of the order
    below, for bucket ``bucket``.
    """
    names = [c.split()[0] for c in _MERGED.split(", ")]
    schema = pa.schema([("kind", pa.string()), ("bucket", pa.int32()), ("data", pa.binary()), *((n, pa.int64()) for n in names[3:])])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        volume = None
        for b, table in _each_bucket(batches):
            volume = volume or _Volume(folder, f"order{order}", b // in_volume)
            parts = [unpack(data.as_py(), order) for data in table["data"]]
            columns, counts = add_up([np.concatenate([p[0][k] for p in parts]) for k in range(order)], np.concatenate([p[1] for p in parts]))
            del parts
            hashed = context_hash(columns[:-1], len(counts))
            by_context = np.argsort(hashed, kind="stable")
            found, totals = _totals(hashed[by_context], counts[by_context])
            shared = np.isin(found, hot)
            rows = [dict(zip(names, ("order", b, None, None, *(int((counts == k).sum()) for k in range(1, 5)))))]
            rows += [dict(zip(names, ("hot", b, None, int(c.astype(np.int64)), *map(int, totals[:, k])))) for k, c in zip(np.flatnonzero(shared), found[shared])]
            keys = chain(hashed, columns[-1])
            by_key = np.argsort(keys)
            volume.add(b, found[~shared], _small(totals[:, ~shared]), keys[by_key], _small(counts[by_key]))
            del hashed, keys, by_key, by_context
            yield from pa.Table.from_pylist(rows, schema).to_batches()
            if order > 1:
                for batch in pack_by_bucket(*add_up(columns[1:], np.ones(len(counts), np.int64)), buckets, hot):
                    yield pa.RecordBatch.from_pylist([{"kind": "tails", "bucket": batch["bucket"][0].as_py(), "data": batch["data"][0].as_py()}], schema)
        if volume is not None:
            yield pa.RecordBatch.from_pylist([{"kind": "volume", "bucket": volume.close()}], schema)

    return _by_volume(packed, buckets, in_volume).mapInArrow(merge, _MERGED)


def _small(counts: np.ndarray) -> np.ndarray:
    return counts.astype(np.uint32 if counts.max(initial=0) < 1 << 32 else np.uint64)


class _Volume:
    """A file of arrays, put in place by a rename, so that a repeated task only replaces it by the same."""

    def __init__(self, folder: str, kind: str, number: int):
        self.number = number
        self.system, base = file_system(folder)
        self.path, self.draft = f"{base}/{kind}-{number}", f"{base}/.{kind}-{number}-{uuid.uuid4().hex}"
        self.out, self.at, self.index = self.system.open_output_stream(self.draft), 0, {}

    def add(self, bucket: int, *arrays: np.ndarray) -> None:
        for array in arrays:
            gap = -self.at % 64
            data = np.ascontiguousarray(array)
            self.out.write(bytes(gap))
            self.out.write(pa.py_buffer(data) if data.size else b"")
            self.index.setdefault(bucket, []).append((self.at + gap, data.dtype.str, data.shape))
            self.at += gap + data.nbytes

    def close(self) -> int:
        index = json.dumps(self.index).encode()
        self.out.write(index + len(index).to_bytes(8, "little"))
        self.out.close()
        self.system.move(self.draft, self.path)
        return self.number


def _map(folder: str, kind: str, number: int) -> dict[int, list[np.ndarray]]:
    """A volume's arrays by bucket, mapped into memory: from a nameless copy beside the worker if the folder is not local."""
    system, base = file_system(folder)
    path = f"{base}/{kind}-{number}"
    if system.type_name == "local":
        file = open(path, "rb")
    else:
        file = tempfile.TemporaryFile()
        with system.open_input_stream(path) as source:
            shutil.copyfileobj(source, file, 1 << 20)
        file.flush()
    with file:
        options = {"trackfd": False} if sys.version_info >= (3, 13) else {}  # a map then keeps no descriptor
        data = mmap.mmap(file.fileno(), 0, access=mmap.ACCESS_READ, **options)
    end = len(data) - 8
    index = json.loads(data[end - int.from_bytes(data[end:], "little") : end])
    return {int(b): [np.frombuffer(data, np.dtype(kind), math.prod(shape), at).reshape(shape) for at, kind, shape in arrays] for b, arrays in index.items()}


def _totals(contexts: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct contexts (sorted input), and their sums, a row each: of counts, and of n-grams counted once, twice, and more."""
    at = np.flatnonzero(np.concatenate(([True], contexts[1:] != contexts[:-1]))) if len(contexts) else np.empty(0, np.int64)
    if not len(at):
        return contexts[:0], np.empty((4, 0), np.int64)
    return contexts[at], np.stack([np.add.reduceat(x.astype(np.int64), at) for x in (counts, counts == 1, counts == 2, counts >= 3)])


def train(texts: DataFrame, *, text: str = "text", order: int = 2, in_bucket: int | None = None, hot_tokens: int | None = None) -> Model:
    """Count ``texts`` and write the model's arrays to a new shared folder.

    in_bucket: n-grams that a bucket holds on average, a task's memory against the number of buckets; a
    million by default, and more where tokens go into the trillions.  hot_tokens: contexts that are seen
    more often are dealt over all buckets, by default a quarter of ``in_bucket``; there are at most
    tokens / hot_tokens of each length, which bounds what the driver gathers: four a bucket.
    """
    if order < 2:
        raise ValueError("the order is 2 or more")
    spark = texts.sparkSession
    folder = Files(spark, scratch(spark, "kneser-ney")).root
    files = Files(spark, folder)
    files.make(folder)
    words = materialize(_unigrams(texts, text), "kneser-ney-words")
    n_tokens, n_types = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    in_bucket = in_bucket or _IN_BUCKET
    hot_tokens = max(1, in_bucket // 4) if hot_tokens is None else hot_tokens
    buckets = max(1, -(-n_tokens // in_bucket))
    in_volume = min(_IN_VOLUME, max(1, buckets // 64))
    often = words.where(F.col("n") > hot_tokens).select("word").collect()
    single = np.array([START, *np.array([r["word"] for r in often], np.int64).view(np.uint64)], np.uint64)
    hot = [context_hash([single], len(single)), np.zeros(1, np.uint64)]  # zero: the empty context of order 1
    if order > 2:
        hot.append(_hot_contexts(texts, text, order, single, hot_tokens))
    hot = np.sort(np.concatenate(hot))
    d, sums_of, volumes = {}, {}, {"words": _write_words(words, folder, buckets, in_volume)}
    release(words)
    packed, before = _packed(texts, text, order, buckets, hot), None
    for k in range(order, 0, -1):
        merged = materialize(_merged(packed, k, folder, buckets, in_volume, hot), f"kneser-ney-{k}")
        if before is not None:
            release(before)
        n = [F.sum(c) for c in "abcd"]
        d[k] = discounts([x or 0 for x in merged.where("kind = 'order'").agg(*n).first()])
        sums_of[k] = {r[0] % (1 << 64): tuple(r[1:]) for r in merged.where("kind = 'hot'").groupBy("context").agg(*n).collect()}
        volumes[f"order{k}"] = frozenset(r["bucket"] for r in merged.where("kind = 'volume'").select("bucket").collect())  # a row a file
        packed, before = merged.where("kind = 'tails'").select("bucket", "data"), merged
    release(before)
    return Model(folder, order, buckets, in_volume, volumes, n_tokens, n_types, tuple(hot.tolist()), d, sums_of)


def _write_words(words: DataFrame, folder: str, buckets: int, in_volume: int) -> frozenset[int]:
    """Token counts as sorted arrays; the volumes that have any."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        volume = None
        for b, table in _each_bucket(batches):
            volume = volume or _Volume(folder, "words", b // in_volume)
            keys, counts = table["word"].to_numpy().view(np.uint64), table["n"].to_numpy()
            order = np.argsort(keys)
            volume.add(b, keys[order], counts[order])
        if volume is not None:
            yield pa.RecordBatch.from_pydict({"volume": pa.array([volume.close()], pa.int32())})

    own = words.select((F.call_function("shiftrightunsigned", "word", F.lit(32)) % F.lit(buckets)).cast("int").alias("bucket"), "word", "n")
    return frozenset(r["volume"] for r in _by_volume(own, buckets, in_volume).mapInArrow(write, "volume int").collect())


# --- scoring ---


class Arrays:
    """The model's arrays, mapped into memory by one task: the ``_MAPPED`` volumes last used."""

    def __init__(self, model: Model):
        self.model = model
        self.dealt = np.array(model.dealt, np.uint64)
        self._maps: dict[tuple[str, int], dict[int, list[np.ndarray]]] = {}

    def _arrays(self, kind: str, bucket: int) -> list[np.ndarray] | None:
        volume = kind, bucket // self.model.in_volume
        if volume[1] not in self.model.volumes[kind]:
            return None
        found = self._maps.pop(volume, None) or _map(self.model.folder, *volume)
        if len(self._maps) >= _MAPPED:
            self._maps.pop(next(iter(self._maps)))
        self._maps[volume] = found
        return found.get(bucket)

    def look_up(self, kind: str, first: int, bucket: np.ndarray, keys: np.ndarray, rows: int = 1) -> np.ndarray:
        """The values of keys, 0 where there is none; ``rows`` of them each.  first: which of a bucket's arrays has the keys."""
        out = np.zeros((rows, len(keys)))
        by_key = np.argsort(keys)
        order, edges = by_bucket(bucket[by_key], self.model.buckets)
        order = by_key[order]
        for b in np.flatnonzero(np.diff(edges)).tolist():
            arrays = self._arrays(kind, b)
            if arrays is not None and len(arrays[first]):
                known, values = arrays[first : first + 2]
                own = order[edges[b] : edges[b + 1]]
                at = np.minimum(np.searchsorted(known, keys[own]), len(known) - 1)
                hit = known[at] == keys[own]
                out[:, own[hit]] = values[..., at[hit]]
        return out

    def counts(self, words: np.ndarray) -> np.ndarray:
        """How often words were seen in training."""
        return self.look_up("words", 0, ((words >> np.uint64(32)) % np.uint64(self.model.buckets)).astype(np.int64), words)[0]

    def sums(self, k: int, distinct: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Total and backing-off weight of contexts; 0 and 1 for one that was never seen."""
        found = self.look_up(f"order{k}", 0, bucket_of(distinct, distinct, self.model.buckets, np.empty(0, np.uint64)), distinct, 4)
        for i in np.flatnonzero(np.isin(distinct, self.dealt)).tolist():
            found[:, i] = self.model.hot[k].get(int(distinct[i]), (0, 0, 0, 0))
        total = found[0]
        return total, np.where(total > 0, np.array(self.model.d[k]) @ found[1:] / np.maximum(total, 1), 1.0)

    def _level(self, k: int, context: np.ndarray, words: np.ndarray, total: np.ndarray, gamma: np.ndarray, lower: np.ndarray) -> np.ndarray:
        count = self.look_up(f"order{k}", 2, bucket_of(context, words, self.model.buckets, self.dealt), chain(context, words))[0]
        return (count - _discount(count.astype(np.int64), self.model.d[k])) / np.maximum(total, 1) + gamma * lower

    def probability(self, found: Numbered) -> np.ndarray:
        """p of each token after those before it; the first two orders' contexts are worked out for distinct tokens."""
        model, distinct = self.model, found.hashes
        none = np.zeros(len(distinct), np.uint64)
        total, gamma = self.sums(1, none[:1])
        p = self._level(1, none, distinct, total[0], gamma[0], np.full(len(distinct), 1.0 / (model.n_types + 1)))[found.tokens]
        words, context = distinct[found.tokens], None
        for k in range(2, model.order + 1):
            if k == 2:
                each, inverse = chain(none, distinct), found.before(1)
                context = each[inverse]
            else:
                context = context_hash([distinct[found.before(back)] for back in range(k - 1, 0, -1)], len(words))
                each, inverse = np.unique(context, return_inverse=True)
            total, gamma = self.sums(k, each)
            p = self._level(k, context, words, total[inverse], gamma[inverse], p)
        return p


def score(df: DataFrame, model: Model, *, text: str = "text", result: str = "lm") -> DataFrame:
    """Adds ``result``: (n_tokens, n_known, base_score, score), logarithms to base 10."""
    names = ["n_tokens", "n_known", "base_score", "score"]

    def each(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        arrays = Arrays(model)
        for texts in batches:
            columns: list[list[np.ndarray]] = [[np.empty(0, np.int64)], [np.empty(0, np.int64)], [np.empty(0)], [np.empty(0)]]
            for some in pieces(texts, _PIECE):
                found = number(some)
                seen = arrays.counts(found.hashes)
                base = np.log10((seen + 0.1) / (model.n_tokens + 0.1 * (model.n_types + 1)))[found.tokens]
                p, starts = np.log10(arrays.probability(found)), found.starts
                for column, value in zip(columns, (np.diff(starts), sums((seen > 0)[found.tokens].astype(np.int64), starts), sums(base, starts), sums(p, starts))):
                    column.append(value)
            ints, floats = [np.concatenate(c) for c in columns[:2]], [np.concatenate(c) for c in columns[2:]]
            yield pa.StructArray.from_arrays([*(pa.array(c, pa.int64()) for c in ints), *(pa.array(c, pa.float64()) for c in floats)], names)

    return df.withColumn(result, F.arrow_udf(each, "n_tokens long, n_known long, base_score double, score double")(F.col(text)))


def held_out(id: Column, folds: int = 10) -> Column:
    """Whether crc32 of the id as text leaves no remainder by ``folds``; a null id counts as an empty text."""
    return F.crc32(F.coalesce(id.cast("string"), F.lit("")).cast("binary")) % folds == 0
