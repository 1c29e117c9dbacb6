"""SentencePiece encoding and decoding by a Viterbi search that words with a common prefix share.

A text becomes marked words: blanks turn into the mark, and a cut stands before each run of marks.
In the vocabularies served here no piece has a mark after another character (checked on loading),
so no segmentation crosses a cut and each distinct word is searched once.  The words not yet known
are sorted, which is the order of a depth-first walk of their trie; the forward cells of the common
prefix with the word before stay, and only the rest is computed.

A cell holds the best score and last piece of any segmentation of a prefix.  For unigram models a
piece adds its score.  For BPE models a step from one piece to the next is allowed only if the pair,
merged alone, gives just these two pieces: a sequence is what BPE makes of its text exactly if all
its neighbours are so, and each prefix of such a sequence is too, so one path survives and it is the
BPE encoding.  Runs of marks share one score in such vocabularies, which leaves merges tied; words
that start with more than one mark are therefore merged directly.

Defined results: a null or empty text has no ids and decodes to an empty one; characters outside the
vocabulary become byte pieces, or the unknown id without those; a mark in a text decodes to a blank;
repeated rows give repeated rows; extra columns pass through, but for one with the result's name.
The model file is read on the driver and sent whole; its size is checked.
"""

from __future__ import annotations

import hashlib
import heapq
import os
import re
from collections.abc import Iterator
from itertools import chain
from struct import pack

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import pieces

MARK = "\u2581"
_WORD = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")
#: Words that a worker remembers newly before it sets them aside for those it set aside before.
_REMEMBERED = 300_000
_MAX_MODEL_BYTES = 32 << 20
#: Stands for no piece before the first; pairs of numbers are one number with this factor.
_NONE, _WIDE = 1 << 21, 1 << 23


class Vocabulary:
    """A model's pieces and scores, and its encoder."""

    def __init__(self, model: bytes, unigram: bool | None = None):
        from sentencepiece import SentencePieceProcessor
        from sentencepiece.sentencepiece_model_pb2 import ModelProto

        spec = ModelProto.FromString(model)
        if spec.normalizer_spec.precompiled_charsmap or spec.normalizer_spec.remove_extra_whitespaces or spec.trainer_spec.treat_whitespace_as_suffix:
            raise ValueError("only models that leave texts as they are, but for the blanks' marks, are served")
        plain = SentencePieceProcessor(model_proto=model)
        count = plain.get_piece_size()
        self.unigram = spec.trainer_spec.model_type == 1 if unigram is None else unigram
        self.prefix = spec.normalizer_spec.add_dummy_prefix
        usual = [i for i in range(count) if not (plain.is_control(i) or plain.is_unknown(i) or plain.is_byte(i))]
        self.ids = {plain.id_to_piece(i): i for i in usual}
        if any(MARK in p.lstrip(MARK) for p in self.ids):
            raise ValueError("a piece has a mark after another character, so words can't be cut apart")
        self.scores = {p: plain.get_score(i) for p, i in self.ids.items()}
        self.longest = max(map(len, self.ids), default=1)
        self.unknown = plain.unk_id()
        self.bytes = {int(plain.id_to_piece(i)[1:-1], 16): i for i in range(count) if plain.is_byte(i)}
        self.texts = {i: p.replace(MARK, " ").encode() for p, i in self.ids.items()} | {i: bytes([b]) for b, i in self.bytes.items()} | {self.unknown: " \u2047 ".encode()}
        self.floor = min(self.scores.values(), default=0.0) - 10.0
        #: Words' ids as 32-bit numbers, and those set aside.
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self._pairs: dict[int, bool] = {}
        self._names = {i: p for p, i in self.ids.items()}
        self._items = {p: (plain.get_score(i), i, pack("i", i)) for p, i in self.ids.items()}
        #: By a prefix's last three (else two) characters: lengths of the pieces that may end it, the longest first.
        ends: dict[str, set[int]] = {}
        for piece in self.ids:
            for k in (2, 3):
                if len(piece) >= k:
                    ends.setdefault(piece[-k:], {1}).add(len(piece))
        for tail, lengths in ends.items():
            if len(tail) == 3 and tail[1:] in self.ids:
                lengths.add(2)
            elif len(tail) == 2:
                lengths.intersection_update({1, 2})
        self._ends = {tail: tuple(sorted(lengths, reverse=True)) for tail, lengths in ends.items()}

    def merge(self, word: str) -> list[str]:
        """BPE by merging the best pair first, the leftmost of equals."""
        parts: list[str | None] = list(word)
        after, before = list(range(1, len(parts) + 1)), list(range(-1, len(parts) - 1))
        queue: list[tuple[float, int, int, str]] = []

        def offer(i: int) -> None:
            j = after[i]
            if j < len(parts) and (score := self.scores.get(parts[i] + parts[j])) is not None:
                heapq.heappush(queue, (-score, i, j, parts[i] + parts[j]))

        for i in range(len(parts) - 1):
            offer(i)
        while queue:
            _, i, j, joined = heapq.heappop(queue)
            if parts[i] is None or parts[j] is None or after[i] != j or parts[i] + parts[j] != joined:
                continue
            parts[i], parts[j], after[i] = joined, None, after[j]
            if after[i] < len(parts):
                before[after[i]] = i
            offer(i)
            if before[i] >= 0:
                offer(before[i])
        return [p for p in parts if p is not None]

    def learn(self, words: list[str]) -> None:
        """Segment words, in sorted order: the cells of the prefix shared with the word before are kept."""
        cells: list[tuple[float, int, bytes]] = [(0.0, _NONE, b"")]
        last, step = "", self._best if self.unigram else self._surviving
        for word in words:
            if not self.unigram and word.startswith(MARK + MARK):
                self.known[word] = self._joined(self.merge(word))
                continue
            shared = 0
            for a, b in zip(last, word):
                if a != b:
                    break
                shared += 1
            del cells[shared + 1 :]
            step(cells, word)
            last = word
            self.known[word] = cells[-1][2]

    def _item(self, piece: str) -> tuple[float, int, bytes]:
        """Score, number and packed ids of a piece; of a character outside the vocabulary, its bytes' ids."""
        if (found := self._items.get(piece)) is None:
            ids = [self.bytes[b] for b in piece.encode()] if self.bytes else [self.unknown]
            found = (self.floor, -1 - ord(piece), pack(f"{len(ids)}i", *ids))
        return found

    def _after(self, ids: bytes, number: int, more: bytes) -> bytes:
        """Ids with a piece's behind them; unknown ids in a row are one."""
        return ids if number < 0 and not self.bytes and ids.endswith(more) else ids + more

    def _joined(self, path: list[str]) -> bytes:
        ids = b""
        for piece in path:
            _, number, more = self._item(piece)
            ids = self._after(ids, number, more)
        return ids

    def _lengths(self, word: str, end: int) -> tuple[int, ...]:
        """Lengths of pieces that may end at ``end``, the longest first; a single character always may."""
        if end >= 3 and (found := self._ends.get(word[end - 3 : end])) is not None:
            return found
        return self._ends.get(word[end - 2 : end], (1,)) if end >= 2 else (1,)

    def _best(self, cells: list[tuple[float, int, bytes]], word: str) -> None:
        """Cells to the word's end, of a unigram model; of equal scores the longer last piece."""
        for end in range(len(cells), len(word) + 1):
            best, chosen, before = -np.inf, None, None
            for length in self._lengths(word, end):
                if length <= end and (length == 1 or word[end - length : end] in self.ids):
                    item = self._item(word[end - length : end])
                    if item[0] + cells[end - length][0] > best:
                        best, chosen, before = item[0] + cells[end - length][0], item, cells[end - length]
            cells.append((best, chosen[1], self._after(before[2], chosen[1], chosen[2])))

    def _surviving(self, cells: list[tuple[float, int, bytes]], word: str) -> None:
        """Cells to the word's end, of a BPE model: a step from piece to piece must be one that merging leaves."""
        items, pairs, ends, count = self._items, self._pairs, self._ends, len(word)
        for end in range(len(cells), count + 1):
            for length in (ends.get(word[end - 3 : end]) if end > 2 else None) or self._lengths(word, end):
                start = end - length
                if start < 0:
                    continue
                if (item := items.get(word[start:end])) is None:
                    if length > 1:
                        continue
                    item = self._item(word[start:end])
                total, before, ids = cells[start]
                score, number, more = item
                if (stays := pairs.get(before * _WIDE + number)) is None:
                    stays = self._stays(before, number)
                if stays:
                    cells.append((total + score, number, ids + more if number >= 0 else self._after(ids, number, more)))
                    break
            else:  # no path survived, which a vocabulary built by merges rules out
                path = self.merge(word[:end])
                cells.append((self.floor, self._item(path[-1])[1], self._joined(path)))

    def _stays(self, left: int, right: int) -> bool:
        """Whether BPE of two pieces' text is just these two (of a first piece, with nothing before it, the piece)."""
        if len(self._pairs) >= 2 * _REMEMBERED:
            self._pairs.clear()
        parts = [self._names[n] if n >= 0 else chr(-1 - n) for n in (left, right) if n != _NONE]
        found = self._pairs[left * _WIDE + right] = self.merge("".join(parts)) == parts
        return found

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All ids in one array, and where each text starts in it."""
        split = [_WORD.findall(((MARK if self.prefix else "") + t.replace(" ", MARK)) if t else "") for t in texts]
        distinct = set(chain.from_iterable(split))
        fresh = distinct.difference(self.known)
        if len(self.known) + len(fresh) > _REMEMBERED:
            self.known, self.older = {}, self.known
            fresh = distinct
        held = {w: ids for w in fresh if (ids := self.older.get(w)) is not None}
        self.known.update(held)
        self.learn(sorted(fresh.difference(held)))
        look = self.known.__getitem__
        each = [b"".join(map(look, words)) for words in split]
        starts = np.zeros(len(texts) + 1, np.int64)
        np.cumsum([len(x) // 4 for x in each], out=starts[1:])
        return np.frombuffer(b"".join(each), np.int32), starts

    def decode(self, ids: list[int]) -> str:
        """The text of ids; byte pieces that are no UTF-8 become replacement characters."""
        text = b"".join([self.texts.get(i, b"") for i in ids]).decode("utf-8", "replace")
        return text[1:] if self.prefix and text.startswith(" ") else text


_loaded: dict[tuple[str, bool | None], Vocabulary] = {}


def _vocabulary(model: bytes, unigram: bool | None) -> Vocabulary:
    """One vocabulary, with the words it remembers, a worker process."""
    key = (hashlib.sha256(model).hexdigest(), unigram)
    if key not in _loaded:
        _loaded[key] = Vocabulary(model, unigram)
    return _loaded[key]


def load_model(path: str) -> bytes:
    if os.path.getsize(path) > _MAX_MODEL_BYTES:
        raise ValueError(f"the model has over {_MAX_MODEL_BYTES} bytes")
    with open(path, "rb") as file:
        return file.read()


def encode(df: DataFrame, model: bytes, *, text: str = "text", result: str = "ids", unigram: bool | None = None) -> DataFrame:
    """Adds ``result``: the ids of each text."""
    sent = df.sparkSession.sparkContext.broadcast(model)

    def each(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        vocabulary = _vocabulary(sent.value, unigram)
        for texts in batches:
            made = [vocabulary.encode([t.decode("utf-8", "replace") for t in some]) for some in pieces(texts)]
            parts = [pa.ListArray.from_arrays(pa.array(starts, pa.int32()), pa.array(ids, pa.int32())) for ids, starts in made]
            yield pa.concat_arrays(parts) if parts else pa.array([], pa.list_(pa.int32()))

    return df.withColumn(result, F.arrow_udf(each, "array<int>")(F.col(text)))


def encode_checked(df: DataFrame, model: bytes, *, id: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, ids, n_tokens, round_trip) of each row, the last whether the ids decode to the text with its marks as blanks.

    One pass in one worker, piece by piece, where encode and decode after one another would keep two
    vocabularies a task and the ids of a whole batch.
    """
    sent = df.sparkSession.sparkContext.broadcast(model)
    kind = df.schema[id].dataType.simpleString()

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = _vocabulary(sent.value, None)
        for batch in batches:
            at = 0
            for some in pieces(batch.column(1), 1 << 20):
                said = [t.decode("utf-8", "replace") for t in some]
                ids, starts = vocabulary.encode(said)
                same = [vocabulary.decode(ids[a:b].tolist()) == t.replace(MARK, " ") for t, a, b in zip(said, starts, starts[1:])]
                lists = pa.ListArray.from_arrays(pa.array(starts, pa.int32()), pa.array(ids, pa.int32()))
                columns = [batch.column(0).slice(at, len(some)), lists, pa.array(np.diff(starts), pa.int64()), pa.array(same, pa.bool_())]
                yield pa.RecordBatch.from_arrays(columns, [id, "ids", "n_tokens", "round_trip"])
                at += len(some)

    return df.select(id, text).mapInArrow(each, f"`{id}` {kind}, ids array<int>, n_tokens long, round_trip boolean")


def decode(df: DataFrame, model: bytes, *, ids: str = "ids", result: str = "decoded") -> DataFrame:
    """Adds ``result``: the text of each row's ids."""
    sent = df.sparkSession.sparkContext.broadcast(model)

    def each(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        vocabulary = _vocabulary(sent.value, None)
        for rows in batches:
            yield pa.array([vocabulary.decode(r.values.to_numpy(zero_copy_only=False).tolist()) if r.is_valid else "" for r in rows], pa.string())

    return df.withColumn(result, F.arrow_udf(each, "string")(F.col(ids)))


def read_back(df: DataFrame, model: bytes, *, ids: str = "ids", result: str = "read") -> DataFrame:
    """Adds ``result``: (n_tokens, ids_sha256 of the ids as little-endian 32-bit numbers, decoded_sha256 of the decoded text)."""
    sent = df.sparkSession.sparkContext.broadcast(model)
    kind = pa.struct([("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])

    def each(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        vocabulary = _vocabulary(sent.value, None)
        for rows in batches:
            out = []
            for row in rows:
                numbers = row.values.to_numpy(zero_copy_only=False).astype("<i4") if row.is_valid else np.empty(0, "<i4")
                decoded = vocabulary.decode(numbers.tolist()).encode()
                out.append({"n_tokens": len(numbers), "ids_sha256": hashlib.sha256(numbers.tobytes()).hexdigest(), "decoded_sha256": hashlib.sha256(decoded).hexdigest()})
            yield pa.array(out, kind)

    return df.withColumn(result, F.arrow_udf(each, "n_tokens long, ids_sha256 string, decoded_sha256 string")(F.col(ids)))
