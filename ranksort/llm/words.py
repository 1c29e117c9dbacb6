"""Reading texts in Arrow batches, in pieces of bounded size, and numbering words."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text that are worked on at once; a longer text is a piece of its own.
PIECE_BYTES = 4 << 20
#: ASCII white space between words, as in ``[^\x20\x09-\x0D]+``; bytes.split() splits at the same six.
BLANKS = b" \t\n\x0b\x0c\r"
_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def pieces(texts: pa.Array, piece_bytes: int = PIECE_BYTES) -> Iterator[list[bytes]]:
    """The batch's texts as UTF-8 bytes, null as empty, in lists of about ``piece_bytes``."""
    if not len(texts):
        return
    sizes = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    part = (np.cumsum(sizes) - sizes) // piece_bytes
    cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(sizes)]
    raw = texts.cast(pa.large_binary())
    for a, b in zip(cuts, cuts[1:]):
        yield [t or b"" for t in raw.slice(a, b - a).to_pylist()]


def lower(text: bytes) -> bytes:
    """A-Z lower-cased, all else as it is."""
    return text.translate(_LOWER)


@dataclass(frozen=True)
class Spans:
    """Stretches of some texts that lie one after the other in ``data``, each text's together.

    stops: one past the end of each stretch; starts: the first stretch of each text, and one more entry.
    """

    data: np.ndarray
    stops: np.ndarray
    starts: np.ndarray

    def numbers(self) -> tuple[np.ndarray, pa.Array]:
        """Equal stretches' numbers, from 0 in order of appearance, and the distinct stretches."""
        offsets = np.zeros(len(self.stops) + 1, np.int64)
        offsets[1:] = self.stops
        cells = pa.Array.from_buffers(pa.large_binary(), len(self.stops), [None, pa.py_buffer(offsets), pa.py_buffer(self.data)])
        coded = cells.dictionary_encode()
        return coded.indices.to_numpy(zero_copy_only=False), coded.dictionary


_IS_BLANK = np.zeros(256, bool)
_IS_BLANK[list(BLANKS)] = True


def joined(texts: list[bytes], lowered: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """The texts' bytes, a line break after each, and where each starts (one more entry than texts)."""
    ends = np.cumsum(np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts)))
    whole = b"\n".join([*texts, b""])
    return np.frombuffer(lower(whole) if lowered else whole, np.uint8), np.concatenate(([0], ends)).astype(np.int64)


def words_of(raw: np.ndarray, begins: np.ndarray) -> tuple[Spans, np.ndarray]:
    """The words of ``joined`` texts, without Python objects, and where each begins in them."""
    inside = ~_IS_BLANK[raw]
    edge = np.flatnonzero(np.diff(inside.view(np.int8), prepend=np.int8(0)))  # a text ends in a blank: starts and ends in turn
    first, past = edge[::2], edge[1::2]
    return Spans(raw[inside], np.cumsum(past - first), np.searchsorted(first, begins)), first


def lines_of(raw: np.ndarray, begins: np.ndarray) -> tuple[Spans, np.ndarray]:
    """The lines of ``joined`` texts, with their breaks, and where each begins in them."""
    stops = np.flatnonzero(raw == ord("\n")) + 1
    first = np.concatenate(([0], stops[:-1])) if len(stops) else stops
    return Spans(raw, stops, np.searchsorted(first, begins)), first


def sums(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Sum of the values of each text (0 for an empty one)."""
    total = np.zeros(len(values) + 1, values.dtype if values.dtype.kind == "f" else np.int64)
    np.cumsum(values, out=total[1:])
    return total[starts[1:]] - total[starts[:-1]]
