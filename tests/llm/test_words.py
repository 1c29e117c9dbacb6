import numpy as np
import pyarrow as pa

from ranksort.llm import words


def test_pieces_cover_all_texts():
    texts = pa.array([None, "", "a b", "é" * 100, None, "x" * 5000, "z"])
    for size in (1, 50, 10**6):
        assert [t for some in words.pieces(texts, size) for t in some] == [(t or "").encode() for t in texts.to_pylist()]
    assert [t for some in words.pieces(texts.slice(2, 3), 10) for t in some] == [b"a b", ("é" * 100).encode(), b""]
    assert list(words.pieces(pa.array([], pa.string()))) == []


def test_numbers_and_sums():
    spans, first = words.words_of(*words.joined([b"a b\x0b a", b"", b" \n", b"C"], lowered=True))
    ids, distinct = spans.numbers()
    starts = spans.starts
    assert ids.tolist() == [0, 1, 0, 2] and starts.tolist() == [0, 3, 3, 3, 4] and distinct.to_pylist() == [b"a", b"b", b"c"] and first.tolist() == [0, 2, 5, 11]
    lines, _ = words.lines_of(*words.joined([b"x\ny", b"", b"x\n"]))
    assert lines.numbers()[0].tolist() == [0, 1, 2, 0, 2] and lines.starts.tolist() == [0, 2, 3, 5]
    empty, _ = words.words_of(*words.joined([]))
    assert empty.starts.tolist() == [0] and len(empty.numbers()[0]) == 0
    assert words.sums(np.array([1.5, 2.0, 0.5, 4.0]), starts).tolist() == [4.0, 0.0, 0.0, 4.0]
    assert words.lower("ÀB z\x1c".encode()) == "Àb z\x1c".encode()
