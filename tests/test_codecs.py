import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from bitsort.operators import aggregate as A
from bitsort.operators import codecs as K
from bitsort.operators.measure import HYBRID31, MARKER, marker_codec

run_lists = st.lists(st.tuples(st.integers(0, 1), st.integers(1, 90)), min_size=1, max_size=12)


def bits_of(runs):
    return np.concatenate([np.full(n, b, dtype=np.int8) for b, n in runs])


@settings(max_examples=60, deadline=None)
@given(run_lists)
def test_round_trips(runs):
    bits = bits_of(runs)
    for codec in (MARKER[16], MARKER[32], MARKER[64], marker_codec(16, 12), marker_codec(16, 4, extend=True)):
        words = K.pack_bits(bits, codec.w)
        stream = K.encode_marker(words, len(bits), codec)
        assert np.array_equal(K.decode_marker(stream, len(bits), codec), words)
        assert np.array_equal(K.unpack_bits(words, codec.w, len(bits)), bits)
    words = K.pack_bits(bits, 31)
    assert np.array_equal(K.decode_hybrid(K.encode_hybrid(words, len(bits)), len(bits)), words)
    assert np.array_equal(K.decode_bytewise(K.encode_bytewise(bits), len(bits)), bits)


def test_worked_run_lengths():
    assert K.run_length_text(np.array([1, 1, 1, 1, 0, 0, 0, 0])) == "4140"
    assert K.escaped_text("1011110000") == "10114004"
    assert [K.gamma_bits(x) for x in (1, 2, 4, 9)] == [1, 3, 5, 7]


def test_hybrid_single_bit():
    bits = np.zeros(62, dtype=np.int8)
    bits[31] = 1
    stream = K.encode_hybrid(K.pack_bits(bits, 31), 62)
    assert stream.tolist() == [1 << 31 | 1, 1]


def test_expansion_is_small():
    bits = np.random.default_rng(1).integers(0, 2, 32 * 40_000).astype(np.int8)
    words = K.pack_bits(bits, 32)
    assert len(K.encode_marker(words, len(bits), MARKER[32])) <= len(words) * 1.001
    assert len(K.encode_hybrid(K.pack_bits(bits, 31), len(bits), HYBRID31)) <= len(words) * 1.04


@settings(max_examples=40, deadline=None)
@given(st.lists(st.lists(st.integers(0, 1), min_size=70, max_size=70), min_size=1, max_size=6), st.sampled_from(["and", "or", "xor"]))
def test_strategies_agree(rows, op):
    bitmaps = [np.array(r, dtype=np.int8) for r in rows]
    want = {"and": np.bitwise_and, "or": np.bitwise_or, "xor": np.bitwise_xor}[op].reduce(bitmaps)
    runs = [A.to_runs(b) for b in bitmaps]
    for s in A.STRATEGIES:
        work = A.Work()
        assert np.array_equal(A.from_runs(A.combine_runs(runs, op, s, 70, work), 70), want), s
        assert len(A.combine_runs(runs, op, s, 70)) <= sum(map(len, runs))


@pytest.mark.parametrize("op,t", [("at_least", 2), ("exactly", 1), ("majority", 0), ("all_equal", 0), ("nand", 0), ("nor", 0), ("xnor", 0)])
def test_symmetric_functions(op, t):
    rng = np.random.default_rng(3)
    bitmaps = [rng.integers(0, 2, 200).astype(np.int8) for _ in range(5)]
    flip = [True, False, False, True, False]
    ones = sum(b ^ f for b, f in zip(bitmaps, flip, strict=True))
    test = A.symmetric_test(op, 5, t)
    got = A.heap_runs([A.to_runs(b) for b in bitmaps], op, t, flip)
    assert np.array_equal(A.from_runs(got, 200), np.array([test(int(x)) for x in ones]))
    f = A.scan_runs([A.to_runs(b) for b in bitmaps], lambda v: int(v[0] and not v[1] or v[2]))
    assert np.array_equal(A.from_runs(f, 200), (bitmaps[0] & (1 - bitmaps[1])) | bitmaps[2])


def test_skipping_and_choice():
    dense, sparse = np.full(1000, 5, dtype=np.uint64), np.zeros(1000, dtype=np.uint64)
    sparse[7] = 1
    assert K.words_touched_and(dense, sparse, 32_000, 32, True) < 5 < K.words_touched_and(dense, sparse, 32_000, 32, False)
    assert A.choose_strategy("or", [1] * 50, 10**6, 0.001) == "in_place" and A.choose_strategy("xor", [1, 2], 10, 0.5) == "pairwise"


def test_sparse_encoding_equals_dense():
    """Streams from non-zero words alone, many bitmaps at once, are those of the dense encoders; long bitmaps cost nothing."""
    rng = np.random.default_rng(3)
    for codec, encode in ((MARKER[16], K.encode_marker), (marker_codec(16, 12), K.encode_marker), (marker_codec(16, None, True), K.encode_marker), (MARKER[32], K.encode_marker), (MARKER[64], K.encode_marker), (HYBRID31, K.encode_hybrid)):
        w, parts, want = codec.w, [], []
        for g in range(60):
            rows = int(rng.integers(1, 9000))
            total = -(-rows // w)
            full = K.full_words(total, w, rows)
            kinds = np.repeat(rng.integers(0, 3, total), rng.integers(1, 400, total))[:total]
            bits = np.where(kinds == 0, 0, np.where(kinds == 1, full, np.minimum(rng.integers(1, 1000, total).astype(np.uint64), full))).astype(np.uint64)
            bits[rng.integers(0, total)] = 1
            at = np.flatnonzero(bits)
            parts.append((np.full(len(at), g), at, bits[at], np.full(len(at), total), np.full(len(at), rows - (total - 1) * w)))
            want.append(encode(bits, rows, codec))
        stream, lengths = K.encode_sparse(*(np.concatenate(x) for x in zip(*parts, strict=True)), codec)
        assert np.array_equal(stream, np.concatenate(want)) and lengths.tolist() == [len(x) for x in want]
    one = np.ones(1, dtype=np.int64)
    stream, lengths = K.encode_sparse(one * 0, one * 5, one.astype(np.uint64), one * (1 << 40), one * 64, MARKER[64])
    assert len(stream) == lengths[0] == 258 and stream[1] == 1


def test_streams_take_no_more_than_their_words():
    """Long bitmaps of few words: memory follows the streams, and streams are made so many words at once."""
    import tracemalloc

    n, codec = 500, MARKER[16]
    words = (np.arange(2 * n) // 2, np.tile([7, 900_000], n), np.full(2 * n, 5, dtype=np.uint64), np.full(2 * n, 1 << 20), np.full(2 * n, 16))
    tracemalloc.start()
    stream, lengths = K.encode_sparse(*words, codec)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    dense = np.zeros(1 << 20, dtype=np.uint64)
    dense[[7, 900_000]] = 5
    assert np.array_equal(stream[: lengths[0]], K.encode_marker(dense, 16 << 20, codec)) and peak < 3 * stream.nbytes
    cuts = K.stream_cuts(np.arange(0, 2 * n, 2), 2 * n, np.full(n, 1 << 28), codec)
    assert cuts[0] == 0 and cuts[-1] == n and (np.diff(cuts)[:-1] == K.STREAMED // ((1 << 28) // 255 + 10)).all()
    alone = K.stream_cuts(np.arange(3), 3, np.full(3, 1 << 40), codec)
    assert alone.tolist() == [0, 1, 2, 3]
