from itertools import combinations
from math import comb

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitsort.operators import codes as C


def dense(code, n):
    return [int(p in code) for p in range(1, n + 1)]


def text(code, n):
    return "".join(map(str, dense(code, n)))


def test_reflected_two_of_four():
    assert [text(c, 4) for c in C.code_list(4, 2)] == ["0011", "0110", "0101", "1100", "1010", "1001"]


def test_exchanged_ends():
    got = [text(c, 4) for c in C.code_list(4, 2, permute=[4, 2, 3, 1])]
    assert got == ["1010", "0110", "1100", "0101", "0011", "1001"]


def test_numeric_is_binary_order():
    for n, k in ((6, 2), (7, 3), (9, 4)):
        values = [int(text(c, n), 2) for c in C.code_list(n, k, scheme="numeric")]
        assert values == sorted(values) and len(set(values)) == comb(n, k)


@pytest.mark.parametrize("n,k", [(7, 2), (7, 3), (8, 4)])
def test_reflected_orders_agree(n, k):
    codes = C.code_list(n, k)
    for a, b in zip(codes, codes[1:], strict=False):
        assert len(set(a) ^ set(b)) == 2
        assert C.reflected_less(dense(a, n), dense(b, n)) and C.reflected_less_sparse(a, b)
        assert not C.reflected_less_sparse(b, a)
    key = lambda c: [-p if i % 2 == 0 else p for i, p in enumerate(c)]
    assert codes == sorted(codes, key=key)


def test_sparse_comparator_on_any_weights():
    every = [c for w in range(6) for c in combinations(range(1, 6), w)]
    for a in every:
        for b in every:
            assert C.reflected_less_sparse(a, b) == C.reflected_less(dense(a, 5), dense(b, 5))


def test_descending_is_the_reverse():
    assert C.code_list(7, 3, descending=True) == C.code_list(7, 3)[::-1]


def test_caps_and_counts():
    assert [C.cap_k(n, 4) for n in (4, 5, 20, 21, 84, 85)] == [1, 2, 2, 3, 3, 4]
    assert C.min_bitmaps(2_000_000, 2) == 2001 and C.sufficient_bitmaps(2_000_000, 2) == 2829
    for n in range(1, 400):
        for k in (1, 2, 3, 4):
            m = C.min_bitmaps(n, k)
            assert comb(m, k) >= n and (m == k or comb(m - 1, k) < n) and m <= max(k, C.sufficient_bitmaps(n, k))
            counts = C.compare_bitmap_counts(n, k)
            assert counts["k_of_n"] <= max(counts["components"], k)


def test_weight_adjacent_and_long_run_lists_are_complete():
    for scheme in ("weight_adjacent", "long_run", "random"):
        assert sorted(C.code_list(8, 2, None, scheme)) == sorted(combinations(range(1, 9), 2))


def test_walks_are_gray_codes():
    for n in range(2, 11):
        for walk in (list(C._level_walk(n)), list(C._long_run_walk(n))):
            assert len(set(walk)) == len(walk) == 2**n
            assert all(len(set(a) ^ set(b)) == 1 for a, b in zip(walk, walk[1:], strict=False))
        weights = [len(c) for c in C._level_walk(n)]
        assert all(w >= max(weights[:i], default=0) - 1 for i, w in enumerate(weights))
        first, last = list(C._long_run_walk(n))[0], list(C._long_run_walk(n))[-1]
        assert len(set(first) ^ set(last)) == 1
    for n, k in ((8, 2), (8, 3)):
        own = C.code_list(n, k, None, "weight_adjacent")
        assert all(len(set(a) ^ set(b)) == 2 for a, b in zip(own, own[1:], strict=False))
        assert own not in (C.code_list(n, k), C.code_list(n, k)[::-1], C.code_list(n, k, None, "numeric"))


def shortest_run(walk, n):
    runs = []
    for bit in range(1, n + 1):
        flips = [i for i in range(len(walk)) if (bit in walk[i]) != (bit in walk[i - 1])]
        runs += [(b - a) % len(walk) for a, b in zip(flips, flips[1:] + flips[:1], strict=True)]
    return min(runs)


def test_long_runs_are_longer():
    assert shortest_run([set(c) for c in C._long_run_walk(8)], 8) > shortest_run([set(c) for c in C._binary_reflected(8)], 8)


def test_random_codes_do_not_step_evenly():
    for total in (28, 1140, 1001):
        own = C.keyed_permutation(np.arange(total), total, 3)
        assert sorted(own.tolist()) == list(range(total)) and len(set(np.diff(own).tolist())) > total // 4
        assert own.tolist() != C.keyed_permutation(np.arange(total), total, 4).tolist()


def test_permuted_and_padded_codes(spark):
    from bitsort.operators import build, dictionary, measure, query

    df = spark.createDataFrame([(i % 11, i % 3) for i in range(300)], "a long, b long")
    turned = dictionary.build_dictionary(df, ["a", "b"], 2, permute={0: [5, 4, 3, 2, 1, 6]})
    plain = dictionary.build_dictionary(df, ["a", "b"], 2)
    code = lambda d: {(r["attr"], r["value"]): tuple(r["code"]) for r in d.collect()}
    turn = {1: 5, 2: 4, 3: 3, 4: 2, 5: 1, 6: 6}
    assert {k: tuple(sorted(turn[p] for p in c)) if k[0] == 0 else c for k, c in code(plain).items()} == code(turned)
    for policy in ("minimal", "padded"):
        index = build.build_index(df, ["a", "b"], 2, n_policy=policy)
        assert query.count(index, query.eq("a", 4)).first()[0] == sum(i % 11 == 4 for i in range(300))
        assert measure.total_sizes(index).first()["compressed"] > 0


def test_run_lengths_of_two_of_eight(spark):
    from bitsort.operators import measure

    hist = {(r["name"], r["len"]): r["count"] for r in measure.run_histogram(C.code_frame(spark, C.code_list(8, 2, None, "numeric"), 8, "n").unionByName(C.code_frame(spark, C.code_list(8, 2), 8, "g"))).collect()}
    assert hist[("n", 1)] == 32
    assert max(length for (name, length) in hist if name == "g") == 21


def test_coded_ranks_match_the_list(spark):
    rows = {r["rank"]: tuple(r["code"]) for r in C.coded(spark.range(35).withColumnRenamed("id", "rank"), "rank", 35, 3).collect()}
    assert [rows[i] for i in range(35)] == C.code_list(C.min_bitmaps(35, 3), 3, 35)
    assert np.array_equal(C.unrank(np.arange(35), 7, 3, "reflected"), np.array(C.code_list(7, 3)))


def test_random_codes_are_distinct(spark):
    got = C.coded(spark.range(200).withColumnRenamed("id", "rank"), "rank", 200, 2, "random").select(F.col("code").cast("string")).distinct().count()
    assert got == 200
