import numpy as np
import pytest
from pyspark.sql import functions as F

from bitsort.operators import build, measure, query, roworder, theory
from bitsort.operators import dictionary as D
from bitsort.sources import tables as S


def words_of(spark, rows, cols, **kw):
    return build.build_index(S.literal(spark, rows, cols), cols, **kw)


def test_one_hot(spark):
    index = words_of(spark, [(1,), (2,), (1,), (1,), (0,), (0,)], ["pet"], allocation="numeric", row_order="natural")
    assert sorted(r["n"] for r in index.words.groupBy("bitmap").agg(F.sum(F.bit_count("bits")).alias("n")).collect()) == [1, 2, 3]


def test_row_numbers_are_gapless(spark, sf):
    df, cols = S.fixture(spark, sf, "line4")
    for how in ("lex", "shuffle", "cluster", "blocks", "freq_lex", "rarest_first"):
        out = roworder.order_rows(df, how, cols, **({"blocks": 5} if how == "blocks" else {}))
        r = out.agg(F.count("*"), F.min("row_id"), F.max("row_id"), F.countDistinct("row_id")).first()
        assert r[0] == df.count() == r[2] + 1 == r[3] and r[1] == 0, how


def letters(spark, how):
    df = S.literal(spark, [(ord(c),) for c in "afcccadeaceabe"], ["c"])
    return "".join(chr(r["c"]) for r in roworder.order_rows(df, how, ["c"]).orderBy("row_id").collect())


def test_letters(spark):
    assert letters(spark, "lex") == "aaaabccccdeeef"
    assert letters(spark, "freq_lex") == "bdfeeeaaaacccc"  # ascending counts; the printed example has the frequent ones first


def test_components_first(spark):
    cat, dog, blue, red, green = 1, 2, 1, 2, 3
    rows = [(cat, blue), (cat, red), (dog, green), (cat, green)]
    got = roworder.order_rows(S.literal(spark, rows, ["a", "b"]), "rarest_first", ["a", "b"]).orderBy("row_id").collect()
    assert [tuple(r)[:2] for r in got][0] == (dog, green) or (got[0]["a"], got[0]["b"]) == (dog, green)


@pytest.mark.parametrize("k", [1, 2])
def test_alternating_allocation_equals_key_sort(spark, sf, k):
    df, _ = S.fixture(spark, sf, "line3")
    cols = ["ln", "disc"]
    a = build.build_index(df, cols, k, "reflected_alternating", "lex")
    b = build.build_index(df, cols, k, "reflected_alternating", "reflected")
    sizes = [measure.total_sizes(x).first()["compressed"] for x in (a, b)]
    assert sizes[0] == sizes[1]


def test_sorting_and_allocation_shape(spark, sf):
    df, _ = S.fixture(spark, sf, "line4")
    cols = ["part", "ship", "disc", "ln"]
    size = lambda k, a, how: measure.total_sizes(build.build_index(df, cols, k, a, how)).first()["compressed"]
    assert size(1, "numeric", "lex") < size(1, "numeric", "shuffle")
    assert size(2, "reflected", "lex") <= size(2, "numeric", "lex") <= size(2, "random", "lex")


def test_shuffled_single_column_saves_by_sorting(spark):
    df = S.uniform(spark, [200], 20_000)
    cost = lambda how, **o: measure.total_sizes(build.build_index(df, ["c1"], 1, "numeric", how, **o)).first()["storage_cost"]
    saved, model = cost("natural", natural=["place"]) - cost("lex"), theory.saving_model(20_000, 200)
    assert 0.9 * model < saved < 1.1 * model


def test_blocks_cut_words(spark, sf):
    df, _ = S.fixture(spark, sf, "line4")
    one = build.build_index(df, ["disc", "ln"], 1, "numeric", "lex", 32)
    many = build.build_index(df, ["disc", "ln"], 1, "numeric", "lex", 32, block_rows=1024)
    assert many.blocks.count() == -(-df.count() // 1024)
    assert measure.total_sizes(many).first()["dirty"] >= 0
    p = query.eq("disc", 5) & ~query.eq("ln", 2)
    assert query.count(one, p).first()[0] == query.count(many, p).first()[0] == df.filter("disc = 5 and ln <> 2").count()


def test_write_read_append(spark, sf, tmp_path):
    df, _ = S.fixture(spark, sf, "line3")
    index = build.build_index(df, ["ln", "disc"], 1, "numeric", "lex", 32)
    build.write_index(index, str(tmp_path))
    back = build.read_index(spark, str(tmp_path), ["ln", "disc"])
    assert query.count(back, query.eq("ln", 3)).first()[0] == df.filter("ln = 3").count()
    more = build.append_blocks(index, df.limit(100))
    assert more.blocks.count() == 2
    assert query.count(more, query.between("ln", 0, 99)).first()[0] == df.count() + 100


def test_driver_side_orders():
    rows = np.array([[1, 0, 0, 1], [1, 0, 1, 0], [1, 1, 0, 0], [0, 1, 0, 1], [0, 1, 1, 0], [0, 0, 1, 1]])
    best, _ = roworder.best_order_exhaustive(rows)
    order = roworder.tour_order(rows)
    assert best <= roworder.hamming(rows[order]) <= 2 * best
    assert roworder.hamming(rows[roworder.two_switch(rows, 500)]) <= roworder.hamming(rows)
    dense = np.random.default_rng(0).integers(0, 2, (30, 6))
    from bitsort.operators.codes import reflected_less

    sorted_rows = dense[roworder.uncompressed_reorder(dense)].tolist()
    assert not any(reflected_less(b, a) for a, b in zip(sorted_rows, sorted_rows[1:], strict=False))


def test_theory():
    assert theory.query_cost_ratio(100, 2) == pytest.approx(15) and theory.query_cost_ratio(100, 2, "bound") == pytest.approx(90)
    assert theory.best_cardinality(100_000, 32, 1) == 1245 and theory.best_cardinality(100_000, 32, 2) == 13393
    assert theory.best_cardinality(100_000, 32, 1, "numeric") == 870 and theory.best_cardinality(100_000, 32, 2, "numeric") == 7141  # exact rational arithmetic gives the same
    assert theory.column_order([91, 1240, 1478, 99800], "density", 1) == [0, 1, 2, 3]
    assert theory.column_order([91, 1240, 1478, 99800], "density", 2) == [2, 1, 0, 3]
    assert theory.column_order([7, 11, 2526, 400000], "density", 1) == [1, 0, 2, 3]
    assert theory.dirty_tradeoff(15, 45, 2) == {"unary": 15, "k_of_n": 10, "run_switch": 4}
    assert D.range_cover(3, 27, 10, 2) == [(0, i) for i in range(3, 10)] + [(1, 1)] + [(0, i) for i in range(20, 28)]


def test_nulls_and_empty(spark):
    df = spark.createDataFrame([(1,), (None,), (1,)], "a long")
    index = build.build_index(df, ["a"], 1, "numeric", "lex")
    assert index.dictionary.count() == 2
    assert index.words.agg(F.sum(F.bit_count("bits"))).first()[0] == 3


def test_stemmer():
    from bitsort.functions.registered import stem

    known = {"caresses": "caress", "ponies": "poni", "cats": "cat", "agreed": "agre", "plastered": "plaster", "motoring": "motor", "hopping": "hop", "relational": "relat", "happy": "happi", "adjustment": "adjust"}
    assert {w: stem(w) for w in known} == known


def test_streamed_index_equals_batch(spark, sf, tmp_path):
    from bitsort.streaming import events as E

    source = str(tmp_path / "in")
    S.table(spark, sf, "events").repartition(2).write.parquet(source)
    E.append_index(E.event_stream(spark, source), ["user_id"], str(tmp_path / "ix"), str(tmp_path / "cp")).awaitTermination()
    words = spark.read.parquet(str(tmp_path / "ix" / "words"))
    want = {r["user_id"]: r["count"] for r in S.table(spark, sf, "events").groupBy("user_id").count().collect()}
    assert {r["bitmap"]: r["n"] for r in words.groupBy("bitmap").agg(F.sum(F.bit_count("bits")).alias("n")).collect()} == want
    whole = E.compact(spark, str(tmp_path / "ix"), ["user_id"])
    assert {r["bitmap"]: r["n"] for r in whole.groupBy("bitmap").agg(F.sum(F.bit_count("bits")).alias("n")).collect()} == want


def test_size_path_stays_native(spark, sf):
    df, cols = S.fixture(spark, sf, "line4")
    plan = measure.total_sizes(build.build_index(df, cols, 1, "numeric", "lex"))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "CartesianProduct" not in plan and "BroadcastNestedLoop" not in plan


def test_chunks_leave_sizes_alone(spark, sf, monkeypatch):
    """Runs over the borders of chunks are put together again; so are combinations."""
    from bitsort.operators import aggregate, measure, query
    from bitsort.sources import tables

    df, _ = tables.fixture(spark, sf, "line3")
    for how, w in (("lex", 64), ("shuffle", 16)):
        index = build.build_index(df, ["disc", "ln", "part"], 1, "numeric", how, w)
        whole = sorted(tuple(r) for r in measure.attribute_sizes(index).collect())
        answers = {s: sorted((r["block"], r["word_no"], r["bits"]) for r in aggregate.combine(query.column_words(index, query.between("disc", 0, 4), query.selected(index, query.between("disc", 0, 4)).select(F.explode("code").alias("bitmap"))).withColumn("attr", F.lit(0)), index.blocks, "or", s, w).collect()) for s in ("scan", "heap")}
        for size in (3,):
            monkeypatch.setattr(measure, "CHUNK_WORDS", size)
            assert sorted(tuple(r) for r in measure.attribute_sizes(index).collect()) == whole, (how, w, size)
        monkeypatch.setattr(measure, "CHUNK_WORDS", 1 << 16)
        assert answers["scan"] == answers["heap"]
        monkeypatch.setattr(aggregate, "CHUNK_WORDS", 5)
        some = aggregate.combine(query.column_words(index, query.between("disc", 0, 4), query.selected(index, query.between("disc", 0, 4)).select(F.explode("code").alias("bitmap"))).withColumn("attr", F.lit(0)), index.blocks, "or", "heap", w)
        assert sorted((r["block"], r["word_no"], r["bits"]) for r in some.collect()) == answers["heap"]
        monkeypatch.setattr(aggregate, "CHUNK_WORDS", 1 << 16)


def test_typed_columns_and_appended_values(spark):
    import datetime
    from decimal import Decimal

    from bitsort.operators import query

    day = datetime.date(2020, 1, 1)
    rows = [(["ash", "birch", "cedar", None][i % 4], [0.25, 0.75, 1.5, -2.0, float("inf")][i % 5], day + datetime.timedelta(days=i % 9), Decimal(i % 7) / 4, i % 3) for i in range(500)]
    schema = "tree string, x double, day date, dec decimal(10,2), n int"
    for k in (1, 2):
        index = build.build_index(spark.createDataFrame(rows, schema), ["tree", "x", "day", "dec", "n"], k)
        count = lambda p: query.count(index, p).first()[0]
        assert count(query.eq("tree", "birch")) == 125 and count(query.eq("x", 0.25)) == 100 and count(query.between("x", 0.0, 1.0)) == 200
        assert count(query.between("day", day, day + datetime.timedelta(days=2))) == sum(i % 9 < 3 for i in range(500))
        assert count(query.eq("dec", Decimal("0.75")) & query.isin("n", (0, 2))) == sum(i % 7 == 3 and i % 3 != 1 for i in range(500))
        found = query.matching_rows(index, query.eq("tree", "ash") & query.eq("x", 1.5)).select("tree", "x", "n").collect()
        assert sorted(tuple(r) for r in found) == sorted((t, x, n) for t, x, _, _, n in rows if t == "ash" and x == 1.5)
        more = [("yew", 9.5, day, Decimal(1), 9), ("ash", 0.25, day, Decimal("100.25"), 1), (None, 0.3, None, Decimal(1), 9)]
        index = build.append_blocks(index, spark.createDataFrame(more, schema))
        assert count(query.eq("n", 9)) == 2 and count(query.eq("tree", "yew")) == 1 and count(query.eq("tree", "ash")) == 126
        assert count(query.between("x", 0.2, 0.4)) == 102 and count(query.between("dec", Decimal(50), Decimal(200))) == 1 and index.rows.count() == 503
    skipped = build.build_index(spark.createDataFrame(rows, schema), ["tree", "n"], 1, nulls="skip")
    assert query.count(skipped, query.isin("tree", ("ash", "birch", "cedar"))).first()[0] == 375
    assert skipped.words.filter("attr = 0").agg(F.sum(F.bit_count("bits"))).first()[0] == 375


def test_code_hamming_cost(spark):
    """Bits that change between neighbours, against the codes themselves."""
    from bitsort.operators import measure

    rows = [(i * 7 % 13, i * i % 5) for i in range(203)]
    for w in (16, 32, 64):
        for k in (1, 2):
            index = build.build_index(spark.createDataFrame(rows, "a long, b long"), ["a", "b"], k, w=w, row_order="shuffle")
            code = {(r["attr"], r["value"]): set(r["code"]) for r in index.dictionary.collect()}
            ordered = [tuple(r) for r in index.rows.orderBy("row_id").select("a", "b").collect()]
            want = {a: sum(len(code[(a, x[a])] ^ code[(a, y[a])]) for x, y in zip(ordered, ordered[1:], strict=False)) for a in (0, 1)}
            assert {r["attr"]: r["changes"] for r in measure.code_hamming_cost(index).collect()} == want


def test_spans_leave_sizes_alone_and_deal_once(spark, sf, monkeypatch):
    """Words dealt by spans: the same sizes and answers, and no shuffle of words."""
    df, _ = S.fixture(spark, sf, "line3")
    cols = ["disc", "ln", "part"]
    for how, k in (("lex", 1), ("shuffle", 2)):
        whole = build.build_index(df, cols, k, "reflected", how)
        sizes, p = sorted(tuple(r) for r in measure.attribute_sizes(whole).collect()), query.between("part", 10, 60) & query.between("disc", 0, 4)
        with monkeypatch.context() as m:
            m.setattr(build, "SPAN_WORDS", 2)
            m.setattr(build, "SPANS_A_PARTITION", 20)
            cut = build.build_index(df, cols, k, "reflected", how)
        assert "span" in cut.words.columns and cut.words.select("span").distinct().count() > 60
        assert sorted(tuple(r) for r in measure.attribute_sizes(cut).collect()) == sizes
        assert query.count(cut, p).first()[0] == query.count(whole, p).first()[0] == df.filter("part between 10 and 60 and disc between 0 and 4").count()
        plan = cut.words._jdf.queryExecution().executedPlan().toString()
        assert plan.count("Exchange hashpartitioning") == 1 and "hashpartitioning(span" in plan


def test_whole_codes_grow_with_rows_only(spark):
    """A value's bitmaps serve many others; the answer's pieces are as many as the rows."""
    df = spark.range(2000).select((F.col("id") * 7 % 400).alias("a"))
    for k in (2, 3, 4):
        index = build.build_index(df, ["a"], k)
        pieces = query.coded_bits(index.words, k, index.w)
        assert pieces.count() == 2000 and pieces.agg(F.sum(F.bit_count("bits"))).first()[0] == 2000
        assert query.count(index, query.between("a", 50, 349)).first()[0] == 1500


def test_studies_leave_no_tables(spark, sf, tmp_path, monkeypatch):
    """What a task of a study stores goes with it; shuffle files go with the action."""
    from bitsort.plans import recovery

    monkeypatch.setattr(recovery, "shared_folder", lambda spark: f"{tmp_path}/{recovery.uuid.uuid4().hex}")
    df, _ = S.fixture(spark, sf, "line3")
    before = spark.conf.get(recovery.CLEANUP, "false")
    out = recovery.together(spark, [lambda k=k: measure.total_sizes(build.build_index(df, ["disc", "ln"], k)).select("compressed") for k in (1, 2)])
    assert out.count() == 2 and not any(tmp_path.iterdir()) and spark.conf.get(recovery.CLEANUP, "false") == before
    build.build_index(df, ["disc"])
    assert any(tmp_path.iterdir())


@pytest.mark.parametrize("name", ["best_cardinalities", "bitmap_counts", "code_dirty_probability", "code_long_run_probability", "code_neighbour_distances", "code_run_lengths", "component_counts", "measured_savings", "minimal_bitmaps", "query_cost_model", "saving_curve", "synthetic_skewed_orders_k1"])
def test_closed_forms_read_given_tables(spark, tmp_path, name):
    """Without tables there is nothing to answer from."""
    from pyspark.errors import AnalysisException

    from bitsort.plans import workloads

    with pytest.raises(AnalysisException):
        workloads.queries()[name](spark, str(tmp_path))


def test_batches_are_answered_where_words_lie(spark, monkeypatch):
    """Many queries, some that leave columns free, on codes of one and several bitmaps and on row-id lists; words dealt by spans are not shuffled again."""
    rows = [(i * 7 % 90, i * i % 11) for i in range(3000)]
    df, asked = S.literal(spark, rows, ["a", "b"]), {}
    for q in range(70):
        asked[q] = [(0, q, q + 9)] + ([(1, q % 5, q % 5 + 3)] if q % 3 else [])
    asked |= {70: [(0, 5000, 6000)], 71: [(1, 2, 2)]}
    queries = S.literal(spark, [(q, a, lo, hi) for q, parts in asked.items() for a, lo, hi in parts], ["qid", "attr", "lo", "hi"]).withColumn("attr", F.col("attr").cast("int"))
    want = {q: sum(all(lo <= r[a] <= hi for a, lo, hi in parts) for r in rows) for q, parts in asked.items()}
    monkeypatch.setattr(build, "SPAN_WORDS", 8)
    monkeypatch.setattr(build, "SPANS_A_PARTITION", 2)
    base = build.build_index(df, ["a", "b"], 1)
    for k, w in ((1, 32), (1, 64), (2, 32), (3, 64)):
        index = build.recoded(base, k, w)
        assert "span" in index.words.columns
        out = query.batch_counts(index, queries)
        assert {r["qid"]: r["rows"] for r in out.collect()} == want, (k, w)
        plan = out._jdf.queryExecution().executedPlan().toString()
        assert not any("Exchange" in x and "word_no" in x for x in plan.splitlines()), (k, w)
    assert {r["qid"]: r["rows"] for r in query.batch_postings(query.postings(base.rows, base.cols), queries).collect()} == want


@pytest.mark.parametrize("k", [1, 3])
def test_orders_of_one_table_are_sorted_once(spark, monkeypatch, k):
    """Several orders, by value and by reflected codes, as blocks of one index: one sort of rows, the sizes of an index each."""
    cols = ["a", "b", "c"]
    df = S.literal(spark, [(None if i % 37 == 0 else i * 7 % 190, i * i % 11, i % 5) for i in range(3001)], cols)
    plain = build.build_index(df, cols, k, "reflected", "shuffle")
    by_value, want = [["a", "b", "c"], ["c", "a", "b"]], []
    for order in by_value:
        want.append(build.build_index(df, order, k, "reflected", "lex"))
    for how in ("IF", "SF"):
        placed = roworder.bitmap_positions(plain.dictionary, plain.words, 3001, how)
        want.append(build.build_index(df, cols, k, "reflected", "reflected", bitmap_order=placed))
    want = {i: measure.total_sizes(x).first()["compressed"] for i, x in enumerate(want)}
    ranked, sorts, own = D.ranked_rows(df, cols), [], roworder.counted_rows
    monkeypatch.setattr(build, "SPAN_WORDS", 16)
    monkeypatch.setattr(roworder, "counted_rows", lambda *args, **options: sorts.append(args) or own(*args, **options))
    known = D.ranked_dictionary(ranked, k)
    orders = by_value + [roworder.bitmap_positions(known, None, 3001, how) for how in ("IF", "SF")]
    index = build.build_orders(ranked, orders, known, k)
    assert len(sorts) == 1 and "span" in index.words.columns
    assert {r["block"]: r["compressed"] for r in measure.block_totals(index).collect()} == want


def test_packed_numbers_sort_as_they_do():
    bits = [20, 12, 40, 3]
    assert roworder.layout(bits) == [(0, 12), (0, 0), (1, 3), (1, 0)] and build.even_names(7, 3) == build.even_names(6, 3) + build.even_names(7, 3)[6:]


@pytest.mark.parametrize("order", ["value", "frequency"])
def test_ranks_of_large_columns_follow_their_order(spark, monkeypatch, order):
    """Beyond the values that one window takes ranks come from sorted files, which are read in an order of their sizes."""
    monkeypatch.setattr(D, "BROADCAST_VALUES", 10)
    rows = [(0, i if i < 3000 else i * i * 7919, 1 + i % 3) for i in range(4000)] + [(1, -i * i, 1) for i in range(500)] + [(1, None, 2)]
    hist = spark.createDataFrame(rows, "attr int, value long, cnt long")
    got = {(r["attr"], r["value"]): r["rank"] for r in D.ranked(hist, order).collect()}
    for a in (0, 1):
        own = sorted((r for r in rows if r[0] == a), key=lambda r: ((r[2] if order == "frequency" else 0), r[1] is not None, r[1] or 0))
        assert [got[(a, r[1])] for r in own] == list(range(len(own)))


def test_numbered_grams_leave_no_texts(spark, sf, tmp_path, monkeypatch):
    """Of all that numbering the grams stores only the numbers stay."""
    from bitsort.plans import recovery

    monkeypatch.setattr(recovery, "shared_folder", lambda spark: f"{tmp_path}/{recovery.uuid.uuid4().hex}")
    df, cols = S.fixture(spark, sf, "gram4")
    assert len(list(tmp_path.iterdir())) == 1 and df.count() == S.word_grams(spark, sf).count()


def test_batches_give_row_ids(spark, monkeypatch):
    """Row ids of many queries from bitmaps of codes of one and several bitmaps, from row-id lists and from the rows, against brute force."""
    rows = [(i * 7 % 90, i * i % 11) for i in range(3000)]
    df = S.literal(spark, rows, ["a", "b"])
    asked = {q: [(0, q, q + 9)] + ([(1, q % 5, q % 5 + 3)] if q % 3 else []) for q in range(66)} | {66: [(0, 5000, 6000)], 67: [(0, 1, 2), (0, 80, 85), (1, 2, 2)]}
    queries = S.literal(spark, [(q, a, lo, hi) for q, parts in asked.items() for a, lo, hi in parts], ["qid", "attr", "lo", "hi"]).withColumn("attr", F.col("attr").cast("int"))
    monkeypatch.setattr(build, "SPAN_WORDS", 8)
    base = build.build_index(df, ["a", "b"], 1)
    placed = [(r["row_id"], (r["a"], r["b"])) for r in base.rows.collect()]
    want = sorted((q, i) for q, parts in asked.items() for i, r in placed if all(any(lo <= r[a] <= hi for x, lo, hi in parts if x == a) for a in {a for a, _, _ in parts}))
    ids = lambda out: sorted((r["qid"], r["row_id"]) for r in out.collect())
    for k, w in ((1, 32), (1, 64), (2, 32), (3, 64)):
        assert ids(query.batch_row_ids(build.recoded(base, k, w), queries)) == want, (k, w)
    lists = query.postings(base.rows, base.cols)
    assert ids(query.batch_postings_ids(lists, queries)) == want and ids(query.batch_scan(base.rows, base.cols, queries)) == want
    entries = {r["qid"]: r["entries"] for r in query.batch_postings_load(lists, queries).collect()}
    assert entries == {q: n for q, parts in asked.items() if (n := sum(lo <= r[a] <= hi for a, lo, hi in parts for _, r in placed))}


def test_range_times_make_row_ids(spark, sf, monkeypatch):
    """Whole answers are row ids by every method; lists are loaded alone too, a scan stands beside them, and all building counts the sort."""
    from bitsort.plans import workloads

    made, own = [], workloads._row_id_seconds
    monkeypatch.setattr(workloads, "_row_id_seconds", lambda f: made.append(f().columns) or own(f))
    out = workloads.queries()["range_times"](spark, sf).collect()
    assert made == [["qid", "row_id"]] * 20  # a warm-up and the boxes for each of five methods and two orders
    assert [(r["method"], r["w"], r["k"]) for r in out] == [("bitmaps", 32, 1), ("bitmaps", 64, 1), ("bitmaps", 32, 2), ("row_ids", 0, 1), ("scan", 0, 0)] * 2
    assert all(r["load_s"] > 0 and r["total_s"] > 0 and r["build_s"] >= s["build_s"] for r, s in zip(out, [out[4]] * 5 + [out[9]] * 5, strict=True))


def test_allocations_sort_once_an_order(spark, monkeypatch):
    """Three sorts for 24 indexes; sizes are those of indexes that are built one by one."""
    from bitsort.plans import workloads

    cols = workloads.SORTED_BY["line4"]
    df = S.literal(spark, [(i * i % 97, i * 7 % 31, i % 11, i % 3) for i in range(2000)], cols)
    sorts, own, together = [], roworder.counted_rows, workloads.together
    monkeypatch.setattr(S, "fixture", lambda *_: (df, cols))
    monkeypatch.setattr(workloads, "together", lambda spark, tasks, n: together(spark, [tasks[i] for i in (0, 7, 9, 16, 17, 18, 23)], n))
    with monkeypatch.context() as m:
        m.setattr(roworder, "counted_rows", lambda *args, **options: sorts.append(args) or own(*args, **options))
        got = {(r["k"], r["method"]): r["compressed"] for r in workloads.queries()["allocations_line4"](spark, "").collect()}
    assert len(sorts) == 3
    asked = {(1, "unsorted"): ("numeric", "shuffle"), (2, "random"): ("random", "lex"), (2, "reflected"): ("reflected", "lex"), (3, "reflected_alternating"): ("reflected_alternating", "lex"), (3, "freq_reflected"): ("freq_reflected", "freq_lex"), (4, "unsorted"): ("numeric", "shuffle"), (4, "freq_reflected"): ("freq_reflected", "freq_lex")}
    assert got == {(k, m): measure.total_sizes(build.build_index(df, cols, k, a, how, 32)).first()["compressed"] for (k, m), (a, how) in asked.items()}


def test_equality_times_load_once(spark, monkeypatch):
    """The words that queries load are those of the timed load; it runs once for each column, k and order."""
    from bitsort.plans import workloads

    cols = workloads.SORTED_BY["line4"]
    df = S.literal(spark, [(i * i % 17, i * 7 % 31, i % 11, i % 3) for i in range(500)], cols)
    loads, own = [], query.batch_load
    monkeypatch.setattr(S, "fixture", lambda *_: (df, cols))
    monkeypatch.setattr(query, "batch_load", lambda *args: loads.append(args) or own(*args))
    out = workloads.queries()["equality_times"](spark, "").collect()
    assert len(loads) == len(out) == 32 and {(r["col"], r["k"], r["row_order"]) for r in out} == {(c, k, how) for c in cols for k in (1, 2, 3, 4) for how in ("lex", "shuffle")}
    index, asked = loads[0]
    assert out[0]["words"] == round(own(index, asked).agg(F.avg("words")).first()[0], 3) and all(r["measured_words_ratio"] == 1 for r in out if r["k"] == 1)
