"""The published experiments on the given tables, as queries, each with its SQL twin where SQL can say it.

Everything runs over whole tables.  Sizes come from the closed formula, so no payload is made.
"""

from __future__ import annotations

import datetime
import time
from collections.abc import Callable
from functools import reduce
from itertools import permutations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitsort.operators import aggregate, build, codecs, codes, dictionary, measure, query, relational, roworder, theory
from bitsort.plans import oracles as O
from bitsort.plans.recovery import checkpointed, shared_folder, stored, tidy, together
from bitsort.sources import tables as S
from bitsort.streaming import events as stream_events

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
TOTALS = ["bitmaps", "dirty", "clean_runs", "storage_cost", "markers", "compressed", "overruns", "clean_share", "overrun_share"]
#: Sort orders: by descending cardinality ("4321"); for the event table "3214".
SORTED_BY = {"line4": ["part", "ship", "disc", "ln"], "line3": ["part", "disc", "ln"], "event4": ["usr", "hour", "k", "val"], "rating4": ["part", "cust", "day", "prio"], "rating3": ["part", "day", "prio"], "corr3": ["day", "ship", "status"], "gram4": ["w1", "w2", "w3", "w4"]}


def query_of(name: str, oracle: str | None = None):
    def add(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def tagged(df: DataFrame, **tags) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in tags.items()], *df.columns)


def frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def _totals(spark: SparkSession, sf_dir: str, name: str, how: str = "lex", w: int = 32, k: int = 1, allocation: str = "numeric", codec: measure.Codec | None = None, cols: list[str] | None = None, **options) -> DataFrame:
    df, own = S.fixture(spark, sf_dir, name)
    index = build.build_index(df, cols or SORTED_BY.get(name, own), k, allocation, how, w, **options)
    return measure.total_sizes(index, codec).select(*TOTALS)


def _size_query(name: str, fixture: str, how: str = "lex", w: int = 32, codec: measure.Codec | None = None, cols: list[str] | None = None, **oracle) -> None:
    order = cols or SORTED_BY[fixture]
    if fixture in O.FIXTURE_SQL:
        ORACLES[name] = O.totals_sql(O.numbered_sql(O.FIXTURE_SQL[fixture], order, how), order, w, **oracle)
    QUERIES[name] = lambda spark, sf_dir: _totals(spark, sf_dir, fixture, how, w, 1, "numeric", codec, order)


# --- sizes: sorted and shuffled, word lengths, codecs, blocks ------------------------------------
for _f in ("line4", "line3", "event4", "rating4", "corr3", "gram4"):
    _size_query(f"size_{_f}_sorted_w32", _f)
    _size_query(f"size_{_f}_shuffled_w32", _f, "shuffle")
for _w in (16, 64):
    for _h, _n in (("lex", "sorted"), ("shuffle", "shuffled")):
        _size_query(f"size_line4_{_n}_w{_w}", "line4", _h, _w)
        _size_query(f"size_event4_{_n}_w{_w}", "event4", _h, _w)
_size_query("size_line4_sorted_hybrid31", "line4", "lex", 31, measure.HYBRID31, markers=False)
_size_query("size_line4_shuffled_hybrid31", "line4", "shuffle", 31, measure.HYBRID31, markers=False)
_size_query("size_line4_sorted_more_clean_bits", "line4", "lex", 16, measure.marker_codec(16, 10), clean_bits=10)
_size_query("size_line4_freq_lex", "line4", "freq_lex")


def _blocks(b: int):
    df_cols = SORTED_BY["line3"]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df, _ = S.fixture(spark, sf_dir, "line3")
        return tagged(measure.total_sizes(build.build_index(df, df_cols, 1, "numeric", "blocks", 32, blocks=b)).select(*TOTALS), blocks=b)

    return run


for _b in (1, 5, 10, 500):
    QUERIES[f"block_sort_{_b}"] = _blocks(_b)
    ORACLES[f"block_sort_{_b}"] = O.totals_sql(O.numbered_sql(O.FIXTURE_SQL["line3"], SORTED_BY["line3"], "blocks", _b), SORTED_BY["line3"], 32, f"{_b}::INT AS blocks,")

_LINE10 = [c for c in S.FIXTURES["line10"][1]]


def _per_column(order: list[str], how: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df, _ = S.fixture(spark, sf_dir, "line10")
        index = build.build_index(df, order, 1, "numeric", how, 32)
        return measure.attribute_sizes(index).select("attr", "bitmaps", "dirty", "clean_runs", "compressed")

    return run


for _n, _o, _h in (("ascending", _LINE10, "lex"), ("descending", _LINE10[::-1], "lex"), ("unsorted", _LINE10, "shuffle")):
    QUERIES[f"words_per_column_{_n}"] = _per_column(_o, _h)
    ORACLES[f"words_per_column_{_n}"] = O.attributes_sql(O.numbered_sql(O.FIXTURE_SQL["line10"], _o, _h), _o, 32)


# --- data sets, histograms, dictionaries ---------------------------------------------------------
def _characteristics(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df, cols = S.fixture(spark, sf_dir, name)
        return df.agg(F.count(F.lit(1)).alias("row_count"), *[F.count_distinct(c).alias(f"_{c}") for c in cols]).select(F.lit(name).alias("fixture"), "row_count", F.lit(len(cols)).alias("cols"), reduce(lambda a, b: a + b, [F.col(f"_{c}") for c in cols]).alias("sum_card"))

    return run


for _f in O.FIXTURE_SQL:
    _c = S.FIXTURES[_f][1]
    QUERIES[f"characteristics_{_f}"] = _characteristics(_f)
    ORACLES[f"characteristics_{_f}"] = f"SELECT '{_f}' AS fixture, count(*) AS row_count, {len(_c)}::INT AS cols, {' + '.join(f'count(DISTINCT {c})' for c in _c)} AS sum_card FROM ({O.FIXTURE_SQL[_f]})"


@query_of("histogram_line4", f"WITH t AS ({O.FIXTURE_SQL['line4']}) " + " UNION ALL ".join(f"SELECT {i}::INT AS attr, {c} AS value, count(*) AS cnt FROM t GROUP BY ALL" for i, c in enumerate(S.FIXTURES["line4"][1])))
def histogram_line4(spark, sf_dir):
    return dictionary.histograms(*S.fixture(spark, sf_dir, "line4"))


@query_of("histogram_grouping_sets", "SELECT CASE WHEN grouping(l_returnflag)=0 THEN 'l_returnflag' WHEN grouping(l_linestatus)=0 THEN 'l_linestatus' ELSE 'all' END AS col, coalesce(l_returnflag, l_linestatus) AS value, count(*) AS cnt FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def histogram_grouping_sets(spark, sf_dir):
    return relational.histograms_by_sets(S.table(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linestatus"])


def _ranks(order: str):
    def run(spark, sf_dir):
        df, _ = S.fixture(spark, sf_dir, "line4")
        return dictionary.ranked(dictionary.histograms(df, ["part", "ship"]), order).select("attr", "value", "cnt", "rank")

    return run


for _n, _k in (("value", "value"), ("frequency", "cnt, value")):
    QUERIES[f"dictionary_{_n}_ranks"] = _ranks(_n)
    ORACLES[f"dictionary_{_n}_ranks"] = f"WITH t AS ({O.FIXTURE_SQL['line4']}), h AS (SELECT 0::INT AS attr, part AS value, count(*) AS cnt FROM t GROUP BY ALL UNION ALL SELECT 1::INT, ship, count(*) FROM t GROUP BY ALL) SELECT attr, value, cnt, row_number() OVER (PARTITION BY attr ORDER BY {_k}) - 1 AS rank FROM h"


#: Columns of the orders and the numbers of their values, for the closed forms.
_ORDERS = {"status": "o_orderstatus", "priority": "o_orderpriority", "day": "o_orderdate", "customer": "o_custkey"}


def _given(spark: SparkSession, sf_dir: str, *names: str) -> list[int]:
    """How many orders there are, and distinct numbers of values of the named columns (all where none is), ascending."""
    own = S.table(spark, sf_dir, "orders").select("o_orderkey", *[(F.to_date(c) if n == "day" else F.col(c)).alias(n) for n, c in _ORDERS.items()])
    h = own.agg(F.count("o_orderkey").alias("n"), *[F.count_distinct(n).alias(n) for n in names or _ORDERS]).first()
    return [h["n"], *sorted({h[n] for n in names or _ORDERS})]


def _given_sql(*names: str) -> str:
    """The numbers of values as a table n(n)."""
    return " UNION ".join(f"SELECT count(DISTINCT {_ORDERS[n]}{'::DATE' if n == 'day' else ''})::BIGINT AS n FROM orders" for n in names or _ORDERS)


@query_of("bitmap_counts", f"SELECT n::INT AS n, k, ceil(k * pow(n, 1.0 / k) - 1e-9)::BIGINT AS enough FROM ({_given_sql()}), (SELECT unnest([1, 2, 3, 4]) AS k)")
def bitmap_counts(spark, sf_dir):
    rows = [(n, k, codes.sufficient_bitmaps(n, k)) for n in _given(spark, sf_dir)[1:] for k in (1, 2, 3, 4)]
    return frame(spark, rows, "n int, k int, enough long")


_FEW = ("status", "priority", "day")


@query_of("minimal_bitmaps", f"WITH n AS ({_given_sql(*_FEW)}), c AS (SELECT b, b AS c1, b*(b-1)//2 AS c2, b*(b-1)*(b-2)//6 AS c3 FROM (SELECT unnest(range(1, 1 + (SELECT max(n) FROM n)))::BIGINT AS b)) SELECT n, min(b) FILTER (c1 >= n) AS k1, min(b) FILTER (c2 >= n) AS k2, min(b) FILTER (c3 >= n) AS k3 FROM c, n WHERE n > 4 GROUP BY n")
def minimal_bitmaps(spark, sf_dir):
    return frame(spark, [(n, *(codes.min_bitmaps(n, k) for k in (1, 2, 3))) for n in _given(spark, sf_dir, *_FEW)[1:] if n > 4], "n long, k1 long, k2 long, k3 long")


@query_of("component_counts")
def component_counts(spark, sf_dir):
    rows = [(n, k, *codes.compare_bitmap_counts(n, k).values(), str(codes.balanced_radices(n, k))) for n in _given(spark, sf_dir)[1:] for k in (1, 2, 3, 4)]
    return frame(spark, rows, "n long, kappa long, k_of_n long, components long, radices string")


@query_of("component_encoding", f"WITH t AS ({O.FIXTURE_SQL['line4']}), d AS (SELECT part, row_number() OVER (ORDER BY part) - 1 AS r FROM (SELECT DISTINCT part FROM t)) SELECT r % 45 AS d0, (r // 45) % 45 AS d1, count(*) AS row_count FROM t JOIN d USING (part) GROUP BY ALL")
def component_encoding(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    return dictionary.encode_components(df, "part", [45, 45]).groupBy(F.col("part_d0").alias("d0"), F.col("part_d1").alias("d1")).agg(F.count(F.lit(1)).alias("row_count"))


@query_of("equi_width_bins", "WITH v AS (SELECT value, min(value) OVER () AS lo, max(value) OVER () AS hi FROM events) SELECT least(floor((value - lo) / ((hi - lo) / 16)), 15)::BIGINT AS bin, count(*) AS row_count FROM v GROUP BY ALL")
def equi_width_bins(spark, sf_dir):
    return dictionary.bin_attribute(S.table(spark, sf_dir, "events"), "value", 16).groupBy(F.col("value_bin").alias("bin")).agg(F.count(F.lit(1)).alias("row_count"))


@query_of("hierarchical_bins", f"WITH t AS ({O.FIXTURE_SQL['line4']}), d AS (SELECT part, row_number() OVER (ORDER BY part) - 1 AS r FROM (SELECT DISTINCT part FROM t)) SELECT r // 10 AS bin_1, r // 100 AS bin_2, count(*)::BIGINT AS n FROM d GROUP BY ALL")
def hierarchical_bins(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    ranks = dictionary.ranked(dictionary.histograms(df, ["part"]))
    return dictionary.hierarchical_bins(ranks, 10, 2).groupBy("bin_1", "bin_2").agg(F.count(F.lit(1)).alias("n"))


@query_of("zipf_frequencies", "WITH z AS (SELECT unnest(range(1, 101)) AS rank) SELECT rank, round(100000 / rank / (SELECT sum(1.0 / rank) FROM z), 6)::DOUBLE AS freq FROM z")
def zipf_frequencies(spark, sf_dir):
    total = sum(1 / j for j in range(1, 101))
    return spark.range(1, 101).select(F.col("id").alias("rank"), F.round(F.lit(100000.0) / F.col("id") / F.lit(total), 6).alias("freq"))


# --- allocations, column orders, row orders ------------------------------------------------------
def _allocations(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Rows are sorted once for each of three orders; the codes of every k and allocation are laid over them."""
        df, own = S.fixture(spark, sf_dir, name)
        df, cols, out = stored(df), SORTED_BY[name], []
        ordered = {how: build.build_index(df, cols, 1, "numeric", how, 32) for how in ("shuffle", "lex", "freq_lex")}
        for k in (1, 2, 3, 4):
            for allocation, how in (("numeric", "shuffle"), ("random", "lex"), ("numeric", "lex"), ("reflected", "lex"), ("reflected_alternating", "lex"), ("freq_reflected", "freq_lex")):
                label = "unsorted" if how == "shuffle" else allocation
                out.append(lambda k=k, allocation=allocation, how=how, label=label: tagged(measure.total_sizes(build.recoded(ordered[how], k, 32, allocation)).select("compressed"), fixture=name, k=k, method=label))
        n = ordered["lex"].n_rows
        return measure.size_ratio(together(spark, out, n), "unsorted", ["fixture", "k"])

    return run


for _f in ("line4", "event4", "rating4"):
    QUERIES[f"allocations_{_f}"] = _allocations(_f)


@query_of("rarest_first_order")
def rarest_first_order(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "event4")
    df, cols = checkpointed(df), SORTED_BY["event4"]
    return together(spark, [lambda k=k, t=t: tagged(measure.total_sizes(build.build_index(df, cols, k, "reflected", "rarest_first", 32, ties=t)).select("compressed"), k=k, ties=t) for k in (1, 2, 3, 4) for t in ("freq_vector", "pairwise")])


#: Orders of one table are sorted and measured together up to so many rows in all; larger tables one order at a time.
ORDERED_ROWS = 8_000_000


def _ordered(ranked: dictionary.Ranked, n: int, known: DataFrame, k: int, orders: dict[str, list[str] | DataFrame]) -> list[Callable[[], DataFrame]]:
    """Tasks that give (order, compressed) of orders of the same rows."""
    names, most = list(orders), max(1, ORDERED_ROWS // max(n, 1))

    def sizes(own: list[str]) -> DataFrame:
        index = build.build_orders(ranked, [orders[o] for o in own], known, k)
        called = F.element_at(F.array(*[F.lit(o) for o in own]), F.col("block").cast("int") + 1)
        return measure.block_totals(index).select(called.alias("order"), "compressed")

    return [lambda own=names[i : i + most]: sizes(own) for i in range(0, len(names), most)]


def _column_orders(name: str, k: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ranked = dictionary.ranked_rows(*S.fixture(spark, sf_dir, name))
        n, cols, known = ranked.rows.count(), ranked.cols, dictionary.ranked_dictionary(ranked, k)
        orders = {"".join(str(i + 1) for i in p): [cols[i] for i in p] for p in permutations(range(len(cols)))}
        picked = "".join(str(i + 1) for i in theory.column_order(ranked.cards, "density", k))
        sizes = together(spark, _ordered(ranked, n, known, k, orders), n)
        return sizes.select(F.col("order").alias("columns"), F.lit(k).alias("k"), (F.col("order") == picked).alias("picked"), "compressed")

    return run


QUERIES["column_orders_line3_k1"] = _column_orders("line3", 1)
QUERIES["column_orders_line3_k2"] = _column_orders("line3", 2)
for _f in ("line4", "event4"):
    QUERIES[f"column_orders_{_f}_k1"] = _column_orders(_f, 1)
QUERIES["column_orders_line4_k2"] = _column_orders("line4", 2)
for _p in permutations(range(3)):
    _o = [S.FIXTURES["line3"][1][i] for i in _p]
    _size_query("column_order_line3_" + "".join(str(i + 1) for i in _p), "line3", cols=_o)


@query_of("equivalent_reflected_order")
def equivalent_reflected_order(spark, sf_dir):
    """Alternating codes with rows sorted by value, and with rows sorted by their codes' keys: equal sizes."""
    df, _ = S.fixture(spark, sf_dir, "line3")
    df, cols = checkpointed(df), ["ln", "disc", "part"]
    out = []
    for k in (1, 2):
        cheap = build.build_index(df, cols, k, "reflected_alternating", "lex", 32)
        direct = build.build_index(df, cols, k, "reflected_alternating", "reflected", 32)
        out += [tagged(measure.total_sizes(x).select("compressed"), k=k, method=m) for m, x in (("alternating", cheap), ("keys", direct))]
    return union(out)


def _bitmap_permutations(name: str, ks: tuple[int, ...]):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Rows sorted by the reflected order of all bitmaps, these in several orders, beside the picked column order."""
        ranked, out = dictionary.ranked_rows(*S.fixture(spark, sf_dir, name)), []
        n, cols = ranked.rows.count(), ranked.cols

        def sizes(k: int, known: DataFrame) -> list[Callable[[], DataFrame]]:
            orders = {"column_order": [cols[i] for i in theory.column_order(ranked.cards, "density", k)]}
            orders |= {how: roworder.bitmap_positions(known, None, n, how) for how in ("IF", "MSF", "SF", "interleaved", "natural")}
            tasks = _ordered(ranked, n, known, k, orders)
            return [lambda t=t: t().select(F.lit(name).alias("fixture"), F.lit(k).alias("k"), F.col("order").alias("method"), "compressed") for t in tasks]

        for k in ks:
            out += sizes(k, dictionary.ranked_dictionary(ranked, k))
        return measure.size_ratio(together(spark, out, n), "column_order", ["fixture", "k"])

    return run


QUERIES["bitmap_permutations"] = _bitmap_permutations("line3", (1, 2))
QUERIES["bitmap_permutations_line4"] = _bitmap_permutations("line4", (1, 2, 3, 4))


@query_of("component_allocations")
def component_allocations(spark, sf_dir):
    """Columns as mixed-radix digits, one unary attribute each, under the allocations; beside k-of-N codes."""
    df, _ = S.fixture(spark, sf_dir, "line3")
    df, cols, out = checkpointed(df), ["part", "disc", "ln"], []
    for kappa in (1, 2, 3):
        own, digits = df, []
        for c, n in zip(cols, dictionary.cardinalities(df, cols), strict=True):
            radices = codes.balanced_radices(n, codes.cap_k(n, kappa))
            own = dictionary.encode_components(own, c, radices)
            digits += [f"{c}_d{i}" for i in reversed(range(len(radices)))]
        own = checkpointed(own.select(*cols, *digits))
        for allocation in ("numeric", "reflected_alternating", "reflected"):
            out.append(lambda own=own, digits=digits, allocation=allocation, kappa=kappa: tagged(measure.total_sizes(build.build_index(own, digits, 1, allocation, "lex", 32)).select("bitmaps", "compressed"), kappa=kappa, encoding="components", allocation=allocation))
        out.append(lambda own=own, kappa=kappa: tagged(measure.total_sizes(build.build_index(own, cols, kappa, "reflected", "lex", 32)).select("bitmaps", "compressed"), kappa=kappa, encoding="k_of_n", allocation="reflected"))
    return together(spark, out)


@query_of("measured_savings")
def measured_savings(spark, sf_dir):
    """Storage cost saved by sorting a single column of the events, against a random order of rows, beside the model's figure."""
    df, cols = S.event4(spark, sf_dir, "event_id"), S.FIXTURES["event4"][1]
    df = stored(df.withColumn("place", F.xxhash64("event_id")))
    n, cards = df.count(), dictionary.cardinalities(df, cols)

    def saved(name: str, c: int, k: int) -> DataFrame:
        cost = [measure.total_sizes(build.build_index(df, [name], k, "reflected", how, 32, **options)).select(F.col("storage_cost").alias(how)) for how, options in (("natural", {"natural": ["place", "event_id"]}), ("lex", {}))]
        return cost[0].join(cost[1]).select(F.lit(c).alias("card"), F.lit(k).alias("k"), (F.col("natural") - F.col("lex")).alias("saving"), F.lit(round(theory.saving_model(n, c, codes.cap_k(c, k)), 3)).alias("model"))

    return together(spark, [lambda name=name, c=c, k=k: saved(name, c, k) for name, c in zip(cols, cards, strict=True) for k in (1, 2)], n)


# --- synthetic studies ---------------------------------------------------------------------------
def _synthetic_orders(make: Callable[[SparkSession, str], DataFrame], k: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """All 24 column orders."""
        df = stored(make(spark, sf_dir))
        return together(spark, [lambda p=p: tagged(measure.total_sizes(build.build_index(df, [f"c{i}" for i in p], k, "reflected", "lex", 32)).select("compressed"), columns="".join(map(str, p)), k=k) for p in permutations((1, 2, 3, 4))], df.count())

    return run


for _k in (1, 2):
    QUERIES[f"synthetic_uniform_orders_k{_k}"] = _synthetic_orders(lambda spark, sf_dir: S.uniform(spark, [200, 400, 600, 800]), _k)
    QUERIES[f"synthetic_skewed_orders_k{_k}"] = _synthetic_orders(S.skewed4, _k)


def _zipf_dimensions(k: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = []
        for d in (1, 2, 3, 4, 5, 6):
            df = checkpointed(S.zipf(spark, [1.0] * d))
            cols = [f"c{i + 1}" for i in range(d)]
            for method, allocation, how, options in (("shuffled", "numeric", "natural", {"natural": ["place"]}), ("numeric", "numeric", "lex", {}), ("reflected", "reflected", "lex", {})):
                out.append(lambda df=df, cols=cols, allocation=allocation, how=how, options=options, d=d, method=method: tagged(measure.total_sizes(build.build_index(df, cols, k, allocation, how, 32, **options)).select("compressed"), d=d, k=k, method=method))
        return measure.size_ratio(together(spark, out), "shuffled", ["d", "k"])

    return run


for _k in (1, 2, 3, 4):
    QUERIES[f"zipf_dimensions_k{_k}"] = _zipf_dimensions(_k)


def _growth(how: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Sizes of ten growing parts of the shuffled table, sorted or not."""
        df, cols = S.fixture(spark, sf_dir, "gram4")
        numbered = roworder.order_rows(df, "shuffle", cols)
        n = numbered.count()
        return together(spark, [lambda f=f: tagged(measure.total_sizes(build.build_index(numbered.filter(F.col("row_id") < n * f // 100).select(*cols), cols, 1, "numeric", how, 32)).select("compressed"), percent=f, row_order=how) for f in range(10, 101, 10)], n)

    return run


def _growth_sql(how: str) -> str:
    cols, parts = SORTED_BY["gram4"], []
    shuffled = f"SELECT *, count(*) OVER () AS n FROM ({O.numbered_sql(O.FIXTURE_SQL['gram4'], cols, 'shuffle')})"
    for f in range(10, 101, 10):
        own = f"SELECT {', '.join(cols)} FROM ({shuffled}) WHERE rid < n * {f} // 100"
        parts.append(f"SELECT {f}::INT AS percent, '{how}' AS row_order, compressed FROM ({O.totals_sql(O.numbered_sql(own, cols, how), cols)})")
    return " UNION ALL ".join(parts)


for _h, _n in (("lex", "sorted"), ("shuffle", "shuffled")):
    QUERIES[f"growth_gram4_{_n}"] = _growth(_h)
    ORACLES[f"growth_gram4_{_n}"] = _growth_sql(_h)


@query_of("saving_curve", f"WITH r AS (SELECT count(*)::DOUBLE AS r FROM orders), c AS (SELECT n AS card FROM ({_given_sql()})), p AS (SELECT unnest([1, 2]) AS k), x AS (SELECT card, k, r, ceil(k * pow(card, 1.0 / k) - 1e-9) AS b FROM c, p, r) SELECT k::INT AS k, card::INT AS card, round(2 * (1 - pow(1 - k * r / (b * r), 32)) * b * r / 32 - 4.0 * card, 3)::DOUBLE AS saving FROM x")
def saving_curve(spark, sf_dir):
    n, *cards = _given(spark, sf_dir)
    return frame(spark, [(k, c, round(theory.saving_model(n, c, k), 3)) for k in (1, 2) for c in cards], "k int, card int, saving double")


@query_of("best_cardinalities")
def best_cardinalities(spark, sf_dir):
    """For a table of as many rows as there are customers."""
    n = S.table(spark, sf_dir, "customer").agg(F.count_distinct("c_custkey")).first()[0]
    return frame(spark, [(k, how, theory.best_cardinality(n, 32, k, how)) for k in (1, 2) for how in ("closed", "numeric")], "k int, how string, card long")


def _codes_of(spark: SparkSession, sf_dir: str) -> dict[int, tuple[int, int]]:
    """For k = 2, 3 and 4: the bits of as short codes as can be, and the values that take them, of the events' keys (k = 2) and hours."""
    df, _ = S.fixture(spark, sf_dir, "event4")
    keys, hours = dictionary.cardinalities(df, ["k", "hour"])
    return {k: (codes.min_bitmaps(n, k), n) for k, n in ((2, keys), (3, hours), (4, hours))}


@query_of("code_run_lengths")
def code_run_lengths(spark, sf_dir):
    frames = []
    for k, (bits, n) in _codes_of(spark, sf_dir).items():
        for s in ("numeric", "reflected", "random", *(("long_run", "weight_adjacent") if k == 2 else ())):
            frames.append(codes.code_frame(spark, codes.code_list(bits, k, n, s), bits, f"{k}-of-{bits} {s}"))
    return measure.run_histogram(union(frames))


@query_of("code_long_run_probability")
def code_long_run_probability(spark, sf_dir):
    bits, n = _codes_of(spark, sf_dir)[2]
    return measure.long_run_probability(union([codes.code_frame(spark, codes.code_list(bits, 2, n, s), bits, f"2-of-{bits} {s}") for s in ("numeric", "reflected", "random")]))


@query_of("code_dirty_probability")
def code_dirty_probability(spark, sf_dir):
    rows = []
    for k, (bits, n) in _codes_of(spark, sf_dir).items():
        for s in ("numeric", "reflected", "random") if k > 2 else ():
            own = codes.code_list(bits, k, n, s)
            rows += [(f"{k}-of-{bits}", s, j, measure.dirty_probability(own, bits, j)) for j in (2, 4, 8, 16, 32)]
    return frame(spark, rows, "codes string, scheme string, j int, prob double")


@query_of("code_neighbour_distances")
def code_neighbour_distances(spark, sf_dir):
    rows, (bits, n) = [], _codes_of(spark, sf_dir)[2]
    for s in ("numeric", "reflected", "random", "weight_adjacent"):
        d = measure.code_distances(codes.code_list(bits, 2, n, s), 4)
        rows.append((s, int(d["neighbour_max"]), int(d["neighbour_sum"]), int(d["cyclic"]), float(d["collective_mean"])))
    return frame(spark, rows, "scheme string, neighbour_max int, neighbour_sum int, cyclic int, collective_mean double")


#: All 2-of-N codes in numeric order, N as small as can be, for the values of ``part``.
_PAIRS = "n AS (SELECT count(DISTINCT part) AS n FROM t), b AS (SELECT min(x) AS b FROM (SELECT unnest(range(2, 2000)) AS x), n WHERE x * (x - 1) // 2 >= n), pairs AS (SELECT i, j, row_number() OVER (ORDER BY i DESC, j DESC) - 1 AS r FROM (SELECT x AS i FROM (SELECT unnest(range(1, 2000)) AS x), b WHERE x <= b) a, (SELECT x AS j FROM (SELECT unnest(range(1, 2000)) AS x), b WHERE x <= b) c WHERE i < j), used AS (SELECT i, j FROM pairs, n WHERE r < n)"


@query_of("values_per_bitmap", f"WITH t AS ({O.FIXTURE_SQL['line4']}), {_PAIRS}, f AS (SELECT bitmap, count(*) AS values FROM (SELECT i AS bitmap FROM used UNION ALL SELECT j FROM used) GROUP BY bitmap) SELECT 0::INT AS attr, count(*)::BIGINT AS bitmaps, max(values)::BIGINT AS most, min(values)::BIGINT AS least, bool_and(values <= b - 1) AS bounded FROM f, b")
def values_per_bitmap(spark, sf_dir):
    """Two-of-N codes: no bitmap serves more than N - 1 values."""
    df, _ = S.fixture(spark, sf_dir, "line4")
    d = dictionary.build_dictionary(df, ["part"], 2, "numeric")
    n_bits = d.agg(F.max("n_bits")).first()[0]
    return codes.values_per_bitmap(d).groupBy("attr").agg(F.count(F.lit(1)).alias("bitmaps"), F.max("values").alias("most"), F.min("values").alias("least"), (F.max("values") <= n_bits - 1).alias("bounded"))


@query_of("query_cost_model", f"SELECT n::INT AS n, k::INT AS k, round((2 - 1.0 / k) * pow(n, (k - 1.0) / k), 6)::DOUBLE AS estimate, round(3 * (2 * k - 1) * pow(n, (k - 1.0) / k), 6)::DOUBLE AS bound FROM ({_given_sql()}), (SELECT unnest([1, 2, 3, 4]) AS k)")
def query_cost_model(spark, sf_dir):
    rows = [(n, k, round(theory.query_cost_ratio(n, k), 6), round(theory.query_cost_ratio(n, k, "bound"), 6)) for n in _given(spark, sf_dir)[1:] for k in (1, 2, 3, 4)]
    return frame(spark, rows, "n int, k int, estimate double, bound double")


# --- measures on an index ------------------------------------------------------------------------
_ORD4 = O.numbered_sql(O.FIXTURE_SQL["line4"], SORTED_BY["line4"], "lex")


@query_of("column_changes", f"WITH o AS ({_ORD4}), " + "l AS (SELECT " + ", ".join(f"CASE WHEN {c} <> lag({c}) OVER (ORDER BY rid) THEN 1 ELSE 0 END AS d{i}" for i, c in enumerate(SORTED_BY["line4"])) + " FROM o) " + " UNION ALL ".join(f"SELECT {i}::INT AS attr, sum(d{i})::BIGINT AS changes, (sum(d{i}) + 1)::BIGINT AS runs FROM l" for i in range(4)))
def column_changes(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    cols = SORTED_BY["line4"]
    return measure.hamming_cost(roworder.order_rows(df, "lex", cols), cols)


@query_of("data_examined_line4", f"WITH {O.per_bitmap_ctes(_ORD4, SORTED_BY['line4'])} SELECT attr::INT AS attr, round(avg(dirty + markers), 6)::DOUBLE AS words FROM per_bitmap GROUP BY attr")
def data_examined_line4(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    return measure.data_examined(build.build_index(df, SORTED_BY["line4"], 1, "numeric", "lex", 32))


@query_of("data_examined_by_k")
def data_examined_by_k(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    df = stored(df)
    return together(spark, [lambda k=k, how=how: tagged(measure.data_examined(build.build_index(df, SORTED_BY["line4"], k, "reflected", how, 32)), k=k, row_order=how) for k in (1, 2, 3) for how in ("lex", "shuffle")], df.count())


@query_of("sorted_bounds", f"WITH {O.per_bitmap_ctes(_ORD4, SORTED_BY['line4'])}, s AS (SELECT attr, sum(dirty)::BIGINT AS dirty FROM per_bitmap GROUP BY attr) SELECT attr::INT AS attr, dirty, dirty <= 2 * CASE attr WHEN 0 THEN n0 WHEN 1 THEN n0 * n1 WHEN 2 THEN n0 * n1 * n2 ELSE n0 * n1 * n2 * n3 END AS holds FROM s, (SELECT count(DISTINCT part)::HUGEINT AS n0, count(DISTINCT ship)::HUGEINT AS n1, count(DISTINCT disc)::HUGEINT AS n2, count(DISTINCT ln)::HUGEINT AS n3 FROM ord)")
def sorted_bounds(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    cols = SORTED_BY["line4"]
    sizes = measure.attribute_sizes(build.build_index(df, cols, 1, "numeric", "lex", 32))
    return measure.sorted_bounds(sizes, dictionary.cardinalities(df, cols)).select("attr", "dirty", "holds")


@query_of("bitmap_densities", f"WITH t AS ({O.FIXTURE_SQL['line4']}) SELECT disc AS value, count(*)::BIGINT AS ones, round(count(*) / (SELECT count(*) FROM t), 9)::DOUBLE AS density FROM t GROUP BY disc")
def bitmap_densities(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    index = build.build_index(df, ["disc"], 1, "numeric", "lex", 32)
    d = index.dictionary.select("value", F.element_at("code", 1).alias("bitmap"))
    return measure.density(index.words, df.count()).join(d, "bitmap").select("value", "ones", F.round("density", 9).alias("density"))


@query_of("naive_builder_agrees", f"WITH t AS ({O.FIXTURE_SQL['line3']}) SELECT count(DISTINCT ln)::BIGINT AS bitmaps, (count(DISTINCT ln) * ((count(*) + 31) // 32))::BIGINT AS words, count(*)::BIGINT AS ones FROM t")
def naive_builder_agrees(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line3")
    index = build.build_index(df, ["ln"], 1, "numeric", "lex", 32)
    dense = build.naive_words(dictionary.attach(index.rows, ["ln"], index.dictionary), ["ln"], index.dictionary)
    return dense.agg(F.count_distinct("bitmap").alias("bitmaps"), F.count(F.lit(1)).alias("words"), F.sum(F.bit_count("bits")).cast("long").alias("ones"))


def _payloads(codec: measure.Codec, w: int):
    def run(spark, sf_dir):
        df, _ = S.fixture(spark, sf_dir, "line4")
        index = build.build_index(df, SORTED_BY["line4"], 1, "numeric", "lex", w)
        p = codecs.encode_payloads(index.words, index.blocks, codec)
        return p.agg(F.count(F.lit(1)).alias("bitmaps"), F.sum("n_words").alias("compressed"), F.sum(F.length("payload")).alias("bytes"))

    return run


for _n, _codec, _w, _m in (("marker32", measure.MARKER[32], 32, True), ("marker64", measure.MARKER[64], 64, True), ("marker16", measure.MARKER[16], 16, True), ("hybrid31", measure.HYBRID31, 31, False)):
    QUERIES[f"payload_{_n}"] = _payloads(_codec, _w)
    _by = {31: 4, 32: 4, 64: 8, 16: 2}[_w]
    ORACLES[f"payload_{_n}"] = f"WITH {O.per_bitmap_ctes(_ORD4, SORTED_BY['line4'], _w, None, _m)} SELECT count(*)::BIGINT AS bitmaps, sum(dirty + markers)::BIGINT AS compressed, (sum(dirty + markers) * {_by})::BIGINT AS bytes FROM per_bitmap"


# --- queries -------------------------------------------------------------------------------------
def _line4_index(spark, sf_dir, k=1, allocation="reflected", how="lex", w=32):
    df, _ = S.fixture(spark, sf_dir, "line4")
    return build.build_index(df, SORTED_BY["line4"], k, allocation, how, w)


def _answer_query(name: str, where: str, pred, **options) -> None:
    ORACLES[name] = f"SELECT count(*)::BIGINT AS rows FROM ({O.FIXTURE_SQL['line4']}) WHERE {where}"
    QUERIES[name] = lambda spark, sf_dir: query.count(_line4_index(spark, sf_dir, **options), pred)


_E, _B, _I = query.eq, query.between, query.isin
_answer_query("eq_count_k1", "disc = 5", _E("disc", 5))
_answer_query("eq_count_k2", "part = 77", _E("part", 77), k=2)
_answer_query("eq_count_k3_shuffled", "part = 77", _E("part", 77), k=3, how="shuffle")
_answer_query("eq_count_k4_freq", "ship = 9000", _E("ship", 9000), k=4, allocation="freq_reflected", how="freq_lex")
_answer_query("in_count", "ln IN (1, 3, 9)", _I("ln", (1, 3, 9)))
_answer_query("range_count_1d", "part BETWEEN 100 AND 199", _B("part", 100, 199))
_answer_query("range_count_4d_w32", "part BETWEEN 1 AND 1000 AND ship BETWEEN 9000 AND 9099 AND disc BETWEEN 2 AND 8 AND ln BETWEEN 1 AND 5", _B("part", 1, 1000) & _B("ship", 9000, 9099) & _B("disc", 2, 8) & _B("ln", 1, 5))
_answer_query("range_count_4d_w64", "part BETWEEN 1 AND 1000 AND ship BETWEEN 9000 AND 9099 AND disc BETWEEN 2 AND 8 AND ln BETWEEN 1 AND 5", _B("part", 1, 1000) & _B("ship", 9000, 9099) & _B("disc", 2, 8) & _B("ln", 1, 5), w=64)
_answer_query("range_count_4d_k2", "part BETWEEN 1 AND 1000 AND ship BETWEEN 9000 AND 9099", _B("part", 1, 1000) & _B("ship", 9000, 9099), k=2)
_answer_query("or_count", "disc = 5 OR ln = 2", _E("disc", 5) | _E("ln", 2))
_answer_query("xor_count", "(disc = 5) <> (ln = 2)", _E("disc", 5) ^ _E("ln", 2))
_answer_query("not_count", "NOT (disc = 5)", ~_E("disc", 5))
_answer_query("andnot_count", "disc = 5 AND NOT ln = 2", query.Pred("andnot", children=(_E("disc", 5), _E("ln", 2))))
_answer_query("nand_count", "NOT (disc = 5 AND ln = 2)", query.Pred("nand", children=(_E("disc", 5), _E("ln", 2))))
_answer_query("nor_count", "NOT (disc = 5 OR ln = 2)", query.Pred("nor", children=(_E("disc", 5), _E("ln", 2))))
_answer_query("xnor_count", "(disc = 5) = (ln = 2)", query.Pred("xnor", children=(_E("disc", 5), _E("ln", 2))))
_answer_query("predicate_tree_count", "(disc BETWEEN 1 AND 3 OR ln = 7) AND NOT part BETWEEN 500 AND 900", (_B("disc", 1, 3) | _E("ln", 7)) & ~_B("part", 500, 900), w=64)

_PREDS = [_E("disc", 5), _B("ln", 1, 3), _B("ship", 9000, 9500)]
_COUNT = "((disc = 5)::INT + (ln BETWEEN 1 AND 3)::INT + (ship BETWEEN 9000 AND 9500)::INT)"
for _n, _t, _sql in (("at_least", 2, f"{_COUNT} >= 2"), ("exactly", 1, f"{_COUNT} = 1"), ("majority", 0, f"2 * {_COUNT} > 3"), ("parity", 0, f"{_COUNT} % 2 = 1"), ("all_equal", 0, f"{_COUNT} IN (0, 3)")):
    ORACLES[f"symmetric_{_n}"] = f"SELECT count(*)::BIGINT AS rows FROM ({O.FIXTURE_SQL['line4']}) WHERE {_sql}"
    QUERIES[f"symmetric_{_n}"] = lambda spark, sf_dir, n=_n, t=_t: query.symmetric_words(_line4_index(spark, sf_dir), _PREDS, n, t).agg(F.coalesce(F.sum(F.bit_count("bits")), F.lit(0)).cast("long").alias("rows"))
ORACLES["symmetric_inverted"] = f"SELECT count(*)::BIGINT AS rows FROM ({O.FIXTURE_SQL['line4']}) WHERE (NOT disc = 5) OR ln BETWEEN 1 AND 3"
QUERIES["symmetric_inverted"] = lambda spark, sf_dir: query.symmetric_words(_line4_index(spark, sf_dir), _PREDS[:2], "at_least", 1, [True, False]).agg(F.sum(F.bit_count("bits")).cast("long").alias("rows"))


@query_of("row_ids_answer", f"SELECT rid AS row_id FROM ({_ORD4}) WHERE disc = 5 AND ln = 2")
def row_ids_answer(spark, sf_dir):
    return query.row_ids(_line4_index(spark, sf_dir, w=64), _E("disc", 5) & _E("ln", 2))


@query_of("matching_rows", f"SELECT part, ship, disc, ln FROM ({O.FIXTURE_SQL['line4']}) WHERE disc = 5 AND part BETWEEN 10 AND 40")
def matching_rows(spark, sf_dir):
    return query.matching_rows(_line4_index(spark, sf_dir), _E("disc", 5) & _B("part", 10, 40)).select("part", "ship", "disc", "ln")


@query_of("counts_by_value", f"SELECT ln AS value, count(*)::BIGINT AS rows FROM ({O.FIXTURE_SQL['line4']}) GROUP BY ln")
def counts_by_value(spark, sf_dir):
    return query.counts_by_value(_line4_index(spark, sf_dir), "ln")


@query_of("load_only", f"WITH o AS ({_ORD4}) SELECT count(*)::BIGINT AS words FROM (SELECT DISTINCT part, rid // 32 FROM o WHERE part BETWEEN 100 AND 199)")
def load_only(spark, sf_dir):
    return query.load_only(_line4_index(spark, sf_dir), _B("part", 100, 199))


@query_of("postings_range", f"SELECT count(*)::BIGINT AS rows FROM ({O.FIXTURE_SQL['line4']}) WHERE part BETWEEN 1 AND 1000 AND ship BETWEEN 9000 AND 9099")
def postings_range(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    rows = roworder.order_rows(df, "lex", SORTED_BY["line4"])
    return query.postings_range(query.postings(rows, SORTED_BY["line4"]), {0: (1, 1000), 1: (9000, 9099)}).agg(F.count(F.lit(1)).alias("rows"))


@query_of("full_scan_range", f"SELECT count(*)::BIGINT AS rows FROM ({O.FIXTURE_SQL['line4']}) WHERE part BETWEEN 1 AND 1000 AND ship BETWEEN 9000 AND 9099")
def full_scan_range(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    return query.full_scan(df, {"part": (1, 1000), "ship": (9000, 9099)}).agg(F.count(F.lit(1)).alias("rows"))


def _strategy(strategy: str, op: str):
    def run(spark, sf_dir):
        index = _line4_index(spark, sf_dir)
        words = index.words.filter((F.col("attr") == 1) & F.col("bitmap").between(100, 149)) if op == "or" else query.value_words(index, _B("disc", 0, 10)).select("block", F.lit(2).alias("attr"), F.lit(0).cast("long").alias("bitmap"), "word_no", "bits")
        done = aggregate.relational(words, op) if strategy == "relational" else aggregate.combine(words, index.blocks, op, strategy, 32)
        return done.agg(F.coalesce(F.sum(F.bit_count("bits")), F.lit(0)).cast("long").alias("rows"))

    return run


#: Bitmaps 100 .. 149 of the ship column are, in value order, the dates of rank n - bitmap.
_SHIPS = f"WITH t AS ({O.FIXTURE_SQL['line4']}), d AS (SELECT ship, row_number() OVER (ORDER BY ship DESC) AS bitmap FROM (SELECT DISTINCT ship FROM t)) SELECT count(*)::BIGINT AS rows FROM t JOIN d USING (ship) WHERE bitmap BETWEEN 100 AND 149"
for _s in (*aggregate.STRATEGIES, "relational"):
    QUERIES[f"combine_or_{_s}"] = _strategy(_s, "or")
    ORACLES[f"combine_or_{_s}"] = _SHIPS


# --- typed and appended values, sizes without compression, work counts -------------------------------
def _orders_index(spark, sf_dir, k=1):
    df = S.table(spark, sf_dir, "orders").select("o_orderpriority", "o_totalprice", F.to_date("o_orderdate").alias("day"), "o_orderstatus")
    return build.build_index(df, ["o_orderstatus", "o_orderpriority", "day", "o_totalprice"], k)


@query_of("typed_string_count", "SELECT count(*)::BIGINT AS rows FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus = 'O'")
def typed_string_count(spark, sf_dir):
    return query.count(_orders_index(spark, sf_dir), _I("o_orderpriority", ("1-URGENT", "2-HIGH")) & _E("o_orderstatus", "O"))


@query_of("typed_double_range", "SELECT count(*)::BIGINT AS rows FROM orders WHERE o_totalprice BETWEEN 1000.5 AND 100000.25")
def typed_double_range(spark, sf_dir):
    return query.count(_orders_index(spark, sf_dir, 2), _B("o_totalprice", 1000.5, 100000.25))


@query_of("typed_date_rows", "SELECT o_orderstatus, o_orderpriority, o_orderdate::DATE AS day, o_totalprice FROM orders WHERE o_orderdate::DATE BETWEEN DATE '1995-03-01' AND DATE '1995-03-31' AND o_orderstatus <> 'O'")
def typed_date_rows(spark, sf_dir):
    march = _B("day", datetime.date(1995, 3, 1), datetime.date(1995, 3, 31))
    return query.matching_rows(_orders_index(spark, sf_dir), march & ~_E("o_orderstatus", "O")).select("o_orderstatus", "o_orderpriority", "day", "o_totalprice")


@query_of("append_unseen_values", f"SELECT part AS value, count(*)::BIGINT AS rows FROM ({O.FIXTURE_SQL['line4']}) GROUP BY part")
def append_unseen_values(spark, sf_dir):
    """Lines of the lower half of the parts first, the others as a second block; counts of every part."""
    df, _ = S.fixture(spark, sf_dir, "line4")
    half = df.agg(F.max("part")).first()[0] // 2
    index = build.append_blocks(build.build_index(df.filter(F.col("part") <= half), ["part", "ln"]), df.filter(F.col("part") > half))
    return query.counts_by_value(index, "part")


@query_of("padded_bitmaps_count", f"SELECT count(*)::BIGINT AS rows FROM ({O.FIXTURE_SQL['line4']}) WHERE ln = 3 AND disc BETWEEN 2 AND 4")
def padded_bitmaps_count(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    return query.count(build.build_index(df, ["disc", "ln"], 3, n_policy="padded"), _E("ln", 3) & _B("disc", 2, 4))


@query_of("uncompressed_size", f"WITH t AS ({O.FIXTURE_SQL['line4']}) " + " UNION ALL ".join(f"SELECT {i}::INT AS attr, count(DISTINCT {c})::BIGINT AS bitmaps, (count(DISTINCT {c}) * ((count(*) + 31) // 32))::BIGINT AS words FROM t" for i, c in enumerate(SORTED_BY["line4"])))
def uncompressed_size(spark, sf_dir):
    return measure.uncompressed_words(_line4_index(spark, sf_dir))


@query_of("code_changes", f"WITH o AS ({_ORD4}), l AS (SELECT " + ", ".join(f"CASE WHEN {c} <> lag({c}) OVER (ORDER BY rid) THEN 2 ELSE 0 END AS d{i}" for i, c in enumerate(SORTED_BY["line4"])) + " FROM o) " + " UNION ALL ".join(f"SELECT {i}::INT AS attr, sum(d{i})::BIGINT AS changes FROM l" for i in range(4)))
def code_changes(spark, sf_dir):
    """Bits that change between neighbouring rows of the sorted index."""
    return measure.code_hamming_cost(_line4_index(spark, sf_dir))


@query_of("combine_work")
def combine_work(spark, sf_dir):
    """Work of every strategy for OR and AND of 2 to 100 bitmaps of the sorted table, and the bound on the answer's size."""
    index = _line4_index(spark, sf_dir)
    index.words = checkpointed(index.words)
    out = []

    def worked(words: DataFrame, sizes: DataFrame, op: str, s: str, n: int) -> DataFrame:
        done = aggregate.combine(words, index.blocks, op, s, 32)
        work = done.agg(F.coalesce(F.sum(F.bit_count("bits")), F.lit(0)).cast("long").alias("rows"), F.count(F.lit(1)).alias("answer_words"), *[F.coalesce(F.max(c), F.lit(0).cast("long")).alias(c) for c in aggregate.COUNTERS])
        return tagged(work.join(sizes), bitmaps=n, op=op, strategy=s, chosen=s == aggregate.choose_strategy(op, [1] * n, 1, n / 2500))

    for n in (2, 10, 50, 100):
        words = checkpointed(index.words.filter((F.col("attr") == 1) & F.col("bitmap").between(100, 99 + n)))
        sizes = measure.bitmap_sizes(words, index.blocks, measure.MARKER[32]).agg(F.sum("compressed").alias("input_words"))
        sizes = checkpointed(sizes)
        for op in ("or", "and", "xor"):
            for s in aggregate.STRATEGIES:
                out.append(lambda words=words, sizes=sizes, op=op, s=s, n=n: worked(words, sizes, op, s, n))
    return together(spark, out)


# --- samples of queries on written indexes -------------------------------------------------------------
#: The sampled values of a column are those with the smallest products of a prime field.
SAMPLED, RANGES = 100, 20


def _sample_sql(c: str) -> str:
    return f"SELECT {c} AS value FROM (SELECT DISTINCT {c} FROM t) ORDER BY ({c} * 48271) % 2147483647, {c} LIMIT {SAMPLED}"


def sampled_values(df: DataFrame, cols: list[str]) -> DataFrame:
    """(qid, attr, lo, hi): up to SAMPLED equality queries of each column."""
    parts = []
    for i, c in enumerate(cols):
        some = df.select(F.col(c).alias("lo")).distinct().orderBy(F.pmod(F.col("lo") * F.lit(48_271), F.lit(2_147_483_647)), "lo").limit(SAMPLED)
        parts.append(some.select((F.lit(i << 40) + F.col("lo")).alias("qid"), F.lit(i).alias("attr"), "lo", F.col("lo").alias("hi")))
    return checkpointed(union(parts))


#: Twenty boxes: from a part, a day, a discount and a line number on, so many values wide.
BOXES = [(1 + 97 * q % 1500, 100, 8100 + 211 * q % 2000, 100, q % 8, 4, 1 + q % 4, 4) for q in range(RANGES)]


def sampled_ranges(spark: SparkSession) -> DataFrame:
    return frame(spark, [(q, a, b[2 * a], b[2 * a] + b[2 * a + 1] - 1) for q, b in enumerate(BOXES) for a in range(4)], "qid long, attr int, lo long, hi long")


@query_of("equality_sample_counts", f"WITH t AS ({O.FIXTURE_SQL['line4']}) " + " UNION ALL ".join(f"SELECT {k}::INT AS k, '{c}' AS col, value, (SELECT count(*) FROM t WHERE {c} = value)::BIGINT AS rows FROM ({_sample_sql(c)})" for k in (1, 2, 3, 4) for c in SORTED_BY["line4"]))
def equality_sample_counts(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    cols = SORTED_BY["line4"]
    asked = sampled_values(df, cols)
    names = F.element_at(F.array(*[F.lit(c) for c in cols]), F.shiftright("qid", 40).cast("int") + 1)
    return union([query.batch_counts(_line4_index(spark, sf_dir, k), asked).select(F.lit(k).alias("k"), names.alias("col"), F.col("qid").bitwiseAND(F.lit((1 << 40) - 1)).alias("value"), "rows") for k in (1, 2, 3, 4)])


_BOX_SQL = " UNION ALL ".join(f"SELECT {q}::BIGINT AS qid, count(*)::BIGINT AS rows FROM t WHERE part BETWEEN {b[0]} AND {b[0] + b[1] - 1} AND ship BETWEEN {b[2]} AND {b[2] + b[3] - 1} AND disc BETWEEN {b[4]} AND {b[4] + b[5] - 1} AND ln BETWEEN {b[6]} AND {b[6] + b[7] - 1}" for q, b in enumerate(BOXES))


@query_of("range_sample_counts", f"WITH t AS ({O.FIXTURE_SQL['line4']}), b AS ({_BOX_SQL}) SELECT method, qid, rows FROM b, (SELECT unnest(['w32', 'w64', 'k2', 'postings']) AS method)")
def range_sample_counts(spark, sf_dir):
    """The rows are sorted once for all methods; each is answered by itself, and its shuffle files and tables go with it."""
    boxes, base = sampled_ranges(spark), _line4_index(spark, sf_dir)
    asked = {
        "w32": lambda: query.batch_counts(base, boxes),
        "w64": lambda: query.batch_counts(build.recoded(base, w=64), boxes),
        "k2": lambda: query.batch_counts(build.recoded(base, 2), boxes),
        "postings": lambda: query.batch_postings(query.postings(base.rows, base.cols), boxes),
    }
    return together(spark, [lambda m=m, f=f: f().select(F.lit(m).alias("method"), "qid", "rows") for m, f in asked.items()], base.n_rows)


def written_index(spark: SparkSession, index: build.Index, rows: DataFrame | None = None) -> build.Index:
    """``rows``: the index's rows where they are stored already; then they are not written again."""
    path = shared_folder(spark)
    with tidy(spark):
        build.write_index(index, path, rows is None)
    return build.read_index(spark, path, index.cols, index.w, index.k, index.allocation, rows=rows)


def _row_id_seconds(f: Callable[[], DataFrame]) -> float:
    """Every row id is made, where it is; none reaches the driver."""
    began = time.perf_counter()
    f().write.format("noop").mode("overwrite").save()
    return round(time.perf_counter() - began, 4)


def _timed(f: Callable[[], DataFrame]) -> tuple[list, float]:
    """A few rows, and the seconds they took."""
    began = time.perf_counter()
    rows = f().collect()
    return rows, round(time.perf_counter() - began, 4)


def _seconds(f: Callable[[], DataFrame]) -> float:
    return _timed(f)[1]


@query_of("range_times")
def range_times(spark, sf_dir):
    """Seconds for the same twenty boxes on written indexes: load alone and whole, words of 32 and 64 bits, row-id lists, a scan.  Building stands apart.

    Whole answers are row ids.  Rows are sorted once for each order; every index's building counts the seconds of that
    sort.  One box warms up.
    """
    boxes, rows = checkpointed(sampled_ranges(spark)), []
    one = boxes.filter("qid = 0")
    for how in ("lex", "shuffle"):
        began = time.perf_counter()
        base = _line4_index(spark, sf_dir, how=how)
        sort_s = time.perf_counter() - began
        for w, k in ((32, 1), (64, 1), (32, 2)):
            began = time.perf_counter()
            index = written_index(spark, base if (w, k) == (32, 1) else build.recoded(base, k, w), base.rows)
            built = round(sort_s + time.perf_counter() - began, 4)
            _row_id_seconds(lambda: query.batch_row_ids(index, one))  # warm-up
            rows.append((how, "bitmaps", w, k, built, _seconds(lambda: query.batch_load(index, boxes)), _row_id_seconds(lambda: query.batch_row_ids(index, boxes))))
        lists = shared_folder(spark)
        began = time.perf_counter()
        query.postings(base.rows, base.cols).repartitionByRange("attr", "value").sortWithinPartitions("attr", "value", "row_id").write.partitionBy("attr").parquet(lists)
        built = round(sort_s + time.perf_counter() - began, 4)
        written = spark.read.parquet(lists)
        _row_id_seconds(lambda: query.batch_postings_ids(written, one))
        rows.append((how, "row_ids", 0, 1, built, _seconds(lambda: query.batch_postings_load(written, boxes)), _row_id_seconds(lambda: query.batch_postings_ids(written, boxes))))
        _row_id_seconds(lambda: query.batch_scan(base.rows, base.cols, one))
        rows.append((how, "scan", 0, 0, round(sort_s, 4), _seconds(lambda: base.rows.agg(*[F.max(c) for c in base.cols])), _row_id_seconds(lambda: query.batch_scan(base.rows, base.cols, boxes))))
    return frame(spark, rows, "row_order string, method string, w int, k int, build_s double, load_s double, total_s double")


@query_of("equality_times")
def equality_times(spark, sf_dir):
    """Per column, k and row order: words that a hundred equality queries load, seconds to load and to answer; the model's slow-down beside the measured one."""
    df, _ = S.fixture(spark, sf_dir, "line4")
    cols, rows = SORTED_BY["line4"], []
    cards = dictionary.cardinalities(df, cols)
    asked = sampled_values(df, cols)
    for how in ("lex", "shuffle"):
        base: dict[int, tuple[float, float]] = {}
        ordered = _line4_index(spark, sf_dir, how=how)  # sorted once for all k
        for k in (1, 2, 3, 4):
            index = written_index(spark, ordered if k == 1 else build.recoded(ordered, k), ordered.rows)
            for a, (c, n) in enumerate(zip(cols, cards, strict=True)):
                own = asked.filter(F.col("attr") == a)
                loaded, load = _timed(lambda: query.batch_load(index, own))  # one row a query
                words, total = sum(r["words"] for r in loaded) / len(loaded), _seconds(lambda: query.batch_counts(index, own))
                base.setdefault(a, (words, total))
                rows.append((c, k, how, round(words, 3), load, total, round(theory.query_cost_ratio(n, codes.cap_k(n, k)), 4), round(words / base[a][0], 4), round(total / base[a][1], 4)))
    return frame(spark, rows, "col string, k int, row_order string, words double, load_s double, total_s double, model_slowdown double, measured_words_ratio double, measured_time_ratio double")


# --- relational surroundings and streams ---------------------------------------------------------
@query_of("range_join_bins", "SELECT b.bin AS bin, count(*)::BIGINT AS rows FROM lineitem, (SELECT unnest(range(0, 10)) AS bin) b WHERE l_partkey >= b.bin * 100 AND l_partkey < b.bin * 100 + 70 GROUP BY ALL")
def range_join_bins(spark, sf_dir):
    bins = spark.range(10).select(F.col("id").alias("bin"), (F.col("id") * 100).alias("lo"), (F.col("id") * 100 + 70).alias("hi"))
    return relational.range_join(S.table(spark, sf_dir, "lineitem").select("l_partkey"), bins, "l_partkey", "lo", "hi", 100).groupBy("bin").agg(F.count(F.lit(1)).alias("rows"))


@query_of("as_of_join_events", "WITH o AS (SELECT o_custkey AS user_id, o_orderdate AS t, max(o_orderkey) AS k FROM orders GROUP BY ALL) SELECT count(*)::BIGINT AS rows, count(k)::BIGINT AS found, sum(k)::BIGINT AS keys FROM (SELECT e.event_id, o.k FROM events e ASOF LEFT JOIN o ON e.user_id = o.user_id AND e.ts >= o.t)")
def as_of_join_events(spark, sf_dir):
    events = S.table(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    orders = S.table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("t")).agg(F.max("o_orderkey").alias("k"))
    return relational.as_of_join(events, orders, ["user_id"], "ts", "t", "k").agg(F.count(F.lit(1)).alias("rows"), F.count("k").alias("found"), F.sum("k").alias("keys"))


@query_of("bitmap_join_nation", "SELECT n_nationkey::BIGINT AS value, count(*)::BIGINT AS rows FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL")
def bitmap_join_nation(spark, sf_dir):
    customers = S.table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    facts = relational.bitmap_join_column(S.table(spark, sf_dir, "orders").select("o_custkey"), customers, "o_custkey", "c_custkey", "c_nationkey")
    return query.counts_by_value(build.build_index(facts, ["c_nationkey"], 1, "numeric", "lex"), "c_nationkey")


@query_of("top_values", f"WITH t AS ({O.FIXTURE_SQL['event4']}), h AS (SELECT usr AS value, count(*) AS cnt FROM t GROUP BY ALL) SELECT 0::INT AS attr, value, cnt, row_number() OVER (ORDER BY cnt DESC, value)::INT AS place FROM h QUALIFY place <= 5")
def top_values(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "event4")
    return relational.top_values(dictionary.histograms(df, ["usr"]), 5)


@query_of("tumbling_windows", "SELECT date_trunc('hour', ts) AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY ALL")
def tumbling_windows(spark, sf_dir):
    return stream_events.windowed_counts(S.table(spark, sf_dir, "events"))


@query_of("timed_build")
def timed_build(spark, sf_dir):
    df, _ = S.fixture(spark, sf_dir, "line4")
    rows = []
    for how in ("lex", "shuffle"):
        t = build.build_index(df, SORTED_BY["line4"], 1, "numeric", how, 32, timed=True).timings
        rows.append((how, t["dictionary_s"], t["sort_s"], t["index_s"], t["total_s"]))
    return frame(spark, rows, "row_order string, dictionary_s double, sort_s double, index_s double, total_s double")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
