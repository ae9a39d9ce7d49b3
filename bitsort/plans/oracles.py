"""DuckDB twins of the sizing workloads: the same fixtures, orders and size formula in SQL."""

from __future__ import annotations

from bitsort.operators.roworder import SHUFFLE_FACTORS, SHUFFLE_PRIME

FIXTURE_SQL = {
    "line4": "SELECT l_linenumber::BIGINT AS ln, round(l_discount*100)::BIGINT AS disc, datediff('day', DATE '1970-01-01', l_shipdate::DATE)::BIGINT AS ship, l_partkey::BIGINT AS part FROM lineitem",
    "line3": "SELECT l_linenumber::BIGINT AS ln, round(l_discount*100)::BIGINT AS disc, l_partkey::BIGINT AS part FROM lineitem",
    "line10": "SELECT ascii(l_linestatus)::BIGINT AS status, ascii(l_returnflag)::BIGINT AS flag, l_linenumber::BIGINT AS ln, round(l_tax*100)::BIGINT AS tax, round(l_discount*100)::BIGINT AS disc, l_quantity::BIGINT AS qty, datediff('day', DATE '1970-01-01', l_shipdate::DATE)::BIGINT AS ship, l_suppkey::BIGINT AS supp, l_partkey::BIGINT AS part, round(l_extendedprice*100)::BIGINT AS price FROM lineitem",
    "event4": "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, (floor(epoch(ts)/3600))::BIGINT AS hour, user_id::BIGINT AS usr, round(value*100)::BIGINT AS val FROM events",
    "rating4": "SELECT substr(o_orderpriority,1,1)::BIGINT AS prio, datediff('day', DATE '1970-01-01', o_orderdate::DATE)::BIGINT AS day, o_custkey::BIGINT AS cust, l_partkey::BIGINT AS part FROM lineitem JOIN orders ON l_orderkey=o_orderkey",
    "rating3": "SELECT substr(o_orderpriority,1,1)::BIGINT AS prio, datediff('day', DATE '1970-01-01', o_orderdate::DATE)::BIGINT AS day, l_partkey::BIGINT AS part FROM lineitem JOIN orders ON l_orderkey=o_orderkey",
    "corr3": "SELECT datediff('day', DATE '1970-01-01', o_orderdate::DATE)::BIGINT AS day, datediff('day', DATE '1970-01-01', l_shipdate::DATE)::BIGINT AS ship, ascii(o_orderstatus)::BIGINT AS status FROM lineitem JOIN orders ON l_orderkey=o_orderkey",
    "gram4": "SELECT " + ", ".join(f"dense_rank() OVER (ORDER BY w[i + {k}]) - 1 AS w{k + 1}" for k in range(4)) + " FROM (SELECT w, unnest(range(1, len(w) - 2)) AS i FROM (SELECT [regexp_replace(x, '(ing|ed|es|s)$', '') for x in regexp_split_to_array(lower(text), '[^\\p{L}]+') if length(x) > 3] AS w FROM documents) WHERE len(w) >= 4)",
}


def shuffle_sql(cols: list[str]) -> str:
    total = " + ".join(f"(({c} * {SHUFFLE_FACTORS[i % 10] + i // 10}) % {SHUFFLE_PRIME} + {SHUFFLE_PRIME}) % {SHUFFLE_PRIME} * {SHUFFLE_FACTORS[(i + 3) % 10]}" for i, c in enumerate(cols))
    return f"((({total}) % {SHUFFLE_PRIME}) * 48271 + (({total}) % 65521) * 69621) % {SHUFFLE_PRIME}"


def order_sql(how: str, cols: list[str]) -> str:
    plain = ", ".join(cols)
    if how == "lex":
        return plain
    if how == "shuffle":
        return f"{shuffle_sql(cols)}, {plain}"
    raise ValueError(how)


def numbered_sql(source: str, cols: list[str], how: str = "lex", blocks: int = 1) -> str:
    """rid for every row of a source query."""
    if how == "blocks":
        inner = f"SELECT row_number() OVER (ORDER BY {order_sql('shuffle', cols)}) - 1 AS i, count(*) OVER () AS n, * FROM ({source})"
        return f"SELECT row_number() OVER (ORDER BY (i * {blocks}) // n, {', '.join(cols)}) - 1 AS rid, {', '.join(cols)} FROM ({inner})"
    if how == "freq_lex":
        freq = ", ".join(f"count(*) OVER (PARTITION BY {c}) AS f_{c}" for c in cols)
        keys = ", ".join(f"f_{c}, {c}" for c in cols)
        return f"SELECT row_number() OVER (ORDER BY {keys}) - 1 AS rid, {', '.join(cols)} FROM (SELECT *, {freq} FROM ({source}))"
    return f"SELECT row_number() OVER (ORDER BY {order_sql(how, cols)}) - 1 AS rid, {', '.join(cols)} FROM ({source})"


def per_bitmap_ctes(numbered: str, cols: list[str], w: int = 32, clean_bits: int | None = None, markers: bool = True) -> str:
    """CTEs up to ``per_bitmap`` (attr, v, dirty, clean_runs, markers, overruns), unary codes, one block."""
    clean_bits = (w // 2 if markers else 30) if clean_bits is None else clean_bits
    cmax, dmax = 2**clean_bits - 1, 2 ** max(w - 1 - clean_bits, 0) - 1
    bits = " UNION ALL ".join(f"SELECT {i} AS attr, {c} AS v, rid // {w} AS wn, bit_or(1::HUGEINT << (rid % {w})::INT) AS bits FROM ord GROUP BY ALL" for i, c in enumerate(cols))
    extra = f"CASE WHEN full_ THEN 0 ELSE greatest((len + {dmax} - 1) // {dmax} - 1, 0) + CASE WHEN run = 1 AND zeros = 0 THEN 1 ELSE 0 END END" if markers else "0"
    over = f"CASE WHEN full_ THEN len // {cmax} ELSE len // {dmax} END" if markers else f"CASE WHEN full_ THEN len // {cmax} ELSE 0 END"
    return f"""ord AS ({numbered}),
tot AS (SELECT count(*) AS n, (count(*) + {w - 1}) // {w} AS words FROM ord),
bits AS ({bits}),
kinds AS (SELECT attr, v, wn, bits = CASE WHEN wn = words - 1 THEN (1::HUGEINT << (n - wn * {w})::INT) - 1 ELSE (1::HUGEINT << {w}) - 1 END AS full_, words FROM bits, tot),
gaps AS (SELECT *, wn - coalesce(lag(wn) OVER o, -1) - 1 AS gap, lag(full_) OVER o AS pf FROM kinds WINDOW o AS (PARTITION BY attr, v ORDER BY wn)),
marked AS (SELECT *, sum(CASE WHEN gap > 0 OR pf IS NULL OR pf <> full_ THEN 1 ELSE 0 END) OVER (PARTITION BY attr, v ORDER BY wn ROWS UNBOUNDED PRECEDING) AS run FROM gaps),
runs AS (SELECT attr, v, run, first(full_) AS full_, count(*) AS len, max(gap) AS zeros, max(wn) AS lastw, first(words) AS words FROM marked GROUP BY attr, v, run),
tails AS (SELECT *, CASE WHEN run = max(run) OVER (PARTITION BY attr, v) THEN words - 1 - lastw ELSE 0 END AS tail FROM runs),
per_bitmap AS (SELECT attr, v, sum(CASE WHEN full_ THEN 0 ELSE len END)::BIGINT AS dirty,
  sum((zeros > 0)::INT + full_::INT + (tail > 0)::INT)::BIGINT AS clean_runs,
  sum((zeros + {cmax} - 1) // {cmax} + CASE WHEN full_ THEN (len + {cmax} - 1) // {cmax} ELSE 0 END + (tail + {cmax} - 1) // {cmax} + {extra})::BIGINT AS markers,
  sum(zeros // {cmax} + tail // {cmax} + {over})::BIGINT AS overruns
  FROM tails GROUP BY attr, v)"""


def totals_sql(numbered: str, cols: list[str], w: int = 32, head: str = "", markers: bool = True, clean_bits: int | None = None) -> str:
    """One row of totals, ``head`` before them."""
    return f"""WITH {per_bitmap_ctes(numbered, cols, w, clean_bits, markers)}
SELECT {head} count(*)::BIGINT AS bitmaps, sum(dirty)::BIGINT AS dirty, sum(clean_runs)::BIGINT AS clean_runs, sum(dirty + clean_runs)::BIGINT AS storage_cost,
  sum(markers)::BIGINT AS markers, sum(dirty + markers)::BIGINT AS compressed, sum(overruns)::BIGINT AS overruns,
  round(sum(markers)::DOUBLE / sum(dirty + markers), 6) AS clean_share, round(sum(overruns)::DOUBLE / sum(markers), 6) AS overrun_share FROM per_bitmap"""


def attributes_sql(numbered: str, cols: list[str], w: int = 32, head: str = "") -> str:
    return f"""WITH {per_bitmap_ctes(numbered, cols, w)}
SELECT {head} attr::INT AS attr, count(*)::BIGINT AS bitmaps, sum(dirty)::BIGINT AS dirty, sum(clean_runs)::BIGINT AS clean_runs, sum(dirty + markers)::BIGINT AS compressed FROM per_bitmap GROUP BY attr"""
