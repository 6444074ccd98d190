"""Execution digests and result fingerprints."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


# Expressions are built as SQL text: hundreds of calls to build them one by one take longer than a small query.


#: What stands for a null, and what the counts of rounded numbers are crossed with, so that neither meets a whole number or a text's hash.
_NULL, _COUNTED = -7046029254386353131, 5871781006564002453


def _rounded(c: str, digits: int, double: bool) -> str:
    """A number as a whole number, equal where it is equal after rounding to so many digits, whatever its type: below 2^53 units of the last digit the count of units, which is
    exact and far cheaper than a formatted number; beyond it, and for what is no number, the hash of that. Units of a double below 2^48 that lie within two fifths of a whole number are
    counted at once: the product is off by less than a sixteenth there, so exact decimal rounding, which costs far more, ends at the same number."""
    unit = 10**digits
    counted = lambda x: f"CAST(rint({x}) AS BIGINT) ^ {_COUNTED}L"
    near = f"WHEN abs({c}) < {(1 << 48) // unit} AND abs({c} * {unit}.0D - rint({c} * {unit}.0D)) < 0.4D THEN {counted(f'{c} * {unit}.0D')} " if double else ""
    return f"CASE {near}WHEN abs({c}) < {(1 << 52) // unit}L THEN {counted(f'CAST(round({c}, {digits}) AS DOUBLE) * {unit}')} ELSE xxhash64(format_number(round({c}, {digits}) + 0.0D, {digits})) END"


def _texts(c: str) -> str:
    """The hash of a text, or the whole number that it writes: a value is one in any type that has the same text."""
    return f"CASE WHEN {c} < ':' AND CAST(try_cast({c} AS BIGINT) AS STRING) = {c} THEN try_cast({c} AS BIGINT) ELSE xxhash64({c}) END"


def _cells(df: DataFrame, digits: int) -> list[str]:
    """Columns as whole numbers: doubles rounded (no negative zero), whole numbers as they are, others by their text; nulls apart from all."""
    out = []
    for i, (_, kind) in enumerate(df.dtypes):
        if kind in ("double", "float") or kind.startswith("decimal"):
            c = f"CASE WHEN c{i} IS NOT NULL THEN {_rounded(f'c{i}', digits, kind == 'double')} END"
        elif kind in ("tinyint", "smallint", "int", "bigint"):
            c = f"CAST(c{i} AS BIGINT)"
        else:
            text = f"c{i}" if kind == "string" else f"CAST(c{i} AS STRING)"
            c = f"CASE WHEN c{i} IS NOT NULL THEN {_texts(text)} END"
        out.append(f"coalesce({c}, {_NULL}L)")
    return out


_LONG, _SHORT = (21, 21, 22), (16, 16)  # bits a piece of a hash


def _pieces(h: str, widths: tuple[int, ...]) -> list[Column]:
    """Sums of a hash's bits in pieces, the lowest first: whole numbers that no count of rows makes overflow, at a small part of a decimal sum's cost."""
    out, at = [], 0
    for k, width in enumerate(widths):
        piece = f"shiftright({h}, {at})" if k + 1 == len(widths) else f"shiftright({h}, {at}) & {(1 << width) - 1}L"  # the last piece holds the sign
        out.append(F.expr(f"sum({piece}) AS {h}{k}"))
        at += width
    return out


def _whole(h: str, widths: tuple[int, ...]) -> str:
    """The sum of a hash as text, from those of its pieces."""
    parts = [f"CAST(coalesce({h}{k}, 0) AS DECIMAL(19,0)) * CAST({1 << sum(widths[:k])} AS DECIMAL(16,0))" for k in range(len(widths))]
    return f"CAST(CAST({' + '.join(parts)} AS DECIMAL(38,0)) AS STRING)"


def _key_parts(df: DataFrame, digits: int, leads: tuple[int, ...] = ()) -> tuple[DataFrame, list[Column], list[Column]]:
    """Rows with plain column names and their hashes, aggregates over them, and the keys formed of these: that of df, and of df with each constant before its columns."""
    rows = df.toDF(*[f"c{i}" for i in range(len(df.columns))])
    cells = _cells(df, digits)
    rows = rows.selectExpr("*", *[f"{c} AS h{i}_" for i, c in enumerate(cells)])
    own = [f"h{i}_" for i in range(len(cells))]
    hashed = [own or ["0L"], *[[f"{x}L", *own] for x in leads]]
    rows = rows.selectExpr("*", *[e for i, of in enumerate(hashed) for e in (f"xxhash64({', '.join(of)}) AS a{i}_", f"CAST(hash({', '.join(of)}, 7) AS BIGINT) AS b{i}_")])
    sums, keys = [F.count("*").alias("n")], []
    for i in range(len(hashed)):
        sums += [*_pieces(f"a{i}_", _LONG), *_pieces(f"b{i}_", _SHORT)]
        keys.append(F.expr(f"concat_ws(':', '{len(df.columns) + (i > 0)}', CAST(n AS STRING), {_whole(f'a{i}_', _LONG)}, {_whole(f'b{i}_', _SHORT)})"))
    return rows, sums, keys


def result_key(df: DataFrame, digits: int = 6) -> DataFrame:
    """One row, result_key: row count, and sums of two row hashes, of all columns in order, names aside. Equal multisets of
    rows have equal keys; one aggregate, no row is shuffled."""
    rows, sums, keys = _key_parts(df, digits)
    return rows.agg(*sums).select(keys[0].alias("result_key"))


def digest(df: DataFrame, key: tuple[str, ...] = (), sample: int = 0, with_result: bool = False, leads: tuple[int, ...] = ()) -> DataFrame:
    """One row: n_rows, n_cols, nulls (share of null cells); keys, repeats and fanout (distinct keys, n_rows / keys, and the most rows of
    one key less one) if a key is named; sample (that many rows as text, the least by hash) and result_key if asked for, with lead_keys, those of df with each of some constants before its columns. One scan, but for a key's
    largest count."""
    rows, sums, key_texts = _key_parts(df, 6, leads)
    places = [f"c{df.columns.index(k)}" for k in key]
    empty = " + ".join(["0", *[f"CAST(c{i} IS NULL AS INT)" for i in range(len(df.columns))]])
    parts = [*sums, F.expr(f"sum({empty}) AS empty")]
    if places:
        # rows of a key first, so that a key of any size is a number
        counted = rows.groupBy(*places).agg(F.count("*").alias("k"))
        keyed = counted.agg(F.count("*").alias("keys"), F.max("k").alias("most"))
    out = rows.agg(*parts)
    fields = [F.col("n").alias("n_rows"), F.lit(len(df.columns)).alias("n_cols"), F.try_divide(F.col("empty"), F.col("n") * len(df.columns)).alias("nulls")]
    if places:
        out = out.crossJoin(keyed)  # one row each
        fields += ["keys", F.try_divide("n", "keys").alias("repeats"), F.coalesce(F.col("most") - 1, F.lit(0)).alias("fanout")]
    if sample:
        text = F.to_json(F.struct(*[F.col(c).cast("string").alias(c) for c in rows.columns[: len(df.columns)]]))
        picked = rows.select(F.xxhash64(text).alias("h"), text.alias("t")).distinct().orderBy("h", "t").limit(sample).agg(F.array_sort(F.collect_list(F.struct("h", "t"))).alias("s"))
        out = out.crossJoin(picked)  # one row each
        fields.append(F.transform("s", lambda x: x["t"]).alias("sample"))
    if with_result:
        fields.append(key_texts[0].alias("result_key"))
    if leads:
        fields.append(F.array(*key_texts[1:]).alias("lead_keys"))
    return out.select(*fields)


def fanout(before: DataFrame, after: DataFrame, keys: list[str]) -> DataFrame:
    """keys..., rows_before, rows_after, ratio for keys whose rows a join multiplied."""
    a = before.groupBy(*keys).agg(F.count("*").alias("rows_before"))
    b = after.groupBy(*keys).agg(F.count("*").alias("rows_after"))
    return a.join(b, keys).where("rows_after > rows_before").withColumn("ratio", F.col("rows_after") / F.col("rows_before"))
