"""Step chains: ordered named subqueries and a closing query.

STEP rows: qid, traj_id, no (from 1), name, rationale, sql, kind (`step` or `close`)."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

CHAIN_FIELDS = ("no", "name", "rationale", "sql", "kind")


def chains_from_steps(steps: DataFrame) -> DataFrame:
    return steps.groupBy("qid", "traj_id").agg(F.array_sort(F.collect_list(F.struct(*CHAIN_FIELDS))).alias("steps"))


def steps_from_chains(chains: DataFrame) -> DataFrame:
    return chains.select("qid", "traj_id", F.inline("steps"))


def compose(steps: list[tuple[str, str]], close: str | None = None, upto: int | None = None) -> str:
    """Runnable text: the first `upto` steps and a select-all from the last of them, or all steps and the closing query."""
    used = steps if upto is None else steps[:upto]
    body = close if upto is None else f"SELECT * FROM {used[-1][0]}"
    return ("WITH " + ",\n".join(f"{n} AS ({q})" for n, q in used) + "\n" if used else "") + body


def compose_column(chains: DataFrame) -> DataFrame:
    """qid, traj_id, query: the same for a whole table of chains, in column form."""
    named = F.filter("steps", lambda s: s["kind"] == "step")
    close = F.get(F.filter("steps", lambda s: s["kind"] == "close"), F.lit(0))["sql"]
    ctes = F.array_join(F.transform(named, lambda s: F.concat(s["name"], F.lit(" AS ("), s["sql"], F.lit(")"))), ", ")
    return chains.select("qid", "traj_id", F.concat(F.when(F.size(named) > 0, F.concat(F.lit("WITH "), ctes, F.lit(" "))).otherwise(""), close).alias("query"))


def flatten(steps: list[tuple[str, str]], close: str) -> str:
    """One query without named steps: every reference in a FROM or JOIN becomes a derived table."""
    done: dict[str, str] = {}

    def inline(text: str) -> str:
        for name, body in done.items():
            text = re.sub(rf"\b(FROM|JOIN)\s+{name}\b(?!\s*\.)(\s+(?:AS\s+)?(?!ON\b|USING\b|WHERE\b|GROUP\b|ORDER\b|JOIN\b|LEFT\b|RIGHT\b|FULL\b|CROSS\b|INNER\b|LIMIT\b|HAVING\b|UNION\b)[a-z_]\w*)?", lambda m: f"{m[1]} ({body}){m[2] or ' AS ' + name}", text, flags=re.I)
        return text

    for name, body in steps:
        done[name] = inline(body)
    return inline(close)


#: Words that may follow a table's name and are no alias.
_AFTER = "on|using|where|group|order|join|left|right|full|cross|inner|limit|having|union|natural|lateral"
REFERENCE = r"(?i)\b(?:from|join)\s+([a-z_][a-z0-9_]*)"


def validate_bulk(steps: DataFrame, tables: list[str]) -> DataFrame:
    """qid, traj_id, malformed, undefined, conflicts: counts of the three reasons to reject, from step texts alone."""
    name = F.lower("name")
    rows = steps.withColumn("bad", (F.length(F.regexp_replace("sql", r"[^(]", "")) != F.length(F.regexp_replace("sql", r"[^)]", ""))) | ~F.lower("sql").rlike(r"^\s*(select|with|values)\b"))
    malformed = rows.groupBy("qid", "traj_id").agg(F.count_if("bad").alias("malformed"))
    named = rows.where("kind = 'step'").select("qid", "traj_id", "no", name.alias("name"))
    clash = named.groupBy("qid", "traj_id", "name").agg(F.count("*").alias("k")).select(
        "qid", "traj_id", (F.col("k") - 1 + F.col("name").isin(tables).cast("int")).alias("clash")
    ).groupBy("qid", "traj_id").agg(F.sum("clash").alias("conflicts"))
    refs = rows.select("qid", "traj_id", "no", F.explode(F.array_distinct(F.transform(F.regexp_extract_all("sql", F.lit(REFERENCE), F.lit(1)), F.lower))).alias("ref")).where(~F.col("ref").isin(tables))
    known = named.groupBy("qid", "traj_id", F.col("name").alias("ref")).agg(F.min("no").alias("since"))
    undefined = (
        refs.join(known, ["qid", "traj_id", "ref"], "left").where("since is null or since >= no").groupBy("qid", "traj_id").agg(F.count("*").alias("undefined"))
    )
    out = malformed.join(undefined, ["qid", "traj_id"], "left").join(clash, ["qid", "traj_id"], "left")
    return out.select("qid", "traj_id", "malformed", F.coalesce("undefined", F.lit(0)).cast("bigint").alias("undefined"), F.coalesce("conflicts", F.lit(0)).cast("bigint").alias("conflicts"))


def resolve_names(steps: DataFrame) -> DataFrame:
    """Steps with repeated names renamed, and references mended: a later step or closing query that names a repeated step means the latest
    one before it. New names are the old one and a number, those that are free in turn."""
    chain = ["qid", "traj_id"]
    k = F.row_number().over(Window.partitionBy(*chain, F.lower("name")).orderBy("no"))
    named = steps.where("kind = 'step'").select(*chain, "no", "name", k.alias("k"))
    taken = named.groupBy(*chain).agg(F.collect_set(F.lower("name")).alias("taken"))
    # the step of rank k among its namesakes takes the free number of rank k - 1; a chain has as many names as steps, so there is one
    numbered = lambda i: F.concat("name", F.lit("_"), i.cast("string"))
    free = F.filter(F.transform(F.sequence(F.lit(2), F.col("k") + F.size("taken")), numbered), lambda n: ~F.array_contains(F.col("taken"), F.lower(n)))
    named = named.join(taken, chain).select(*chain, "no", F.lower("name").alias("ref"), F.when(F.col("k") == 1, F.col("name")).otherwise(F.get(free, F.col("k") - 2)).alias("new"), "k")
    refs = steps.select(*chain, F.col("no").alias("at"), F.explode(F.array_distinct(F.transform(F.regexp_extract_all("sql", F.lit(REFERENCE), F.lit(1)), F.lower))).alias("ref"))
    latest = refs.join(named, [*chain, "ref"]).where("no < at").groupBy(*chain, "at", "ref").agg(F.max(F.struct("no", "new", "k")).alias("d")).where("d.k > 1")
    swaps = latest.groupBy(*chain, F.col("at").alias("no")).agg(F.collect_list(F.struct("ref", F.col("d.new").alias("new"))).alias("swaps"))
    own = named.select(*chain, "no", "new")
    # a reference that has an alias keeps it; one without gets its old name as alias, so columns that name it still do
    lead, word = F.lit(r"(?i)(\b(?:from|join)\s+)"), F.lit(rf"(\s+(?:as\s+)?(?!(?:{_AFTER})\b)[a-z_]\w*)")
    aliased = lambda text, x: F.regexp_replace(text, F.concat(lead, x["ref"], word), F.concat(F.lit("$1"), x["new"], F.lit("$2")))
    bare = lambda text, x: F.regexp_replace(text, F.concat(lead, x["ref"], F.lit(r"\b(?!\s*\.)")), F.concat(F.lit("$1"), x["new"], F.lit(" AS "), x["ref"]))
    mended = F.aggregate("swaps", F.col("sql"), lambda text, x: bare(aliased(text, x), x))
    keep = [c for c in steps.columns if c not in ("name", "sql")]
    out = steps.join(own, [*chain, "no"], "left").join(swaps, [*chain, "no"], "left")
    return out.select(*keep, F.when(F.col("kind") == "step", F.coalesce("new", "name")).otherwise(F.col("name")).alias("name"), F.when(F.col("swaps").isNull(), F.col("sql")).otherwise(mended).alias("sql")).select(*steps.columns)


def corpus_stats(steps: DataFrame, generated: DataFrame) -> DataFrame:
    """One row: chains, acceptance in percent of the rows of generated, mean and largest number of steps, mean words of rationales and texts."""
    words = lambda c: F.size(F.split(F.trim(c), r"\s+"))
    chains = steps.groupBy("qid", "traj_id").agg(F.count_if(F.col("kind") == "step").alias("k"), F.sum(words("rationale")).alias("r"), F.sum(words("sql")).alias("s"), F.count("*").alias("n"))
    both = chains.agg(
        F.count("*").alias("chains"), F.avg("k").alias("mean_steps"), F.max("k").alias("max_steps"),
        (F.sum("r") / F.sum("n")).alias("rationale_words"), (F.sum("s") / F.sum("n")).alias("step_words"),
    ).crossJoin(generated.agg(F.count("*").alias("all")))  # one row each
    return both.select("chains", (100 * F.col("chains") / F.col("all")).alias("acceptance"), "mean_steps", "max_steps", "rationale_words", "step_words")


def redundancy(digests: DataFrame) -> DataFrame:
    """Adds repeats_result (an earlier step of the chain has the same result), keeps_all_rows (as many rows as the step before),
    redundant (either) to qid, traj_id, no, n_rows, result_key."""
    same = Window.partitionBy("qid", "traj_id", "result_key").orderBy("no")
    chain = Window.partitionBy("qid", "traj_id").orderBy("no")
    repeats = F.row_number().over(same) > 1
    stays = F.coalesce(F.col("n_rows") == F.lag("n_rows").over(chain), F.lit(False))
    return digests.withColumn("repeats_result", repeats).withColumn("keeps_all_rows", stays).withColumn("redundant", F.col("repeats_result") | F.col("keeps_all_rows"))


def redundant_steps(runs: DataFrame) -> DataFrame:
    """qid, whole, slot and five rules for every executed step (rows with qid, whole, slot, slots, name, sql, status, n_rows, n_cols, result_key): repeats_result (an earlier step of the
    chain has the same result), duplicate_join (an earlier step joins the same tables), idle_filter (a filter that removes no row of the step it reads), unreferenced (no later
    step reads it), keeps_all_rows (all rows and columns of the step it reads, nothing joined or added up); redundant is any of them. Closing queries are never redundant."""
    chain = ["qid", "whole"]
    refs = F.array_sort(F.array_distinct(F.transform(F.regexp_extract_all("sql", F.lit(REFERENCE), F.lit(1)), F.lower)))
    t = runs.select(*chain, "slot", "slots", F.lower("name").alias("name"), F.lower("sql").alias("sql"), "status", "n_rows", "n_cols", "result_key").withColumn("refs", refs)
    ok = F.col("status") == "ok"
    joins = F.when(F.col("sql").rlike(r"\bjoin\b"), F.array_join("refs", ","))
    nth = lambda c: F.row_number().over(Window.partitionBy(*chain, c).orderBy("slot"))
    t = t.withColumn("joined", joins).withColumn("repeats_result", ok & (nth(F.col("result_key")) > 1)).withColumn("duplicate_join", F.col("joined").isNotNull() & (nth(F.col("joined")) > 1))
    read = t.select(*chain, F.col("slot").alias("by"), F.explode("refs").alias("ref"))
    used = read.select(*chain, F.col("ref").alias("name"), "by").groupBy(*chain, "name").agg(F.max("by").alias("last_use"))
    source = read.join(t.select(*chain, F.col("name").alias("ref"), F.col("n_rows").alias("rows_in"), F.col("n_cols").alias("cols_in")), [*chain, "ref"]).groupBy(*chain, F.col("by").alias("slot")).agg(
        F.max("rows_in").alias("rows_in"), F.max("cols_in").alias("cols_in")
    )
    plain = ~F.col("sql").rlike(r"\bjoin\b|\bgroup by\b|\bover \(|\b(sum|avg|count|min|max)\(")
    same = F.coalesce(ok & (F.col("n_rows") == F.col("rows_in")), F.lit(False))
    rules = ("repeats_result", "duplicate_join", "idle_filter", "unreferenced", "keeps_all_rows")
    out = (
        t.join(used, [*chain, "name"], "left").join(source, [*chain, "slot"], "left")
        .withColumn("idle_filter", same & F.col("sql").rlike(r"\bwhere\b") & plain)
        .withColumn("unreferenced", F.coalesce(F.col("last_use") <= F.col("slot"), F.lit(True)))
        .withColumn("keeps_all_rows", same & plain & F.coalesce(F.col("n_cols") >= F.col("cols_in"), F.lit(False)) & ~F.col("sql").rlike(r"\bwhere\b"))
    )
    inner = F.col("slot") < F.col("slots")
    out = out.select(*chain, "slot", *[(F.col(r) & inner).alias(r) for r in rules])
    return out.withColumn("redundant", F.greatest(*[F.col(r) for r in rules]))


def chain_error(cases: DataFrame) -> DataFrame:
    """traj_id, category for failed chains (traj_id, gold_rows, kept_rows, n_steps, redundant_steps, merged_steps): rows
    lost on the way, a needless step, a wrong boundary, or nothing to do with steps - the first that holds."""
    return cases.select(
        "traj_id",
        F.when(F.col("kept_rows") < F.col("gold_rows"), "data loss").when(F.col("redundant_steps") > 0, "redundant step").when(F.col("merged_steps") > 0, "wrong boundary").otherwise("not step-related").alias("category"),
    )


def _close_of(text: str, at: int) -> int:
    """Place of the parenthesis that closes the one at `at`, quotes aside; -1 if none does."""
    depth, quoted = 0, False
    for i in range(at, len(text)):
        c = text[i]
        if c == "'":
            quoted = not quoted
        elif not quoted and c in "()":
            depth += 1 if c == "(" else -1
            if depth == 0:
                return i
    return -1


def _top(text: str, words: str) -> int:
    """Place of the first of some words (a pattern) outside parentheses and quotes; -1 if there is none."""
    depth = 0
    for m in re.finditer(rf"[()]|'[^']*'|\b(?:{words})\b", text, re.I):
        if m[0] in "()":
            depth += 1 if m[0] == "(" else -1
        elif depth == 0 and m[0][0] != "'":
            return m.start()
    return -1


def _split_group(text: str, columns) -> tuple[str, str] | None:
    """(rows, rest) of a grouped query: a step with the columns it needs of its joined and filtered rows, and the query over a table that is yet to be named {}."""
    start, group = _top(text, "FROM"), _top(text, "GROUP BY")
    if not 0 < start < group or re.search(r"\b[a-z_]\w*\.[a-z_]", text, re.I):
        return None
    head, source, rest = text[:start], text[start:group].strip(), text[group:]
    every = columns(f"SELECT * {source}")
    if not every or len(set(every)) < len(every) or (_top(source, "JOIN|WHERE") < 0):
        return None
    used = [c for c in every if re.search(rf"\b{re.escape(c)}\b", head + rest)] or every[:1]
    return f"SELECT {', '.join(used)} {source}", f"{head}FROM {{}} {rest}"


def decompose(gold: str, columns, prefix: str = "part") -> tuple[list[tuple[str, str]], str]:
    """(steps, close) of a query: nested queries become named steps, the innermost first, where they stand alone (one that refers to the query
    around it stays in place); a grouped query over joined or filtered rows becomes two; what orders and limits the result is the closing query.
    columns(text) gives the column names of a query, or None if it is not valid."""
    steps: list[tuple[str, str]] = []
    left: set[str] = set()
    valid = lambda close, *more: columns(compose([*steps, *more], close)) is not None
    named = lambda: f"{prefix}{len(steps) + 1}"
    while True:
        spots = [(m.start(), _close_of(gold, m.start())) for m in re.finditer(r"\(\s*SELECT\b", gold, re.I)]
        spots = [(a, z) for a, z in spots if z > 0 and gold[a : z + 1] not in left]
        if not spots:
            break
        at, end = spots[-1]  # the last one holds no other that is still to do
        inner, name = gold[at + 1 : end].strip(), named()
        if not valid(inner):
            left.add(gold[at : end + 1])
            continue
        steps.append((name, inner))
        put = name if re.search(r"\b(FROM|JOIN)\s*$", gold[:at], re.I) else f"(SELECT * FROM {name})"
        left.add(put)
        gold = gold[:at] + put + gold[end + 1 :]
    cut = _top(gold, "ORDER BY|LIMIT")
    body, tail = (gold[:cut].strip(), gold[cut:].strip()) if cut > 0 else (gold, "")
    halves = _split_group(body, lambda text: columns(compose(steps, text)))
    if halves and valid(halves[1].format(named()), (named(), halves[0])):
        body = halves[1].format(named())
        steps.append((named(), halves[0]))
    name = named()
    close = f"SELECT * FROM {name}" + (f" {tail}" if tail else "")
    if tail and not valid(close, (name, body)):
        body, close = f"{body} {tail}", f"SELECT * FROM {name}"
    return [*steps, (name, body)], close
