"""Running step chains: every distinct prefix once, its result digested inside Spark."""

from __future__ import annotations

import hashlib
import re
import time
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager
from dataclasses import dataclass
from functools import cached_property

from py4j.java_gateway import JavaObject
from py4j.protocol import Py4JError
from pyspark.errors import AnalysisException, ParseException, PySparkException
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stepsql.sources.shared import drop, written

from .chains import compose
from .digest import digest

DIGEST = "prefix_key string, depth int, status string, condition string, n_rows bigint, n_cols int, nulls double, result_key string, seconds double, run_key string"

# Error conditions by the reason to reject a chain.
REASONS = {"PARSE_SYNTAX_ERROR": "malformed", "TABLE_OR_VIEW_NOT_FOUND": "undefined reference", "DUPLICATED_CTE_NAMES": "name conflict"}


def condition(e: Exception) -> str:
    """Error condition of Spark, without its subclass."""
    found = e.getCondition() if isinstance(e, PySparkException) else None
    return (found or type(e).__name__).split(".")[0]


def validate(spark: SparkSession, steps: list[tuple[str, str]], close: str) -> tuple[bool, str, int]:
    """(accepted, reason, step): analysed prefix by prefix, no job started. Names that repeat, or that clash with a view, are conflicts."""
    seen: set[str] = set()
    for k, (name, _) in enumerate(steps, 1):
        if name.lower() in seen:
            return False, "name conflict", k
        seen.add(name.lower())
        try:
            spark.sql(compose(steps, upto=k))
        except (ParseException, AnalysisException) as e:
            return False, REASONS.get(condition(e), condition(e)), k
    try:
        spark.sql(compose(steps, close))
    except (ParseException, AnalysisException) as e:
        return False, REASONS.get(condition(e), condition(e)), len(steps) + 1
    return True, "", 0


def prefix_keys(steps: list[tuple[str, str]], close: str | None = None) -> list[str]:
    """A digest for each prefix, chained, so that chains share the keys of shared prefixes."""
    out, held = [], ""
    for name, text in [*steps, *([("", close)] if close else [])]:
        held = hashlib.sha256(f"{held}\x1f{name}\x1f{text}".encode()).hexdigest()
        out.append(held)
    return out


_STAR = re.compile(
    r"SELECT (?P<out>(?:(?!\bSELECT\b|\bFROM\b).)*?) FROM (?P<hub>\w+) JOIN (?P<a>\w+) ON (?P<a1>\w+) = (?P<a2>\w+) JOIN (?P<b>\w+) ON (?P<b1>\w+) = (?P<b2>\w+) GROUP BY (?P<by>\w+(?:, \w+)*)(?=\)|\s*$)", re.I | re.S
)


def apart(spark: SparkSession, text: str) -> str:
    """The text, with a star of two tables around one, of which only distinct values of either side are counted by columns of the middle, turned into the union of both sides, each where
    the other has a match. Its groups and counts are the same, without the pairs of both sides, of which there are as many as their product."""

    def put(m: re.Match) -> str:
        try:
            columns = {t: {c.lower() for c in spark.table(m[t]).columns} for t in ("hub", "a", "b")}
        except PySparkException:
            return m[0]  # a named step, or nothing
        owner = lambda c: [t for t, own in columns.items() if c.lower() in own]
        counted = re.findall(r"(?i)\bcount\(DISTINCT (\w+)\)", m["out"])
        rest = re.sub(r"(?i)\bcount\(DISTINCT \w+\)", "0", m["out"])
        keys = m["by"].split(", ")
        names = {w.lower() for w in re.findall(r"\b[a-z_]\w*", re.sub(r"(?i)\bAS \w+|\b\d[\w.]*", " ", rest), re.I)}
        fits = (
            len({m[t].lower() for t in ("hub", "a", "b")}) == 3 and set(map(str.lower, keys)) >= names and not set("()'\"`") & set(rest)
            and not re.search(r"(?:^|,)\s*\*", rest) and all(owner(k) == ["hub"] for k in keys) and {tuple(owner(c)) for c in counted} == {("a",), ("b",)}
            and all(sorted(owner(m[f"{t}1"]) + owner(m[f"{t}2"])) == sorted([t, "hub"]) for t in ("a", "b"))
        )
        if not fits:
            return m[0]

        def side(t: str, other: str) -> str:
            shown = [c if owner(c) == [t] else f"NULL AS {c}" for c in dict.fromkeys(counted)]
            on = lambda x: f"{m[x]} ON {m[f'{x}1']} = {m[f'{x}2']}"
            return f"SELECT {', '.join([*keys, *shown])} FROM {m['hub']} JOIN {on(t)} LEFT SEMI JOIN {on(other)}"

        return f"SELECT {m['out']} FROM ({side('a', 'b')} UNION ALL {side('b', 'a')}) AS apart_ GROUP BY {m['by']}"

    return _STAR.sub(put, text)


def run_text(spark: SparkSession, text: str, leads: tuple[int, ...] = ()) -> dict:
    """Status and digest of one query; its rows stay in Spark. With leads also the result_key of its rows with each of these constants before them, by constant."""
    began = time.perf_counter()
    try:
        df = spark.sql(apart(spark, text))
        row = digest(df, with_result=True, leads=leads).collect()[0]
        out = {"status": "ok", "condition": "", "n_rows": row.n_rows, "n_cols": row.n_cols, "nulls": row.nulls, "result_key": row.result_key, "seconds": time.perf_counter() - began}
        return out | {"lead_keys": dict(zip(leads, row.lead_keys))} if leads else out
    except PySparkException as e:
        kind = "invalid" if isinstance(e, (ParseException, AnalysisException)) else "runtime error"
        return {"status": kind, "condition": condition(e), "n_rows": None, "n_cols": None, "nulls": None, "result_key": None, "seconds": time.perf_counter() - began}


#: Joins whose smaller side has no shuffled partition above this size, as measured, hash it in place of sorting both sides; Spark does so only where it aims at partitions no larger.
HASHED = "8m"
#: Splits of a file: the hash maps of a task stay small enough not to spill.
SPLIT = "16m"


def _settings(spark: SparkSession) -> dict[str, str]:
    """Settings while chains run. Shuffles start with eight partitions a core, so that those of large tables are small; Spark puts small ones together again."""
    many = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8 * spark.sparkContext.defaultParallelism)
    return {
        "spark.sql.adaptive.maxShuffledHashJoinLocalMapThreshold": HASHED,
        "spark.sql.adaptive.advisoryPartitionSizeInBytes": HASHED,
        "spark.sql.adaptive.coalescePartitions.initialPartitionNum": str(many),
        "spark.sql.files.maxPartitionBytes": SPLIT,
    }


@contextmanager
def hashing(spark: SparkSession) -> Iterator[None]:
    """_settings while chains run; what the session had is put back."""
    settings = _settings(spark)
    before = {key: spark.conf.get(key, None) for key in settings}
    for key, value in settings.items():
        spark.conf.set(key, value)
    try:
        yield
    finally:
        for key, value in before.items():
            spark.conf.unset(key) if value is None else spark.conf.set(key, value)


def _keep(spark: SparkSession, text: str, key: str) -> str | None:
    """The result of a prefix as a table and a view of this name; None where it cannot be written (columns of one name, or of no storable type)."""
    name = f"kept_{key[:24]}"
    try:
        # read a few times and dropped: a dictionary costs more to build than it saves
        written(spark.sql(apart(spark, text)), {"parquet.enable.dictionary": "false"}).createOrReplaceTempView(name)
    except PySparkException:
        return None
    return name


def run_keys(steps: list[tuple[str, str]], close: str | None = None) -> list[tuple[str, list[int]]]:
    """(key, places of the earlier steps that its text may name) of each prefix. Prefixes of one key give one result: their last texts are equal, and so are, name by name,
    the steps that these read, however many steps stand beside them. Where a name repeats, all steps count, as the whole is then an error."""
    out: list[tuple[str, list[int]]] = []
    names = [n.lower() for n, _ in steps]
    for k, (_, text) in enumerate([*steps, *([("", close)] if close else [])]):
        words = set(re.findall(r"\w+", text.lower()))
        plain = all(re.fullmatch(r"\w+", n) for n in names[: k + 1]) and len(set(names[: k + 1])) == len(names[: k + 1])
        read = [j for j in range(min(k, len(steps))) if not plain or names[j] in words]
        held = "\x1f".join([text, *(f"{names[j]}\x1e{out[j][0]}" for j in read)] + ([] if plain else ["\x1d".join(names[: k + 1])]))
        out.append((hashlib.sha256(held.encode()).hexdigest(), read))
    return out


@dataclass(frozen=True)
class Plan:
    """What tells that two prefixes give the same rows: the optimised plan of a prefix, composed from its texts, as Spark compares plans, and the types of its columns. Where the
    text begins with a constant, lead has it, and rest is the plan without that column."""

    df: DataFrame
    lead: int | None = None
    rest: Plan | None = None

    @cached_property
    def tree(self) -> tuple[int, tuple[str, ...], JavaObject]:
        plan = self.df._jdf.queryExecution().optimizedPlan()
        plan = plan.child() if plan.nodeName() == "Sort" else plan  # rows are compared, not their order
        return plan.semanticHash(), tuple(t for _, t in self.df.dtypes), plan

    def same(self, other: Plan) -> bool:
        return self.tree[:2] == other.tree[:2] and self.tree[2].sameResult(other.tree[2])

    def adds_to(self, other: Plan) -> bool:
        """Whether the rows are those of the other behind the constant: the optimiser leaves no row that differs from it only if there can be none."""
        if self.rest is None or not self.rest.same(other):
            return False
        most = _placed(self.df).where(~F.col("c0").eqNullSafe(F.lit(self.lead)))._jdf.queryExecution().optimizedPlan().maxRows()
        return most.isDefined() and int(most.get()) == 0


def _placed(df: DataFrame) -> DataFrame:
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))])


def plan_of(spark: SparkSession, text: str, last: str) -> Plan | None:
    """The plan of a prefix, whose own text is last; None where it has none. No job is started."""
    try:
        df = spark.sql(text)
        found = re.match(r"\s*SELECT (\d{1,9}) AS \w+, ", last)
        led = found and len(df.columns) > 1 and df.dtypes[0][1] == "int" and [c.lower() for c in df.columns].count(df.columns[0].lower()) == 1
        out = Plan(df, int(found[1]), Plan(df.drop(df.columns[0]))) if led else Plan(df)
        _ = out.tree, out.rest and out.rest.tree
        return out
    except (PySparkException, Py4JError):
        return None


def digests(spark: SparkSession, chains: list[tuple[list[tuple[str, str]], str]], prune_failed: bool = True, threads: int = 4, keep: bool = False) -> dict[str, dict]:
    """The fields of DIGEST by prefix key; see run_chains."""
    levels: dict[int, dict[str, tuple]] = {}
    read_by_others: set[str] = set()
    for steps, close in chains:
        keys, runs = prefix_keys(steps, close), run_keys(steps, close)
        if not prune_failed:  # a step that failed, and that nothing reads, still makes the whole an error
            runs = [(key, list(range(min(k, len(steps))))) for k, key in enumerate(keys)]
        read_by_others |= {runs[j][0] for _, read in runs for j in read}
        for k, key in enumerate(keys, 1):
            levels.setdefault(k, {})[key] = (steps[:k], close if k > len(steps) else None, keys[:k], runs[:k])
    done: dict[str, dict] = {}
    shared: dict[str, dict] = {}
    views: dict[str, str] = {}
    paths: set[str] = set()
    known: list[tuple[Plan, str]] = []

    def composed(steps: list[tuple[str, str]], close: str | None, runs: list[tuple[str, list[int]]], views: dict[str, str]) -> str:
        need, todo = set() if close is not None else {len(steps) - 1}, [len(runs) - 1]
        while todo:  # steps that are read, through others that are not kept
            for j in runs[todo.pop()][1]:
                if j not in need:
                    need.add(j)
                    todo += [j] if runs[j][0] not in views else []
        held = [(steps[j][0], f"SELECT * FROM {views[runs[j][0]]}" if runs[j][0] in views else steps[j][1]) for j in sorted(need)]
        return compose(held, close) if close is not None else compose(held, upto=len(held))

    def look(steps: list[tuple[str, str]], close: str | None, runs: list[tuple[str, list[int]]]) -> Plan | None:
        return plan_of(spark, composed(steps, close, runs, {}), close if close is not None else steps[-1][1])

    def run(key: str, steps: list[tuple[str, str]], close: str | None, runs: list[tuple[str, list[int]]], read: bool, leads: tuple[int, ...]) -> dict:
        text, more = composed(steps, close, runs, views), (leads,) if leads else ()
        began = time.perf_counter()
        view = _keep(spark, text, key) if keep and read else None
        if view is None:
            return run_text(spark, text, *more)
        views[runs[-1][0]] = view
        paths.update(f.rsplit("/", 1)[0] for f in spark.table(view).inputFiles()[:1])
        return run_text(spark, f"SELECT * FROM {view}", *more) | {"seconds": time.perf_counter() - began}

    def renamed(own: str, plan: Plan, of: str, lead: bool) -> None:
        """The kept result of an equal prefix under the columns of this one, behind the constant where that is all it has more."""
        columns = plan.df.columns
        if of in views and own in read_by_others and len({c.lower() for c in columns}) == len(columns):
            name, table = f"kept_{own[:24]}", spark.table(views[of])
            (table.select(F.lit(plan.lead), "*") if lead else table).toDF(*columns).createOrReplaceTempView(name)
            views[own] = name

    try:
        with ThreadPoolExecutor(threads) as pool, hashing(spark):
            for k in sorted(levels):
                waiting, todo = {}, {}
                for key, (steps, close, keys, runs) in levels[k].items():
                    parent, own = keys[-2] if k > 1 else None, runs[-1][0]
                    if prune_failed and parent and done[parent]["status"] != "ok":
                        done[key] = {"status": "pruned", "condition": done[parent]["condition"], "n_rows": None, "n_cols": None, "nulls": None, "result_key": None, "seconds": 0.0, "depth": k, "run_key": own}
                        continue
                    waiting[key] = own
                    if own not in shared and own not in todo:
                        todo[own] = (key, steps, close, runs)
                plans = dict(zip(todo, pool.map(lambda own: look(*todo[own][1:]), todo)))
                equal, leads, first = {}, {}, set(todo)
                for own in sorted(todo, key=lambda own: plans[own] is not None and plans[own].rest is not None):  # those behind a constant last
                    plan = plans[own]
                    if plan is None:
                        continue
                    same = next((o for p, o in known if p.same(plan)), None)
                    if same is None and plan.rest is not None and (same := next((o for p, o in known if o in first and plan.adds_to(p)), None)) is not None:
                        leads.setdefault(same, {})[own] = plan.lead
                    elif same is not None:
                        equal[own] = same
                    else:
                        known.append((plan, own))
                        continue
                    first.discard(own)
                read = read_by_others & set(todo) | {of for own, of in equal.items() if own in read_by_others} | {of for of, by in leads.items() if read_by_others & set(by)}
                sent = {own: pool.submit(run, *todo[own], own in read, tuple(sorted(set(leads.get(own, {}).values())))) for own in first}
                shared |= {own: job.result() | {"run_key": own} for own, job in sent.items()}
                for of, by in leads.items():
                    held = shared[of].pop("lead_keys", {})
                    for own, lead in by.items():
                        shared[own] = dict(shared[of])
                        if held:
                            cols = shared[of]["n_cols"]
                            nulls = shared[of]["nulls"]
                            shared[own] |= {"n_cols": cols + 1, "nulls": None if nulls is None else round(nulls * shared[of]["n_rows"] * cols) / (shared[of]["n_rows"] * (cols + 1)), "result_key": held[lead]}
                        renamed(own, plans[own], of, True)
                for own, of in equal.items():
                    shared[own] = dict(shared[of])
                    renamed(own, plans[own], of, False)
                done |= {key: shared[own] | {"depth": k} for key, own in waiting.items()}
    finally:
        for view in views.values():
            spark.catalog.dropTempView(view)
        for path in paths:
            drop(spark, path)
    return done


def run_chains(spark: SparkSession, chains: list[tuple[list[tuple[str, str]], str]], prune_failed: bool = True, threads: int = 4, keep: bool = False) -> DataFrame:
    """DIGEST rows of every distinct prefix of the chains (steps, close), closing queries included. Prefixes go level by level; the
    descendants of one that failed are not run (status `pruned`). Jobs of a level run side by side. Prefixes that differ only in steps that
    they do not read, or that the optimiser turns into the same plan (columns that nothing reads, say), are run once (run_key), each with that run's seconds; so is one
    that puts no more than a constant before the columns of another of its level.

    With keep, the result of every step that others read is written once and read by all of them, so a chain of k steps runs k queries of one
    step each; these tables go at the end. Without it a prefix is composed from its texts, which leaves the optimizer the whole query; that is cheaper where steps are
    large, few read them, and these narrow them."""
    done = digests(spark, chains, prune_failed, threads, keep)
    rows = [(key, d["depth"], d["status"], d["condition"], d["n_rows"], d["n_cols"], d["nulls"], d["result_key"], d["seconds"], d["run_key"]) for key, d in done.items()]
    return spark.createDataFrame(rows, DIGEST)


def numbered(df: DataFrame) -> DataFrame:
    """df with at, the place of each row in the order that its query gives (partitions are in order, and rows within each); offsets come from one
    count a partition."""
    placed = written(df.select("*", F.spark_partition_id().alias("p_"), F.monotonically_increasing_id().alias("m_")))
    counts = placed.groupBy("p_").agg(F.count("*").alias("n_"))
    offsets = counts.select("p_", (F.sum("n_").over(Window.orderBy("p_")) - F.col("n_")).alias("o_"))  # a row a partition
    base = F.col("p_").cast("bigint") * F.lit(1 << 33)
    return placed.join(F.broadcast(offsets), "p_").withColumn("at", F.col("o_") + F.col("m_") - base).drop("p_", "m_", "o_")


def outcome(spark: SparkSession, pred: str, gold: str, mode: str = "multiset") -> int:
    """1 if both results are equal as a `multiset`, a `set`, or `ordered` rows; 0 otherwise, also if the prediction fails. Order is that of a
    closing ORDER BY: rows are numbered by a range partitioning's places, so results of any size keep their order in many tasks."""
    try:
        a, b = spark.sql(pred), spark.sql(gold)
        if len(a.columns) != len(b.columns):
            return 0
        names = [f"c{i}" for i in range(len(a.columns))]
        a, b = a.toDF(*names), b.toDF(*names)
        if mode == "ordered":
            a, b = numbered(a), numbered(b)
        if mode == "set":
            return int(a.subtract(b).isEmpty() and b.subtract(a).isEmpty())
        return int(a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty())
    except PySparkException:
        return 0
