"""Every chain that the bank's menus allow, run once: what experiments on the bank stand on.

A menu has, for every slot of a question's chain (its steps and the closing query), the gold text and mutated ones, each of a known error
type. A chain takes one option a slot. All chains of the menus are run with shared prefixes; a row of the result is a prefix of a chain
with its digest, and the chain's outcome against gold. Sizes depend on the bank and on `most`, not on the tables."""

from __future__ import annotations

import itertools
import re
from collections.abc import Sequence
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from stepsql.sources.bank import Question
from stepsql.sources.shared import written
from stepsql.sources.tables import NAMES, dealt

from .chains import compose, flatten
from .execute import digests, hashing, prefix_keys
from .mutate import MUTATIONS, infer

#: chain is the option numbers so far, joined by '-'; prefix_key names the texts so far; next_token is the option taken.
RUN = (
    "qid bigint, db string, split string, tier string, chain string, whole string, slot int, slots int, token int, error_type string, name string, sql string, "
    "prefix_key string, first_error string, slips int, inferred string, outcome int, gold_key string"
)


LANES = 3  # questions whose chains run side by side
NEEDLESS = "needless steps"  # right, but no step of the chain is read


@dataclass(frozen=True)
class Option:
    kind: str  # error type, '' for gold, NEEDLESS
    sql: str


def menu(q: Question, most: int = 24) -> list[list[Option]]:
    """Options of every slot, gold first; chains of two steps or more have a closing query that needs none of them. Mutated texts are added in turn, later slots first and new error types first, while the question
    has at most so many chains."""
    texts = [t for _, t in q.named] + [q.close]
    out = [[Option("", t)] for t in texts]
    size, seen = 1, set()
    if len(texts) > 2:  # a closing query that does all the work again, and leaves the steps unread
        out[-1].append(Option(NEEDLESS, q.gold))
        size = 2
    for again in (False, False, True):
        for k in reversed(range(len(texts))):
            for kind, pattern, put in MUTATIONS:
                new = re.sub(pattern, put, texts[k], count=1)
                if new == texts[k] or kind in {o.kind for o in out[k]} or (kind in seen and not again) or new in {o.sql for o in out[k]}:
                    continue
                grown = size // len(out[k]) * (len(out[k]) + 1)
                if grown <= most:
                    out[k].append(Option(kind, new))
                    seen.add(kind)
                    size = grown
                break
    return out


def menu_rows(questions: Sequence[Question], most: int = 24) -> list[tuple]:
    """(qid, slot, token, error_type, sql) of every option."""
    return [(q.qid, slot, token, o.kind, o.sql) for q in questions for slot, options in enumerate(menu(q, most), 1) for token, o in enumerate(options)]


def heaviest_first(spark: SparkSession, questions: Sequence[Question], most: int = 24) -> list[int]:
    """Numbers of the questions, those first whose menus sort a whole result in one task (a window without partitions), then by the bytes of the tables that their texts name: what runs
    longest is not left for the end, when the other lanes are done."""
    size = {t: int(str(spark.table(t)._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) for t in NAMES if spark.catalog.tableExists(t)}

    def weight(q: Question) -> tuple[bool, int]:
        texts = [o.sql for options in menu(q, most) for o in options]
        return any(re.search(r"(?i)\bOVER \(ORDER BY\b", t) for t in texts), sum(size.get(w, 0) for t in texts for w in set(re.findall(r"\w+", t.lower())))

    return [q.qid for q in sorted(questions, key=weight, reverse=True)]


def run_menus(spark: SparkSession, questions: Sequence[Question], most: int = 24, threads: int = 8) -> DataFrame:
    """RUN columns and the digest (status, condition, n_rows, n_cols, nulls, result_key, seconds, run_key) for every prefix of every chain."""
    chains, rows = {}, []
    for q in questions:
        options = menu(q, most)
        want = prefix_keys([], q.gold)[-1]
        chains[q.qid] = [([], q.gold)]
        for picks in itertools.product(*[range(len(o)) for o in options]):
            taken = [options[k][p] for k, p in enumerate(picks)]
            steps, close = [(n, o.sql) for (n, _), o in zip(q.named, taken)], taken[-1].sql
            keys = prefix_keys(steps, close)
            chains[q.qid].append((steps, close))
            names = [n for n, _ in steps] + ["answer"]
            kinds = [o.kind for o in taken]
            first = next((k for k in kinds if k), "")
            text, right = compose(steps, close), compose(q.named, q.close)
            for slot, key in enumerate(keys, 1):
                rows.append(
                    (q.qid, q.db, q.split, q.tier, "-".join(map(str, picks[:slot])), "-".join(map(str, picks)), slot, len(keys), picks[slot - 1], kinds[slot - 1], names[slot - 1],
                     taken[slot - 1].sql, key, first, sum(map(bool, kinds)), (text, right), want)
                )
    found: dict[str, dict] = {}
    # a question at a time in each lane, as its kept steps go when it is done
    with hashing(spark), dealt(spark), ThreadPoolExecutor(LANES) as lanes:
        for part in lanes.map(lambda qid: digests(spark, chains[qid], threads=max(1, threads // LANES), keep=True), heaviest_first(spark, questions, most)):
            found |= part
    last = {(r[0], r[5]): found[r[12]] for r in rows if r[6] == r[7]}
    out = []
    for r in rows:
        end, (text, right), want = last[r[0], r[5]], r[15], found[r[16]]["result_key"]
        outcome = int(end["status"] == "ok" and end["result_key"] == want)
        failed = "" if outcome else infer(text, right, "invalid" if end["status"] in ("invalid", "pruned") else end["status"], end["condition"])
        d = found[r[12]]
        out.append((*r[:15], failed, outcome, want, *(d[k] for k in ("status", "condition", "n_rows", "n_cols", "nulls", "result_key", "seconds", "run_key"))))
    return spark.createDataFrame(out, RUN + ", status string, condition string, n_rows bigint, n_cols int, nulls double, result_key string, seconds double, run_key string")


def run_flat(spark: SparkSession, questions: Sequence[Question], most: int = 24, threads: int = 8, gold_keys: dict[int, str] | None = None) -> DataFrame:
    """qid, whole, flat_status, flat_outcome: the gold chain and each chain of one slip of every menu, flattened to one query without named steps. Gold queries
    whose result_key is known are not run again."""
    texts = []
    for q in questions:
        options = menu(q, most)
        for picks in itertools.product(*[range(len(o)) for o in options]):
            if sum(map(bool, picks)) <= 1:
                taken = [options[k][p].sql for k, p in enumerate(picks)]
                texts.append((q, "-".join(map(str, picks)), flatten([(n, t) for (n, _), t in zip(q.named, taken)], taken[-1])))
    golds = {q.qid: q.gold for q in questions if q.qid not in (gold_keys or {})}
    done = digests(spark, [([], t) for *_, t in texts] + [([], g) for g in golds.values()], threads=threads)
    want = {**(gold_keys or {}), **{qid: done[prefix_keys([], g)[-1]]["result_key"] for qid, g in golds.items()}}
    rows = []
    for q, whole, text in texts:
        got = done[prefix_keys([], text)[-1]]
        rows.append((q.qid, whole, got["status"], int(got["status"] == "ok" and got["result_key"] == want[q.qid])))
    return spark.createDataFrame(rows, "qid bigint, whole string, flat_status string, flat_outcome int")


_DONE: dict[tuple[str, str], str] = {}


def kept(spark: SparkSession, sf_dir: str, name: str, make) -> DataFrame:
    """make() as a table that is written once a session and folder; it is made again where its files are gone."""
    key = (spark.sparkContext.applicationId, f"{sf_dir}#{name}")
    if key in _DONE:
        try:
            return spark.read.parquet(_DONE[key])
        except Exception as gone:  # noqa: BLE001 - any reader's error for a path that was cleared
            if "PATH_NOT_FOUND" not in str(gone):
                raise
    df = written(make())
    _DONE[key] = df.inputFiles()[0].rsplit("/", 1)[0]
    return df
