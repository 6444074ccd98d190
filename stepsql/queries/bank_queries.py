"""The question bank, run as chains; gold queries without named steps check them."""

from __future__ import annotations

from pyspark.errors import AnalysisException, ParseException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stepsql.operators import execute as ex
from stepsql.operators.chains import compose, flatten
from stepsql.sources import bank
from stepsql.sources.tables import table

from .registry import query


def _question(q: bank.Question) -> None:
    @query(q.gold, f"bank_{q.qid:02d}")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        bank.prepare(spark, sf_dir)
        return spark.sql(compose(q.named, q.close))


for _q in bank.QUESTIONS:
    _question(_q)


@query(bank.QUESTIONS[0].gold)
def worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Top five customers by mean order value, by steps."""
    bank.prepare(spark, sf_dir)
    return spark.sql(compose(bank.QUESTIONS[0].named, bank.QUESTIONS[0].close))


@query(bank.FANOUT)
def worked_example_fanout(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with a needless join that multiplies orders: wrong by design."""
    bank.prepare(spark, sf_dir)
    return spark.sql(bank.FANOUT)


@query(compose(bank.QUESTIONS[7].named, bank.QUESTIONS[7].close))
def flat_vs_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A chain flattened to one query; the SQL is the chain."""
    bank.prepare(spark, sf_dir)
    q = bank.QUESTIONS[7]
    return spark.sql(flatten(q.named, q.close))


@query("WITH a AS (SELECT o_custkey, o_totalprice FROM orders WHERE year(o_orderdate) = 1996), b AS (SELECT o_custkey FROM a GROUP BY o_custkey) SELECT 1 AS depth, count(*) AS n_rows, 2 AS n_cols FROM a UNION ALL SELECT 2, count(*), 2 FROM b UNION ALL SELECT 3, count(*), 2 FROM b UNION ALL SELECT 4, count(*), 2 FROM b UNION ALL SELECT 5, least(count(*), 5), 3 FROM b")
def step_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Row counts of every prefix of the worked example, each step run once on the kept results of those before it."""
    bank.prepare(spark, sf_dir)
    q = bank.QUESTIONS[0]
    return ex.run_chains(spark, [(q.named, q.close)], keep=True).select("depth", "n_rows", "n_cols")


@query()
def validate_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every chain of the bank, and each seeded corruption, with the reason to reject it."""
    bank.prepare(spark, sf_dir)
    rows = []
    for q in bank.QUESTIONS:
        rows.append((q.qid, "gold", *ex.validate(spark, q.named, q.close)))
        first, *rest = q.named
        rows.append((q.qid, "misspelt", *ex.validate(spark, [(first[0], first[1].replace("SELECT", "SELEC", 1)), *rest], q.close)))
        rows.append((q.qid, "later name", *ex.validate(spark, [("early", f"SELECT * FROM {first[0]}"), *q.named], q.close)))
        rows.append((q.qid, "repeated", *ex.validate(spark, [*q.named, first], q.close)))
    return spark.createDataFrame(rows, "qid bigint, variant string, ok boolean, reason string, step int")


@query()
def decompose_bank(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every gold query rewritten as a chain by rule: its steps, how many, and whether the chain's result is gold's."""
    from stepsql.operators.chains import decompose

    bank.prepare(spark, sf_dir)

    def columns(text: str) -> list[str] | None:
        try:
            return spark.sql(text).columns
        except (AnalysisException, ParseException):
            return None

    made = {q.qid: decompose(q.gold, columns) for q in bank.QUESTIONS}
    done = ex.digests(spark, [([], q.gold) for q in bank.QUESTIONS] + [made[q.qid] for q in bank.QUESTIONS], threads=8, keep=True)
    rows = []
    for q in bank.QUESTIONS:
        steps, close = made[q.qid]
        rows.append((q.qid, len(steps), compose(steps, close), int(done[ex.prefix_keys(steps, close)[-1]]["result_key"] == done[ex.prefix_keys([], q.gold)[-1]]["result_key"])))
    return spark.createDataFrame(rows, "qid bigint, n_steps int, query string, outcome int")


@query(compose(bank.QUESTIONS[0].named, bank.QUESTIONS[0].close))
def composed_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A chain gathered from step rows and composed by column, run."""
    from stepsql.operators.chains import chains_from_steps, compose_column

    bank.prepare(spark, sf_dir)
    return spark.sql(compose_column(chains_from_steps(bank.bank_steps(spark).where("qid = 1"))).first()["query"])


@query("""WITH q(held, qid, question) AS (
  SELECT true, item_id, text FROM benchmark UNION ALL SELECT false, conv_id * 100000 + turn, text FROM conversations WHERE role = 'user'),
w AS (SELECT held, qid, unnest(string_split_regex(lower(question), '[^a-z0-9]+')) AS word FROM q),
c AS (SELECT held, qid, word, count(*)::DOUBLE AS c FROM w WHERE word <> '' GROUP BY ALL),
n AS (SELECT *, c / sqrt(sum(c * c) OVER (PARTITION BY held, qid)) AS w FROM c),
p AS (SELECT a.qid, b.qid AS seed, round(sum(a.w * b.w), 9) AS similarity FROM n a JOIN n b USING (word) WHERE a.held AND NOT b.held GROUP BY ALL)
SELECT qid::BIGINT AS qid, seed::BIGINT AS seed, round(similarity, 6) + 0.0 AS similarity, row_number() OVER (PARTITION BY qid ORDER BY similarity DESC, seed)::INTEGER AS rank
FROM p QUALIFY rank <= 5""")
def few_shot_examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five examples for each held-out item of the benchmark: the users' turns most like it, whose conversations a prompt would show."""
    from stepsql.operators.retrieve import nearest_examples

    asked = table(spark, sf_dir, "benchmark").select(F.col("item_id").cast("bigint").alias("qid"), F.col("text").alias("question"))
    turns = table(spark, sf_dir, "conversations").where("role = 'user'")
    seeds = turns.select((F.col("conv_id").cast("bigint") * 100000 + F.col("turn")).alias("qid"), F.col("text").alias("question"))
    return nearest_examples(asked, seeds).withColumn("similarity", F.round("similarity", 6) + 0.0)
