"""Question bank: questions over the given tables with gold queries and step chains.

Texts keep to what Spark and DuckDB share. Each question: number, database, tier, question, steps (name, rationale, text),
closing query, and a gold query written without named steps. Doubles are rounded in both, a little off the ties of short
decimals, so results compare exactly."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .tables import register

HELD_OUT = ("clicks", "texts")


@dataclass(frozen=True)
class Question:
    qid: int
    db: str
    tier: str
    question: str
    steps: tuple[tuple[str, str, str], ...]
    close: str
    gold: str

    @property
    def split(self) -> str:
        return "held out" if self.db in HELD_OUT else "train"

    @property
    def named(self) -> list[tuple[str, str]]:
        return [(n, q) for n, _, q in self.steps]


_REV = "l_extendedprice * (1 - l_discount)"


def _q(qid, db, tier, question, *steps_close_gold) -> Question:
    *steps, close, gold = steps_close_gold
    return Question(qid, db, tier, question, tuple(steps), close, gold)


QUESTIONS: tuple[Question, ...] = (
    _q(1, "sales", "T3", "Which five customers have the highest mean order value in 1996?",
       ("orders96", "orders of 1996", "SELECT o_custkey, o_totalprice FROM orders WHERE year(o_orderdate) = 1996"),
       ("totals", "sum a customer", "SELECT o_custkey, sum(o_totalprice) AS total FROM orders96 GROUP BY o_custkey"),
       ("counts", "orders a customer", "SELECT o_custkey, count(*) AS n FROM orders96 GROUP BY o_custkey"),
       ("means", "mean a customer", "SELECT totals.o_custkey, total / n AS mean_value FROM totals JOIN counts ON totals.o_custkey = counts.o_custkey"),
       "SELECT c_custkey, c_name, round(mean_value + 1e-9, 2) AS mean_value FROM means JOIN customer ON o_custkey = c_custkey ORDER BY mean_value DESC, c_custkey LIMIT 5",
       "SELECT c_custkey, c_name, round(avg(o_totalprice) + 1e-9, 2) AS mean_value FROM orders JOIN customer ON o_custkey = c_custkey WHERE year(o_orderdate) = 1996 GROUP BY c_custkey, c_name ORDER BY mean_value DESC, c_custkey LIMIT 5"),
    _q(2, "sales", "T1", "How many urgent orders are worth more than 400000?",
       ("big", "urgent and large", "SELECT o_orderkey FROM orders WHERE o_totalprice > 400000 AND o_orderpriority = '1-URGENT'"),
       "SELECT count(*) AS n FROM big",
       "SELECT count(*) AS n FROM orders WHERE o_totalprice > 400000 AND o_orderpriority = '1-URGENT'"),
    _q(3, "sales", "T1", "Which returned line items have a discount of nine percent or more?",
       ("returned", "returned lines", "SELECT l_orderkey, l_partkey, l_suppkey, l_discount FROM lineitem WHERE l_returnflag = 'R'"),
       "SELECT l_orderkey, l_partkey, l_suppkey FROM returned WHERE l_discount >= 0.09",
       "SELECT l_orderkey, l_partkey, l_suppkey FROM lineitem WHERE l_returnflag = 'R' AND l_discount >= 0.09"),
    _q(4, "sales", "T2", "What is the revenue by market segment?",
       ("lines", "lines with customers", f"SELECT o_custkey, {_REV} AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey"),
       "SELECT c_mktsegment, round(sum(revenue) + 1e-5, 2) AS revenue FROM lines JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment",
       f"SELECT c_mktsegment, round(sum({_REV}) + 1e-5, 2) AS revenue FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey GROUP BY c_mktsegment"),
    _q(5, "sales", "T2", "How many orders are there by priority and status?",
       ("pairs", "group", "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY o_orderpriority, o_orderstatus"),
       "SELECT * FROM pairs ORDER BY o_orderpriority, o_orderstatus",
       "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY o_orderpriority, o_orderstatus ORDER BY 1, 2"),
    _q(6, "sales", "T2", "How many customers in each segment have no finished order?",
       ("finished", "customers with a finished order", "SELECT DISTINCT o_custkey FROM orders WHERE o_orderstatus = 'P' AND o_totalprice > 250000"),
       ("without", "the others", "SELECT c_mktsegment FROM customer LEFT JOIN finished ON c_custkey = o_custkey WHERE o_custkey IS NULL"),
       "SELECT c_mktsegment, count(*) AS n FROM without GROUP BY c_mktsegment",
       "SELECT c_mktsegment, count(*) AS n FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P' AND o_totalprice > 250000) GROUP BY c_mktsegment"),
    _q(7, "sales", "T3", "Which customers' totals exceed the mean total?",
       ("totals", "total a customer", "SELECT o_custkey, sum(o_totalprice) AS total FROM orders GROUP BY o_custkey"),
       ("mean_total", "their mean", "SELECT avg(total) AS m FROM totals"),
       "SELECT o_custkey FROM totals CROSS JOIN mean_total WHERE total > m",
       "SELECT o_custkey FROM orders GROUP BY o_custkey HAVING sum(o_totalprice) > (SELECT sum(o_totalprice) / count(DISTINCT o_custkey) FROM orders)"),
    _q(8, "sales", "T3", "What share of revenue was returned each year?",
       ("lines", "revenue by year", f"SELECT year(o_orderdate) AS y, l_returnflag, {_REV} AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey"),
       ("every", "all", "SELECT y, sum(revenue) AS total FROM lines GROUP BY y"),
       ("returned", "returned", "SELECT y, sum(revenue) AS back FROM lines WHERE l_returnflag = 'R' GROUP BY y"),
       "SELECT every.y, round(back / total, 6) AS share FROM every JOIN returned ON every.y = returned.y",
       f"SELECT year(o_orderdate) AS y, round(sum(CASE WHEN l_returnflag = 'R' THEN {_REV} ELSE 0 END) / sum({_REV}), 6) AS share FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY year(o_orderdate)"),
    _q(9, "sales", "T3", "Which ten customers placed the largest single orders?",
       ("largest", "largest order a customer", "SELECT o_custkey, max(o_totalprice) AS top FROM orders GROUP BY o_custkey"),
       "SELECT o_custkey, round(top, 2) AS top FROM largest ORDER BY top DESC, o_custkey LIMIT 10",
       "SELECT o_custkey, round(max(o_totalprice), 2) AS top FROM orders GROUP BY o_custkey ORDER BY top DESC, o_custkey LIMIT 10"),
    _q(10, "sales", "T4", "In which month did revenue jump the most?",
       ("monthly", "total by month", "SELECT year(o_orderdate) * 12 + month(o_orderdate) AS m, sum(o_totalprice) AS s FROM orders GROUP BY year(o_orderdate) * 12 + month(o_orderdate)"),
       ("jumps", "difference from the month before", "SELECT m, s - lag(s) OVER (ORDER BY m) AS d FROM monthly"),
       "SELECT m, round(d, 2) AS d FROM jumps WHERE d IS NOT NULL ORDER BY d DESC LIMIT 1",
       "SELECT m, round(d, 2) AS d FROM (SELECT m, s - lag(s) OVER (ORDER BY m) AS d FROM (SELECT year(o_orderdate) * 12 + month(o_orderdate) AS m, sum(o_totalprice) AS s FROM orders GROUP BY 1) AS a) AS b WHERE d IS NOT NULL ORDER BY d DESC LIMIT 1"),
    _q(11, "sales", "T4", "Who are the three best customers of each nation?",
       ("totals", "total a customer", "SELECT o_custkey, sum(o_totalprice) AS total FROM orders GROUP BY o_custkey"),
       ("ranked", "rank in the nation", "SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY total DESC, c_custkey) AS r FROM totals JOIN customer ON o_custkey = c_custkey"),
       "SELECT n_name, c_custkey FROM ranked JOIN nation ON c_nationkey = n_nationkey WHERE r <= 3",
       "SELECT n_name, c_custkey FROM (SELECT n_name, c_custkey, row_number() OVER (PARTITION BY n_name ORDER BY sum(o_totalprice) DESC, c_custkey) AS r FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name, c_custkey) AS x WHERE r <= 3"),
    _q(12, "sales", "T4", "Which customers ordered again within nine days?",
       ("dated", "date of the order before", "SELECT o_custkey, o_orderdate, lag(o_orderdate) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS before FROM orders"),
       "SELECT DISTINCT o_custkey FROM dated WHERE o_orderdate <= before + INTERVAL '9' DAY",
       "SELECT DISTINCT a.o_custkey FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey <> b.o_orderkey AND a.o_orderdate >= b.o_orderdate AND a.o_orderdate <= b.o_orderdate + INTERVAL '9' DAY"),
    _q(13, "catalog", "T1", "Which promotional parts have a size over 40?",
       ("promo", "promotional parts", "SELECT p_partkey, p_size FROM part WHERE p_type LIKE 'PROMO%'"),
       "SELECT p_partkey FROM promo WHERE p_size > 40", "SELECT p_partkey FROM part WHERE p_size > 40 AND p_type LIKE 'PROMO%'"),
    _q(14, "catalog", "T2", "What is the mean retail price of each brand?",
       ("means", "mean a brand", "SELECT p_brand, avg(p_retailprice) AS m FROM part GROUP BY p_brand"),
       "SELECT p_brand, round(m + 1e-9, 2) AS m FROM means", "SELECT p_brand, round(sum(p_retailprice) / count(*) + 1e-9, 2) AS m FROM part GROUP BY p_brand"),
    _q(15, "catalog", "T2", "What quantity of each part type was sold?",
       ("sold", "lines with types", "SELECT p_type, l_quantity FROM lineitem JOIN part ON l_partkey = p_partkey"),
       "SELECT p_type, sum(l_quantity) AS quantity FROM sold GROUP BY p_type", "SELECT p_type, sum(l_quantity) AS quantity FROM part JOIN lineitem ON l_partkey = p_partkey GROUP BY p_type"),
    _q(16, "catalog", "T2", "Which suppliers in debt have sales?",
       ("debt", "suppliers in debt", "SELECT s_suppkey FROM supplier WHERE s_acctbal < 0"), ("sellers", "suppliers that sold", "SELECT DISTINCT l_suppkey FROM lineitem"),
       "SELECT s_suppkey FROM debt JOIN sellers ON s_suppkey = l_suppkey", "SELECT s_suppkey FROM supplier WHERE s_acctbal < 0 AND s_suppkey IN (SELECT l_suppkey FROM lineitem)"),
    _q(17, "catalog", "T3", "Which brand has the most distinct suppliers?",
       ("pairs", "brands and suppliers", "SELECT DISTINCT p_brand, l_suppkey FROM lineitem JOIN part ON l_partkey = p_partkey"), ("counts", "suppliers a brand", "SELECT p_brand, count(*) AS n FROM pairs GROUP BY p_brand"),
       "SELECT p_brand, n FROM counts ORDER BY n DESC, p_brand LIMIT 1", "SELECT p_brand, count(DISTINCT l_suppkey) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand ORDER BY n DESC, p_brand LIMIT 1"),
    _q(18, "catalog", "T3", "Which large parts were never sold in great number?",
       ("sold", "parts sold in number", "SELECT DISTINCT l_partkey FROM lineitem WHERE l_quantity > 45"),
       "SELECT p_partkey FROM part LEFT JOIN sold ON p_partkey = l_partkey WHERE l_partkey IS NULL AND p_size > 25", "SELECT p_partkey FROM part WHERE p_size > 25 AND p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)"),
    _q(19, "catalog", "T3", "Which parts cost more than the mean of their type?",
       ("type_mean", "mean a type", "SELECT p_type AS kind, avg(p_retailprice) AS m FROM part GROUP BY p_type"),
       "SELECT p_partkey FROM part JOIN type_mean ON p_type = kind WHERE p_retailprice > m", "SELECT p_partkey FROM (SELECT p_partkey, p_retailprice, avg(p_retailprice) OVER (PARTITION BY p_type) AS m FROM part) AS x WHERE p_retailprice > m"),
    _q(20, "catalog", "T4", "Which suppliers hold at least two percent of a brand's revenue?",
       ("pair_revenue", "revenue by brand and supplier", f"SELECT p_brand, l_suppkey, sum({_REV}) AS r FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand, l_suppkey"),
       ("brand_revenue", "revenue by brand", "SELECT p_brand AS brand, sum(r) AS total FROM pair_revenue GROUP BY p_brand"),
       "SELECT p_brand, l_suppkey FROM pair_revenue JOIN brand_revenue ON p_brand = brand WHERE r >= 0.02 * total",
       f"SELECT p_brand, l_suppkey FROM (SELECT p_brand, l_suppkey, sum({_REV}) AS r, sum(sum({_REV})) OVER (PARTITION BY p_brand) AS total FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand, l_suppkey) AS x WHERE r >= 0.02 * total"),
    _q(21, "catalog", "T4", "How does each type's median discount compare with that of all sales?",
       ("medians", "median a type", "SELECT p_type, median(l_discount) AS m FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_type"), ("overall", "median of all", "SELECT median(l_discount) AS a FROM lineitem"),
       "SELECT p_type, round(m - a, 6) AS d FROM medians CROSS JOIN overall", "SELECT p_type, round(median(l_discount) - (SELECT median(l_discount) FROM lineitem), 6) AS d FROM part JOIN lineitem ON l_partkey = p_partkey GROUP BY p_type"),
    _q(22, "catalog", "T4", "Which part sells most in number by supplier nation?",
       ("sold", "quantity by nation and part", "SELECT s_nationkey, l_partkey, sum(l_quantity) AS q FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_nationkey, l_partkey"),
       ("ranked", "rank in the nation", "SELECT s_nationkey, l_partkey, q, row_number() OVER (PARTITION BY s_nationkey ORDER BY q DESC, l_partkey) AS r FROM sold"),
       "SELECT n_name, l_partkey, q FROM ranked JOIN nation ON s_nationkey = n_nationkey WHERE r = 1",
       "SELECT n_name, l_partkey, q FROM (SELECT n_name, l_partkey, sum(l_quantity) AS q, row_number() OVER (PARTITION BY n_name ORDER BY sum(l_quantity) DESC, l_partkey) AS r FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name, l_partkey) AS x WHERE r = 1"),
    _q(23, "geo", "T1", "Which nations lie in Asia?",
       ("asia", "the region", "SELECT r_regionkey FROM region WHERE r_name = 'ASIA'"), "SELECT n_name FROM nation JOIN asia ON n_regionkey = r_regionkey", "SELECT n_name FROM nation, region WHERE n_regionkey = r_regionkey AND r_name = 'ASIA'"),
    _q(24, "geo", "T2", "How many customers are there in each region?",
       ("placed", "customers with regions", "SELECT n_regionkey FROM customer JOIN nation ON c_nationkey = n_nationkey"), "SELECT r_name, count(*) AS n FROM placed JOIN region ON n_regionkey = r_regionkey GROUP BY r_name",
       "SELECT r_name, count(c_custkey) AS n FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey GROUP BY r_name"),
    _q(25, "geo", "T2", "What are the mean balances of customers and suppliers by nation?",
       ("buyers", "customers", "SELECT c_nationkey, avg(c_acctbal) AS c FROM customer GROUP BY c_nationkey"), ("sellers", "suppliers", "SELECT s_nationkey, avg(s_acctbal) AS s FROM supplier GROUP BY s_nationkey"),
       "SELECT coalesce(c_nationkey, s_nationkey) AS nation_, round(c + 1e-9, 2) AS c, round(s + 1e-9, 2) AS s FROM buyers FULL JOIN sellers ON c_nationkey = s_nationkey",
       "SELECT n_nationkey AS nation_, round((SELECT avg(c_acctbal) FROM customer WHERE c_nationkey = n_nationkey) + 1e-9, 2) AS c, round((SELECT avg(s_acctbal) FROM supplier WHERE s_nationkey = n_nationkey) + 1e-9, 2) AS s FROM nation WHERE n_nationkey IN (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier)"),
    _q(26, "geo", "T3", "Which nations have more suppliers per customer than the average nation?",
       ("buyers", "customers", "SELECT c_nationkey, count(*) AS c FROM customer GROUP BY c_nationkey"), ("sellers", "suppliers", "SELECT s_nationkey, count(*) AS s FROM supplier GROUP BY s_nationkey"),
       ("ratios", "suppliers per customer", "SELECT c_nationkey, s * 1.0e0 / c AS r FROM buyers JOIN sellers ON c_nationkey = s_nationkey"), ("mean_ratio", "their mean", "SELECT avg(r) AS m FROM ratios"),
       "SELECT n_name FROM ratios CROSS JOIN mean_ratio JOIN nation ON c_nationkey = n_nationkey WHERE r > m",
       "SELECT n_name FROM (SELECT n_name, r, avg(r) OVER () AS m FROM (SELECT n_name, count(DISTINCT s_suppkey) * 1.0e0 / count(DISTINCT c_custkey) AS r FROM nation JOIN customer ON c_nationkey = n_nationkey JOIN supplier ON s_nationkey = n_nationkey GROUP BY n_name) AS a) AS b WHERE r > m"),
    _q(27, "geo", "T3", "What is the revenue between each pair of different nations?",
       ("lines", "lines with both nations", f"SELECT c_nationkey, s_nationkey, {_REV} AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"),
       "SELECT c_nationkey, s_nationkey, round(sum(revenue) + 1e-5, 2) AS revenue FROM lines WHERE c_nationkey <> s_nationkey GROUP BY c_nationkey, s_nationkey",
       f"SELECT c_nationkey, s_nationkey, round(sum({_REV}) + 1e-5, 2) AS revenue FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey GROUP BY c_nationkey, s_nationkey"),
    _q(28, "geo", "T4", "What is the order value by region and nation, with subtotals?",
       ("placed", "orders with nations", "SELECT r_name, n_name, o_totalprice FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"),
       "SELECT r_name, n_name, round(sum(o_totalprice), 2) AS v FROM placed GROUP BY ROLLUP (r_name, n_name)",
       "SELECT r_name, n_name, round(sum(o_totalprice), 2) AS v FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey GROUP BY GROUPING SETS ((r_name, n_name), (r_name), ())"),
    _q(29, "clicks", "T2", "How many events of each type are there each day?",
       ("days", "events by day", "SELECT event_type, CAST(ts AS DATE) AS day FROM events"), "SELECT event_type, day, count(*) AS n FROM days GROUP BY event_type, day", "SELECT event_type, CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY event_type, CAST(ts AS DATE)"),
    _q(30, "clicks", "T3", "What share of users with a view bought within a day of one?",
       ("views", "views", "SELECT user_id, ts FROM events WHERE event_type = 'view'"), ("buys", "purchases", "SELECT user_id AS buyer, ts AS bought FROM events WHERE event_type = 'purchase'"),
       ("hits", "buyers", "SELECT DISTINCT user_id FROM views JOIN buys ON user_id = buyer AND bought >= ts AND bought <= ts + INTERVAL '1' DAY"),
       "SELECT round((SELECT count(*) FROM hits) * 1.0e0 / (SELECT count(DISTINCT user_id) FROM views), 6) AS share",
       "SELECT round(count(DISTINCT CASE WHEN EXISTS (SELECT 1 FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL '1' DAY) THEN a.user_id END) * 1.0e0 / count(DISTINCT a.user_id), 6) AS share FROM events a WHERE a.event_type = 'view'"),
    _q(31, "clicks", "T4", "Which user had the longest pause between events?",
       ("pauses", "seconds since the event before", "SELECT user_id, epoch(ts) - epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS s FROM events"),
       "SELECT user_id, CAST(floor(max(s)) AS BIGINT) AS longest FROM pauses GROUP BY user_id ORDER BY longest DESC, user_id LIMIT 1",
       "SELECT user_id, CAST(floor(max(s)) AS BIGINT) AS longest FROM (SELECT user_id, epoch(lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) - epoch(ts) AS s FROM events) AS x GROUP BY user_id ORDER BY longest DESC, user_id LIMIT 1"),
    _q(32, "clicks", "T4", "How many sessions, with pauses under half an hour, does each user have?",
       ("flags", "starts of sessions", "SELECT user_id, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL '30' MINUTE THEN 0 ELSE 1 END AS new FROM events"),
       "SELECT user_id, sum(new) AS sessions FROM flags GROUP BY user_id",
       "SELECT user_id, count(*) AS sessions FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events) AS x WHERE before IS NULL OR ts > before + INTERVAL '30' MINUTE GROUP BY user_id"),
    _q(33, "texts", "T2", "What share of labelled documents of each source is good?",
       ("marked", "labelled documents", "SELECT source, quality FROM documents JOIN labels ON documents.doc_id = labels.doc_id"), "SELECT source, round(avg(quality), 6) AS share FROM marked GROUP BY source",
       "SELECT source, round(sum(quality) * 1.0e0 / count(*), 6) AS share FROM labels JOIN documents ON documents.doc_id = labels.doc_id GROUP BY source"),
    _q(34, "texts", "T3", "Which languages are more often toxic than all documents?",
       ("marked", "labelled documents", "SELECT lang, toxic FROM documents JOIN labels ON documents.doc_id = labels.doc_id"), ("rates", "rate a language", "SELECT lang, avg(toxic) AS r FROM marked GROUP BY lang"), ("overall", "rate of all", "SELECT avg(toxic) AS a FROM marked"),
       "SELECT lang FROM rates CROSS JOIN overall WHERE r > a", "SELECT lang FROM documents JOIN labels ON documents.doc_id = labels.doc_id GROUP BY lang HAVING avg(toxic) > (SELECT avg(toxic) FROM labels WHERE doc_id IN (SELECT doc_id FROM documents))"),
    _q(35, "texts", "T3", "How many documents of each source have an exact copy in it?",
       ("hashed", "digests", "SELECT source, md5(text) AS h FROM documents"), ("copies", "repeated digests", "SELECT source, h, count(*) AS n FROM hashed GROUP BY source, h HAVING count(*) > 1"),
       "SELECT source, sum(n) AS documents_ FROM copies GROUP BY source", "SELECT source, count(*) AS documents_ FROM (SELECT source, count(*) OVER (PARTITION BY source, text) AS n FROM documents) AS x WHERE n > 1 GROUP BY source"),
    _q(36, "texts", "T4", "What is the mean length of assistant turns over that of user turns by conversation?",
       ("lengths", "mean length a role", "SELECT conv_id, role, avg(length(text)) AS m FROM conversations GROUP BY conv_id, role"),
       ("wide", "both roles", "SELECT conv_id, max(CASE WHEN role = 'assistant' THEN m END) AS a, max(CASE WHEN role = 'user' THEN m END) AS u FROM lengths GROUP BY conv_id"),
       "SELECT conv_id, round(a / u, 6) AS ratio FROM wide WHERE u > 0 AND a IS NOT NULL",
       "SELECT conv_id, round(avg(CASE WHEN role = 'assistant' THEN length(text) END) / avg(CASE WHEN role = 'user' THEN length(text) END), 6) AS ratio FROM conversations GROUP BY conv_id HAVING count(CASE WHEN role = 'assistant' THEN 1 END) > 0 AND count(CASE WHEN role = 'user' THEN 1 END) > 0"),
)

FANOUT = (
    "SELECT c_custkey, c_name, round(sum(o_totalprice) / count(DISTINCT o_orderkey) + 1e-9, 2) AS mean_value FROM orders JOIN lineitem ON l_orderkey = o_orderkey "
    "JOIN customer ON o_custkey = c_custkey WHERE year(o_orderdate) = 1996 GROUP BY c_custkey, c_name ORDER BY mean_value DESC, c_custkey LIMIT 5"
)


def prepare(spark: SparkSession, sf_dir: str) -> None:
    """Views of all tables, and the one function that the shared dialect lacks."""
    register(spark, sf_dir)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION epoch(t TIMESTAMP) RETURNS DOUBLE RETURN unix_micros(t) / 1000000.0D")


def bank_steps(spark: SparkSession) -> DataFrame:
    """The bank as STEP rows (kinds `step` and `close`), traj_id `gold`."""
    rows = []
    for q in QUESTIONS:
        rows += [(q.qid, "gold", k, n, r, s, "step") for k, (n, r, s) in enumerate(q.steps, 1)]
        rows.append((q.qid, "gold", len(q.steps) + 1, "answer", "answer", q.close, "close"))
    return spark.createDataFrame(rows, "qid bigint, traj_id string, no int, name string, rationale string, sql string, kind string")


def wording(question: str, style: str, qid: int) -> str:
    """Variants of a question's text: `synonym` swaps column words, `realistic` drops their mention, `knowledge` hides a definition."""
    swaps = {"synonym": {"customers": "buyers", "orders": "purchases", "revenue": "turnover", "parts": "articles", "suppliers": "vendors", "mean": "average", "nations": "countries"}, "realistic": {"market ": "", "retail ": "", "line ": "", "labelled ": ""}, "knowledge": {"urgent": "top-priority", "finished": "closed", "in debt": "below zero", "returned": "sent back"}}[style]
    for a, b in swaps.items():
        question = question.replace(a, b)
    return question
