"""Question suites: families of questions with golds over the given tables, one question per parameter row.

Suite A stands for the first public benchmark, B for the second, C for the third; C is held out of training. Golds keep
to SQL that Spark and DuckDB read alike; sums go over decimals so that engines agree to the last digit.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import duck_number, number
from ..sources.load import sql as run_sql

MONEY = "CAST({0} AS DECIMAL(18, 2))"
REVENUE = "CAST(SUM(CAST(l_extendedprice * (1 - l_discount) AS DECIMAL(18, 4))) AS DOUBLE)"


@dataclass(frozen=True)
class Family:
    """``params``: SQL for parameter rows with columns p1, p2; ``default``: the values of the plain gold query; ``duck``:
    the gold with those values for DuckDB, where the engines spell a function differently."""

    id: str
    db: str
    tier: str
    question: str
    gold: str
    params: str
    default: tuple[str, str] = ("", "")
    duck: str = ""

    @property
    def suite(self) -> str:
        return self.id[0]

    @property
    def used(self) -> tuple[str, ...]:
        """Parameters that the gold or the question names; others make no different question."""
        return tuple(p for p in ("p1", "p2") if "{" + p + "}" in self.gold + self.question)

    def text(self, p1: str | None = None, p2: str | None = None) -> str:
        return self.gold.replace("{p1}", p1 or self.default[0]).replace("{p2}", p2 or self.default[1])


_FLAGS = "SELECT DISTINCT l_returnflag AS p1, CAST(year(l_shipdate) AS STRING) AS p2 FROM lineitem"
_PRICES = "SELECT DISTINCT o_orderstatus AS p1, CAST(CAST(floor(o_totalprice / 10000) AS BIGINT) * 10000 AS STRING) AS p2 FROM orders"
_SEGMENTS = "SELECT DISTINCT c_mktsegment AS p1, CAST(c_nationkey AS STRING) AS p2 FROM customer"
_BRANDS = "SELECT DISTINCT p_brand AS p1, CAST(p_size AS STRING) AS p2 FROM part"
_REGIONS = "SELECT DISTINCT r_name AS p1, '0' AS p2 FROM region"
_YEARS = "SELECT DISTINCT CAST(year(o_orderdate) AS STRING) AS p1, o_orderpriority AS p2 FROM orders"
_NATIONS = "SELECT DISTINCT CAST(n_nationkey AS STRING) AS p1, n_name AS p2 FROM nation"
_TYPES = "SELECT DISTINCT event_type AS p1, CAST(day(ts) AS STRING) AS p2 FROM events"
_LANGS = "SELECT DISTINCT lang AS p1, source AS p2 FROM documents"
_ROLES = "SELECT DISTINCT role AS p1, CAST(turn AS STRING) AS p2 FROM conversations"
_LABELS = "SELECT DISTINCT CAST(label AS STRING) AS p1, '0' AS p2 FROM embeddings"

FAMILIES: tuple[Family, ...] = (
    Family("A01", "retail", "simple", "What is the revenue of items with return flag {p1} shipped in {p2}?",
           f"SELECT {REVENUE} AS revenue FROM lineitem WHERE l_returnflag = '{{p1}}' AND year(l_shipdate) = {{p2}}", _FLAGS, ("A", "1996")),
    Family("A02", "retail", "simple", "How many orders with status {p1} cost more than {p2}?",
           "SELECT COUNT(*) AS n FROM orders WHERE o_orderstatus = '{p1}' AND o_totalprice > {p2}", _PRICES, ("F", "100000")),
    Family("A03", "retail", "simple", "How many {p1} customers of nation {p2} have a negative balance?",
           "SELECT COUNT(*) AS n FROM customer WHERE c_mktsegment = '{p1}' AND c_nationkey = {p2} AND c_acctbal < 0", _SEGMENTS, ("BUILDING", "3")),
    Family("A04", "retail", "simple", "Which types does brand {p1} have above size {p2}?",
           "SELECT DISTINCT p_type FROM part WHERE p_brand = '{p1}' AND p_size > {p2}", _BRANDS, ("Brand#17", "5")),
    Family("A05", "retail", "moderate", "What is the revenue of each nation of {p1}?",
           f"SELECT n_name, {REVENUE} AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = '{{p1}}' GROUP BY n_name", _REGIONS, ("ASIA", "0")),
    Family("A06", "retail", "moderate", "Which ten customers ordered most in {p1}?",
           f"SELECT c_custkey, CAST(SUM({MONEY.format('o_totalprice')}) AS DOUBLE) AS total FROM customer JOIN orders ON c_custkey = o_custkey WHERE year(o_orderdate) = {{p1}} GROUP BY c_custkey ORDER BY total DESC, c_custkey LIMIT 10", _YEARS, ("1997", "")),
    Family("A07", "retail", "moderate", "Which share of items ordered in {p1} belongs to {p2} orders?",
           "SELECT ROUND(CAST(SUM(CASE WHEN o_orderpriority = '{p2}' THEN 1 ELSE 0 END) AS DOUBLE) * 100 / COUNT(*), 6) AS share FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE year(o_orderdate) = {p1}", _YEARS, ("1998", "5-LOW")),
    Family("A08", "retail", "moderate", "Which suppliers of nation {p1} give over 5 % discount on average?",
           "SELECT s_suppkey, COUNT(*) AS n FROM supplier JOIN lineitem ON s_suppkey = l_suppkey WHERE s_nationkey = {p1} GROUP BY s_suppkey HAVING SUM(CAST(l_discount AS DECIMAL(18, 2))) > 0.05 * COUNT(*)", _NATIONS, ("3", "")),
    Family("A09", "retail", "challenging", "How many orders of {p1} cost more than their customer's mean?",
           "SELECT COUNT(*) AS n FROM orders JOIN (SELECT o_custkey AS k, AVG(o_totalprice) AS mean FROM orders GROUP BY o_custkey) AS m ON o_custkey = m.k WHERE o_totalprice > m.mean + 0.01 AND year(o_orderdate) = {p1}", _YEARS, ("1996", "")),
    Family("A10", "retail", "challenging", "How many parts does no supplier of nation {p1} sell?",
           "SELECT COUNT(*) AS n FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE l_partkey = p_partkey AND s_nationkey = {p1})", _NATIONS, ("3", "")),
    Family("A11", "retail", "challenging", "Which three brands sell most pieces in each region, sizes above {p2}?",
           "SELECT r_name, p_brand, pieces FROM (SELECT r_name, p_brand, pieces, ROW_NUMBER() OVER (PARTITION BY r_name ORDER BY pieces DESC, p_brand) AS place FROM (SELECT r_name, p_brand, SUM(l_quantity) AS pieces FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE p_size > {p2} GROUP BY r_name, p_brand) AS sold) AS ranked WHERE place <= 3", _BRANDS, ("", "5")),
    Family("A12", "retail", "challenging", "Which customers ordered in {p1} at {p2} priority but never in 1997?",
           "SELECT o_custkey FROM orders WHERE year(o_orderdate) = {p1} AND o_orderpriority = '{p2}' EXCEPT SELECT o_custkey FROM orders WHERE year(o_orderdate) = 1997", _YEARS, ("1996", "1-URGENT")),
    Family("B01", "retail", "easy", "Which nations lie in region {p1}?", "SELECT n_name FROM nation WHERE n_regionkey = {p1}",
           "SELECT DISTINCT CAST(r_regionkey AS STRING) AS p1, r_name AS p2 FROM region", ("1", "")),
    Family("B02", "retail", "easy", "How many parts does {p1} have?", "SELECT COUNT(*) AS n FROM part WHERE p_brand = '{p1}'", _BRANDS, ("Brand#17", "")),
    Family("B03", "retail", "easy", "Which suppliers of nation {p1} are in credit?", "SELECT s_name FROM supplier WHERE s_nationkey = {p1} AND s_acctbal > 0", _NATIONS, ("3", "")),
    Family("B04", "retail", "medium", "Which nations lie in {p1}?", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = '{p1}'", _REGIONS, ("ASIA", "")),
    Family("B05", "retail", "medium", "How many {p1} customers has each nation?", "SELECT n_name, COUNT(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_mktsegment = '{p1}' GROUP BY n_name", _SEGMENTS, ("BUILDING", "")),
    Family("B06", "retail", "medium", "Which five parts of {p1} cost most?", "SELECT p_partkey, p_retailprice FROM part WHERE p_brand = '{p1}' ORDER BY p_retailprice DESC, p_partkey LIMIT 5", _BRANDS, ("Brand#17", "")),
    Family("B07", "retail", "hard", "How many orders of {p1} come from building customers?", "SELECT COUNT(*) AS n FROM orders WHERE year(o_orderdate) = {p1} AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')", _YEARS, ("1997", "")),
    Family("B08", "retail", "hard", "How many items of flag {p1} have the largest quantity?", "SELECT COUNT(*) AS n FROM lineitem WHERE l_returnflag = '{p1}' AND l_quantity = (SELECT MAX(l_quantity) FROM lineitem)", _FLAGS, ("A", "")),
    Family("B09", "retail", "hard", "Which nations have over one supplier beyond region nation {p1}?", "SELECT s_nationkey, COUNT(*) AS n FROM supplier WHERE s_nationkey <> {p1} GROUP BY s_nationkey HAVING COUNT(*) > 1 ORDER BY n DESC, s_nationkey", _NATIONS, ("3", "")),
    Family("B10", "retail", "extra", "Which customers of segment {p1} have only cheap orders or are in debt?", "SELECT c_custkey FROM customer WHERE c_mktsegment = '{p1}' AND c_acctbal < 0 UNION SELECT o_custkey FROM orders GROUP BY o_custkey HAVING MAX(o_totalprice) < 50000", _SEGMENTS, ("BUILDING", "")),
    Family("B11", "retail", "extra", "Which parts of {p1} were never sold in a quantity below two?", "SELECT p_partkey FROM part WHERE p_brand = '{p1}' AND NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity < 2)", _BRANDS, ("Brand#17", "")),
    Family("B12", "retail", "extra", "Which nations have both customers in segment {p1} and suppliers?", "SELECT c_nationkey AS nation FROM customer WHERE c_mktsegment = '{p1}' INTERSECT SELECT s_nationkey FROM supplier", _SEGMENTS, ("BUILDING", "")),
    Family("C01", "activity", "moderate", "How many {p1} events came in each hour?", "SELECT date_trunc('hour', ts) AS hour, COUNT(*) AS n FROM events WHERE event_type = '{p1}' GROUP BY date_trunc('hour', ts)", _TYPES, ("error", "")),
    Family("C02", "activity", "challenging", "How many users bought within an hour after a {p1}?", "SELECT COUNT(DISTINCT a.user_id) AS n FROM events AS a JOIN events AS b ON a.user_id = b.user_id WHERE a.event_type = '{p1}' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '1' HOUR", _TYPES, ("signup", "")),
    Family("C03", "activity", "simple", "What is the largest value of a {p1} event whose properties have k above {p2}?", "SELECT MAX(value) AS most FROM events WHERE event_type = '{p1}' AND CAST(get_json_object(props, '$.k') AS INT) > {p2}", _TYPES, ("purchase", "3"),
           "SELECT MAX(value) AS most FROM events WHERE event_type = 'purchase' AND CAST(json_extract_string(props, '$.k') AS INT) > 3"),
    Family("C04", "activity", "challenging", "How many visits have gaps below 12 hours after a {p1}?", "SELECT COUNT(*) AS n FROM (SELECT ts, LAG(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events WHERE event_type = '{p1}') AS e WHERE before IS NOT NULL AND ts <= before + INTERVAL '12' HOUR", _TYPES, ("click", "")),
    Family("C05", "web", "moderate", "Which share of labelled {p1} documents is good?", "SELECT ROUND(AVG(CAST(quality AS DOUBLE)), 6) AS good FROM documents JOIN labels ON documents.doc_id = labels.doc_id WHERE lang = '{p1}'", _LANGS, ("en", "")),
    Family("C06", "web", "simple", "How many {p1} documents of {p2} are longer than 2000 characters?", "SELECT COUNT(*) AS n FROM documents WHERE lang = '{p1}' AND source = '{p2}' AND n_chars > 2000", _LANGS, ("en", "src0")),
    Family("C07", "web", "challenging", "How many texts in {p1} occur more than once?", "SELECT COUNT(*) AS n FROM (SELECT text FROM documents WHERE lang = '{p1}' GROUP BY text HAVING COUNT(*) > 1) AS t", _LANGS, ("en", "")),
    Family("C08", "web", "moderate", "How many toxic documents has each source in {p1}?", "SELECT source, SUM(toxic) AS n FROM documents JOIN labels ON documents.doc_id = labels.doc_id WHERE lang = '{p1}' GROUP BY source", _LANGS, ("en", "")),
    Family("C09", "web", "simple", "How many pages have /{p1}/ in their address?", "SELECT COUNT(*) AS n FROM pages WHERE url LIKE '%/{p1}/%'", _LANGS, ("en", "")),
    Family("C10", "web", "challenging", "How many {p1} documents hold one of the first twenty benchmark passages?", "SELECT COUNT(*) AS n FROM documents JOIN benchmark ON contains(documents.text, benchmark.text) WHERE lang = '{p1}' AND item_id < 20", _LANGS, ("en", "")),
    Family("C11", "activity", "moderate", "How long are texts of each role from turn {p2} on?", "SELECT role, COUNT(*) AS n, SUM(length(text)) AS size FROM conversations WHERE turn >= {p2} GROUP BY role", _ROLES, ("", "1")),
    Family("C12", "web", "simple", "What is the mean first coordinate of vectors with label {p1}?", "SELECT ROUND(AVG(CAST(embedding[0] AS DOUBLE)), 6) AS mean FROM embeddings WHERE label = {p1}", _LABELS, ("1", ""),
           "SELECT ROUND(AVG(CAST(embedding[1] AS DOUBLE)), 6) AS mean FROM embeddings WHERE label = 1"),
)
BY_ID = {f.id: f for f in FAMILIES}


def questions(spark: SparkSession, sf_dir: str, families: list[str] | None = None) -> DataFrame:
    """``(question_id, suite, db_id, tier, family, p1, p2, question, gold_sql)``: one row per family and different values
    of the parameters that its gold or question names.

    Each parameter source is read once; families (a few dozen rows, broadcast) join it by the source's number."""
    chosen = [(k, f) for k, f in enumerate(FAMILIES) if not families or f.id in families]
    sources = list(dict.fromkeys((f.params, f.used) for _, f in chosen))
    rows = None
    for n, (text, used) in enumerate(sources):
        cells = [F.col(p).cast("string").alias(p) if p in used else F.lit("").alias(p) for p in ("p1", "p2")]
        one = run_sql(spark, sf_dir, text).select(F.lit(n).alias("source"), *cells).distinct()
        rows = one if rows is None else rows.unionByName(one)
    listed = spark.createDataFrame([(sources.index((f.params, f.used)), k, f.id, f.suite, f.db, f.tier, f.question, f.gold) for k, f in chosen],
                                   "source int, k long, family string, suite string, db_id string, tier string, question string, gold_sql string")
    fill = lambda c: F.replace(F.replace(F.col(c), F.lit("{p1}"), F.col("p1")), F.lit("{p2}"), F.col("p2"))
    at = F.pmod(number(F.col("p1"), F.col("p2")), F.lit(1_000_000_000)) + F.col("k") * 1_000_000_000
    return rows.join(F.broadcast(listed), "source").select(at.alias("question_id"), "suite", "db_id", "tier", "family", "p1", "p2",
                                                            fill("question").alias("question"), fill("gold_sql").alias("gold_sql"))


def duck_questions() -> str:
    """The same rows as DuckDB SQL."""
    quoted = lambda s: "'" + s.replace("'", "''") + "'"
    fill = lambda s: f"replace(replace({quoted(s)}, '{{p1}}', p1), '{{p2}}', p2)"
    parts = []
    for k, f in enumerate(FAMILIES):
        cells = ", ".join(f"CAST({p} AS VARCHAR) AS {p}" if p in f.used else f"'' AS {p}" for p in ("p1", "p2"))
        parts.append(f"SELECT {duck_number('p1', 'p2')} % 1000000000 + {k}000000000 AS question_id, {quoted(f.suite)} AS suite, {quoted(f.db)} AS db_id, {quoted(f.tier)} AS tier, "
                     f"{quoted(f.id)} AS family, p1, p2, {fill(f.question)} AS question, {fill(f.gold)} AS gold_sql FROM (SELECT DISTINCT {cells} FROM ({f.params}) AS r) AS p")
    return " UNION ALL ".join(parts)
