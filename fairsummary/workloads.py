"""Points made from the given tables.  One text serves Spark and DuckDB: ``{table}`` names a table, ``LIST(`` makes a list."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .metrics import INVERSIONS, L1, Metric
from .model import FairInstance

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def spark_sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    used = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in TABLES if "{" + t + "}" in text}
    return spark.sql(text.replace("LIST(", "array(").replace("EACH(", "transform("), **used)


def duck_sql(text: str) -> str:
    for t in TABLES:
        text = text.replace("{" + t + "}", t)
    return text.replace("LIST(", "list_value(").replace("EACH(", "list_transform(").replace("x -> ", "lambda x: ")


@dataclass(frozen=True)
class Fixture:
    """(ord, grp, coords) as SQL, with the metric and the capacities it is used with."""

    text: str
    metric: Metric
    caps: tuple[int, ...]

    def points(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = spark_sql(spark, sf_dir, self.text)
        return rows.select(F.col("ord").cast("bigint").alias("ord"), F.col("grp").cast("int").alias("grp"), "coords")

    def instance(self, spark: SparkSession, sf_dir: str) -> FairInstance:
        return FairInstance(self.points(spark, sf_dir), self.metric, self.caps)

    @property
    def duck(self) -> str:
        return duck_sql(self.text)


def _embeddings(grp: str) -> str:
    return f"SELECT vec_id AS ord, CAST({grp} AS INTEGER) AS grp, EACH(embedding, x -> CAST(round(CAST(x AS DOUBLE) * 1000000) AS BIGINT)) AS coords FROM {{embeddings}} WHERE vec_id < 1000"


_LINE = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"
_SIX = ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "lag", "o_totalprice")


def _census(grp: str) -> str:
    """The first 1000 line items as six standardised numbers; the order is that of whole rows."""
    raw = f"SELECT {_LINE}, o_totalprice, o_orderpriority, datediff_days AS lag FROM (SELECT l.*, o.o_totalprice, o.o_orderpriority, CAST(CAST(l.l_shipdate AS DATE) - CAST(o.o_orderdate AS DATE) AS INTEGER) AS datediff_days FROM {{lineitem}} l JOIN {{orders}} o ON l.l_orderkey = o.o_orderkey) x ORDER BY {_LINE} LIMIT 1000"
    z = ", ".join(f"CAST(round(({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER () * 1000) AS BIGINT)" for c in _SIX)
    return f"SELECT row_number() OVER (ORDER BY {_LINE}) - 1 AS ord, CAST({grp} AS INTEGER) AS grp, LIST({z}) AS coords FROM ({raw}) y".replace("{{", "{").replace("}}", "}")


_STATUS = "CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END"
_PRIORITY = "CAST(substr(o_orderpriority, 1, 1) AS INTEGER) - 1"

_TYPE_QTY = """SELECT c.c_custkey, t.p_type, CAST(coalesce(q.qty, 0) AS BIGINT) AS qty FROM {customer} c CROSS JOIN (SELECT DISTINCT p_type FROM {part}) t
LEFT JOIN (SELECT o_custkey, p_type, sum(l_quantity) AS qty FROM {orders} JOIN {lineitem} ON o_orderkey = l_orderkey JOIN {part} ON l_partkey = p_partkey GROUP BY o_custkey, p_type) q
ON q.o_custkey = c.c_custkey AND q.p_type = t.p_type WHERE c.c_custkey < 1000"""


def _ranking(grp: str) -> str:
    """A bit for each pair of part types: whether the customer bought more of the first."""
    ranked = f"SELECT c_custkey, row_number() OVER (PARTITION BY c_custkey ORDER BY qty DESC, p_type) AS pos, dense_rank() OVER (PARTITION BY c_custkey ORDER BY p_type) - 1 AS t FROM ({_TYPE_QTY}) q0"
    return f"""WITH r AS ({ranked}), code AS (SELECT a.c_custkey, sum(CASE WHEN a.pos < b.pos THEN CAST(power(2, a.t * 6 + b.t) AS BIGINT) ELSE 0 END) AS bits FROM r a JOIN r b ON a.c_custkey = b.c_custkey AND a.t < b.t GROUP BY a.c_custkey)
SELECT c.c_custkey AS ord, CAST({grp} AS INTEGER) AS grp, CAST(bits AS BIGINT) AS coords FROM code JOIN {{customer}} c ON c.c_custkey = code.c_custkey"""


def _scores(grp: str) -> str:
    ranked = f"SELECT c_custkey, qty, dense_rank() OVER (PARTITION BY c_custkey ORDER BY p_type) - 1 AS t FROM ({_TYPE_QTY}) q0"
    cells = ", ".join(f"CAST(sum(CASE WHEN t = {i} THEN qty ELSE 0 END) AS BIGINT)" for i in range(6))
    return f"""WITH r AS ({ranked}), s AS (SELECT c_custkey, LIST({cells}) AS coords FROM r GROUP BY c_custkey)
SELECT c.c_custkey AS ord, CAST({grp} AS INTEGER) AS grp, coords FROM s JOIN {{customer}} c ON c.c_custkey = s.c_custkey"""


_DEBT = "CASE WHEN c_acctbal < 0 THEN 1 ELSE 0 END"
_SEGMENT = "CASE c_mktsegment WHEN 'AUTOMOBILE' THEN 0 WHEN 'BUILDING' THEN 1 WHEN 'FURNITURE' THEN 2 WHEN 'HOUSEHOLD' THEN 3 ELSE 4 END"
_LANG = "CASE {c} WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END"
_LETTERS = "LIST(" + ", ".join(f"CAST(floor(1000.0 * (length(t) - length(replace(t, '{c}', ''))) / greatest(length(t), 1)) AS BIGINT)" for c in "abcdefghijklmnopqrstuvwxyz") + ")"

FIXTURES = {
    "emb_m2": Fixture(_embeddings("label % 2"), L1, (2, 2)),
    "emb_m4": Fixture(_embeddings("2 * (label % 2) + CASE WHEN label >= 5 THEN 1 ELSE 0 END"), L1, (2, 2, 2, 2)),
    "emb_m10": Fixture(_embeddings("label"), L1, (1,) * 10),
    "li6_m2": Fixture(_census(_STATUS), L1, (2, 2)),
    "li6_m5": Fixture(_census(_PRIORITY), L1, (2,) * 5),
    "li6_m10": Fixture(_census(f"5 * ({_STATUS}) + {_PRIORITY}"), L1, (1,) * 10),
    "pref_rank_m2": Fixture(_ranking(_DEBT), INVERSIONS, (2, 2)),
    "pref_rank_m5": Fixture(_ranking(_SEGMENT), INVERSIONS, (2,) * 5),
    "pref_rank_m6": Fixture(_ranking("c_nationkey % 6"), INVERSIONS, (2,) * 6),
    "pref_rank_m12": Fixture(_ranking(f"6 * ({_DEBT}) + c_nationkey % 6"), INVERSIONS, (1,) * 12),
    "pref_score_m2": Fixture(_scores(_DEBT), L1, (2, 2)),
    "pref_score_m6": Fixture(_scores("c_nationkey % 6"), L1, (2,) * 6),
    "pref_score_m12": Fixture(_scores(f"6 * ({_DEBT}) + c_nationkey % 6"), L1, (1,) * 12),
    "doc_letters": Fixture(f"SELECT doc_id AS ord, CAST({_LANG.format(c='lang')} AS INTEGER) AS grp, {_LETTERS} AS coords FROM (SELECT doc_id, lang, lower(text) AS t FROM {{documents}}) d", L1, (2, 2, 2, 2)),
    "events": Fixture("SELECT event_id AS ord, CAST(CASE event_type WHEN 'click' THEN 0 WHEN 'view' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS INTEGER) AS grp, LIST(CAST(hour(ts) * 3600 + minute(ts) * 60 + floor(second(ts)) AS BIGINT), CAST(round(value * 100) AS BIGINT)) AS coords FROM {events}", L1, (1,) * 5),
    "supplier_bal": Fixture("SELECT s_suppkey AS ord, CAST(n_regionkey AS INTEGER) AS grp, LIST(CAST(round(s_acctbal * 100) AS BIGINT)) AS coords FROM {supplier} JOIN {nation} ON s_nationkey = n_nationkey", L1, (1,) * 5),
    "customer_bal": Fixture("SELECT c_custkey AS ord, CAST(n_regionkey AS INTEGER) AS grp, LIST(CAST(round(c_acctbal * 100) AS BIGINT)) AS coords FROM {customer} JOIN {nation} ON c_nationkey = n_nationkey", L1, (1,) * 5),
    "part_shape": Fixture("SELECT p_partkey AS ord, CAST(t.n AS INTEGER) AS grp, LIST(CAST(p_size AS BIGINT), CAST(round(p_retailprice * 100) AS BIGINT)) AS coords FROM {part} p JOIN (SELECT p_type, row_number() OVER (ORDER BY p_type) - 1 AS n FROM (SELECT DISTINCT p_type FROM {part}) d) t ON t.p_type = p.p_type", L1, (1,) * 6),
    "nation_trade": Fixture("SELECT n_nationkey AS ord, CAST(n_regionkey AS INTEGER) AS grp, LIST(coalesce(c.n, 0), coalesce(s.n, 0)) AS coords FROM {nation} LEFT JOIN (SELECT c_nationkey, count(*) AS n FROM {customer} GROUP BY c_nationkey) c ON c_nationkey = n_nationkey LEFT JOIN (SELECT s_nationkey, count(*) AS n FROM {supplier} GROUP BY s_nationkey) s ON s_nationkey = n_nationkey", L1, (1,) * 5),
    "doc_labels": Fixture(f"SELECT d.doc_id AS ord, CAST(2 * quality + toxic AS INTEGER) AS grp, {_LETTERS} AS coords FROM (SELECT doc_id, lower(text) AS t FROM {{documents}}) d JOIN (SELECT doc_id, max(quality) AS quality, max(toxic) AS toxic FROM {{labels}} GROUP BY doc_id) l ON l.doc_id = d.doc_id", L1, (2, 2, 2, 2)),
    "page_shape": Fixture("SELECT page_id AS ord, CAST(CASE WHEN url LIKE '%/de/%' THEN 0 WHEN url LIKE '%/en/%' THEN 1 WHEN url LIKE '%/es/%' THEN 2 ELSE 3 END AS INTEGER) AS grp, LIST(CAST(length(html) AS BIGINT), CAST(length(html) - length(replace(html, '<', '')) AS BIGINT), CAST((length(html) - length(replace(html, 'href', ''))) / 4 AS BIGINT)) AS coords FROM {pages}", L1, (2, 2, 2, 2)),
    "turn_shape": Fixture("SELECT conv_id * 64 + turn AS ord, CAST(CASE role WHEN 'system' THEN 0 WHEN 'user' THEN 1 ELSE 2 END AS INTEGER) AS grp, LIST(CAST(turn AS BIGINT), CAST(length(text) AS BIGINT)) AS coords FROM {conversations}", L1, (1, 2, 2)),
}

#: What limits a fixture to the first rows of its table; the whole-table fixtures do without.
_FIRST = (" WHERE vec_id < 1000", " WHERE c.c_custkey < 1000")


def whole(f: Fixture) -> Fixture:
    """The fixture over all rows of its table."""
    text = f.text
    for cut in _FIRST:
        text = text.replace(cut, "")
    return Fixture(text, f.metric, f.caps)


_JOINED = "SELECT l.*, o.o_totalprice, o.o_orderpriority, CAST(CAST(l.l_shipdate AS DATE) - CAST(o.o_orderdate AS DATE) AS INTEGER) AS lag FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey"
#: A total order of line items: their key is not unique, so rows of one key are numbered within it and nothing gathers in one task.
_LINE_ORD = f"(l_orderkey * 8 + l_linenumber) * 64 + row_number() OVER (PARTITION BY l_orderkey, l_linenumber ORDER BY {_LINE}) - 1"


def _census_all(grp: str) -> str:
    """All line items as six standardised numbers."""
    raw = _JOINED
    means = ", ".join(f"avg(CAST({c} AS DOUBLE)) AS a{i}, stddev_pop(CAST({c} AS DOUBLE)) AS s{i}" for i, c in enumerate(_SIX))
    z = ", ".join(f"CAST(round((CAST({c} AS DOUBLE) - a{i}) / s{i} * 1000) AS BIGINT)" for i, c in enumerate(_SIX))
    return f"WITH y AS ({raw}), m AS (SELECT {means} FROM y) SELECT {_LINE_ORD} AS ord, CAST({grp} AS INTEGER) AS grp, LIST({z}) AS coords FROM y CROSS JOIN m"


#: The same over whole tables.
FIXTURES |= {n.replace("_", "_all_", 1) if n.startswith("emb") else n.replace("_m", "_all_m"): whole(FIXTURES[n]) for n in list(FIXTURES) if any(cut in FIXTURES[n].text for cut in _FIRST)}
FIXTURES |= {f"li6_all_m{len(caps)}": Fixture(_census_all(grp), L1, caps) for grp, caps in ((_STATUS, (2, 2)), (_PRIORITY, (2,) * 5), (f"5 * ({_STATUS}) + {_PRIORITY}", (1,) * 10))}

#: The stand-in for the largest run: every line item as six whole numbers (cents, percent points, days), four groups.
FIXTURES["li6_full"] = Fixture(
    f"SELECT {_LINE_ORD} AS ord, CAST(l_orderkey % 4 AS INTEGER) AS grp, LIST(CAST(l_quantity AS BIGINT), CAST(round(l_extendedprice * 100) AS BIGINT), CAST(round(l_discount * 100) AS BIGINT), CAST(round(l_tax * 100) AS BIGINT), CAST(lag AS BIGINT), CAST(round(o_totalprice * 100) AS BIGINT)) AS coords FROM ({_JOINED}) y",
    L1, (2, 2, 2, 2),
)


def uniform_cube(spark: SparkSession, n: int, dim: int, m: int, seed: int, top: float = 10000.0) -> DataFrame:
    """n points with dim coordinates drawn from (0, top) and random groups, made where they are used."""
    coords = F.array(*[(F.pmod(F.xxhash64(F.lit(seed), F.col("id"), F.lit(j)), F.lit(1 << 53)) / float(1 << 53) * top) for j in range(dim)])
    return spark.range(n).select(F.col("id").alias("ord"), F.pmod(F.xxhash64(F.lit(seed), F.col("id")), F.lit(m)).cast("int").alias("grp"), coords.alias("coords"))


def two_files(spark: SparkSession, features: str, attributes: str, dim: int) -> DataFrame:
    """Points from a CSV of coordinates and a CSV of groups, both with a row id in front."""
    f = spark.read.csv(features, schema="ord bigint, " + ", ".join(f"x{j} double" for j in range(dim)))
    a = spark.read.csv(attributes, schema="ord bigint, grp int")
    return f.join(a, "ord").select("ord", "grp", F.array(*[f"x{j}" for j in range(dim)]).alias("coords"))

