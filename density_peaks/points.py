"""Point views over the given tables, as DataFrames and as the same SQL for an oracle."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from density_peaks.rank import global_rank


def _bell(k: str, terms: tuple[tuple[int, int, int], ...]) -> str:
    return "(" + " + ".join(f"(({k} * {a} + {b}) % {m}) / {m}e0" for a, b, m in terms) + " - 1.5e0)"


# Coefficients of the two bell-shaped offsets.
BELL_X = ((7919, 13, 1009), (104729, 7, 2003), (31337, 3, 3001))
BELL_Y = ((6007, 5, 1013), (50021, 11, 1999), (27449, 17, 2999))


def _blob(table: str, key: str, cells: int, wide: int, spread: int) -> str:
    x, y = _bell(key, BELL_X), _bell(key, BELL_Y)
    cell = f"({key} % {cells})"
    row = f"CAST(floor({cell} / {wide}e0) AS BIGINT)"
    return (
        f"SELECT {key} AS id, round({cell} % {wide} * 100e0 + {spread}e0 * {x}, 3) AS x, "
        f"round({row} * 100e0 + {spread}e0 * {y}, 3) AS y, CAST({cell} AS BIGINT) AS truth FROM {table}"
    )


#: name: (tables, Spark SQL, DuckDB SQL); one text where both are the same
_SAME = {
    "P_blob15": (("part",), _blob("part", "p_partkey", 15, 5, 40)),
    "P_blob100": (("customer",), _blob("customer", "c_custkey", 100, 10, 30)),
    "P_part": (("part",), "SELECT p_partkey AS id, CAST(p_size AS DOUBLE) AS x, round((p_retailprice - 900e0) / 2e0, 4) AS y FROM part"),
    "P_cust": (("customer",), "SELECT c_custkey AS id, c_nationkey * 400e0 AS x, c_acctbal AS y FROM customer"),
    "P_supp": (("supplier",), "SELECT s_suppkey AS id, s_nationkey * 400e0 AS x, s_acctbal AS y FROM supplier"),
}
_TWO = {
    "P_orders": (
        ("orders",),
        "SELECT o_orderkey AS id, CAST(datediff(o_orderdate, DATE'1995-01-01') AS DOUBLE) AS x, o_totalprice / 200e0 AS y FROM orders",
        "SELECT o_orderkey AS id, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS DOUBLE) AS x, o_totalprice / 200e0 AS y FROM orders",
    ),
    "P_events": (
        ("events",),
        "SELECT event_id AS id, round((unix_micros(CAST(ts AS TIMESTAMP)) - 1704067200000000) / 3600000000e0, 4) AS x, value AS y FROM events",
        "SELECT event_id AS id, round((epoch_us(ts) - 1704067200000000) / 3600000000e0, 4) AS x, value AS y FROM events",
    ),
    "P_lineitem": (
        ("lineitem",),
        "SELECT * FROM lineitem",
        "SELECT row_number() OVER (ORDER BY {all}) - 1 AS id, l_quantity * 20e0 AS x, round(l_extendedprice / 100e0, 4) AS y FROM lineitem",
    ),
    "P_docs": (  # an empty text has NaN for x, where Spark would raise an error
        ("documents",),
        "SELECT doc_id AS id, round(CASE WHEN length(text) = 0 THEN double('NaN') ELSE 100e0 * length(regexp_replace(text, '[\\\\x00-\\\\x7F]', '')) / length(text) END, 3) AS x, round(10e0 * length(text) / (1 + length(text) - length(replace(text, ' ', ''))), 3) AS y, lang AS truth FROM documents",
        "SELECT doc_id AS id, round(100e0 * length(regexp_replace(text, '[\\x00-\\x7F]', '', 'g')) / length(text), 3) AS x, round(10e0 * length(text) / (1 + length(text) - length(replace(text, ' ', ''))), 3) AS y, lang AS truth FROM documents",
    ),
    "P_emb": (
        ("embeddings",),
        "SELECT vec_id AS id, CAST(embedding AS ARRAY<DOUBLE>) AS vec FROM embeddings",
        "SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS vec FROM embeddings",
    ),
}
VIEWS: dict[str, tuple[tuple[str, ...], str, str]] = {k: (t, s, s) for k, (t, s) in _SAME.items()} | _TWO
_LINE = "l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"


def sql(view: str, where: str = "") -> str:
    """The view as a DuckDB SELECT."""
    text = VIEWS[view][2].replace("{all}", _LINE)
    return f"SELECT * FROM ({text}) WHERE {where}" if where else text


def view(spark: SparkSession, sf_dir: str, name: str, where: str = "") -> DataFrame:
    """A point view: id, x, y (or vec), and truth where the data has one."""
    tables, text, _ = VIEWS[name]
    text = text.replace("{all}", _LINE)
    for t in tables:
        text = text.replace(f"FROM {t}", f"FROM parquet.`{sf_dir}/{t}.parquet`")
    df = spark.sql(text)
    if name == "P_lineitem":  # the table has no key: rows are numbered in the order of all columns, without one task that sorts them
        df = global_rank(df, [F.col(c) for c in _LINE.split(", ")], "id", keep=["l_quantity", "l_extendedprice"])
        df = df.select("id", (F.col("l_quantity") * 20.0).alias("x"), F.round(F.col("l_extendedprice") / 100.0, 4).alias("y"))
    return df.where(where) if where else df
