"""Evaluation relations over the given star schema.

Each view is one SELECT whose text is shared by Spark and by the oracle engine;
the few functions that differ between dialects are named in ``DIALECTS``.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

DIALECTS = {
    "spark": {"days": "datediff({b}, {a})", "dow": "dayofweek({a})", "key": "get_json_object({a}, '$.k')", "piece": "split({a}, '{b}')[{c}]", "pieces": "size(split({a}, '{b}'))", "tail": "substring_index({a}, '.', -1)", "head": "substring_index({a}, '.', 1)", "at": "{a}[{b}]"},
    "duckdb": {"days": "date_diff('day', CAST({a} AS DATE), CAST({b} AS DATE))", "dow": "dayofweek({a}) + 1", "key": "json_extract_string({a}, '$.k')", "piece": "string_split({a}, '{b}')[{c} + 1]", "pieces": "len(string_split({a}, '{b}'))", "tail": "string_split({a}, '.')[-1]", "head": "string_split({a}, '.')[1]", "at": "{a}[{b} + 1]"},
}


@dataclass(frozen=True)
class View:
    """A relation: its source tables, join clause, attributes and further numeric columns."""

    name: str
    tables: tuple[str, ...]
    source: str
    attributes: dict[str, str]
    numeric: dict[str, str]
    dependencies: tuple[tuple[str, str], ...] = ()

    def sql(self, dialect: str, quote: bool = True) -> str:
        """SELECT over table names; in Spark they are placeholders for frames."""

        def expand(text: str) -> str:
            def one(m: re.Match) -> str:
                return DIALECTS[dialect][m[1]].format(**dict(zip("abc", m[2].split(";"))))

            while (now := re.sub(r"@(\w+)\(([^@]*)\)@", one, text)) != text:  # innermost first
                text = now
            return text

        cols = ", ".join(f"{expand(e)} AS {a}" for a, e in {**self.attributes, **self.numeric}.items())
        source = self.source if dialect == "duckdb" else re.sub(r"\b(" + "|".join(self.tables) + r")\b", r"{\1}", self.source)
        return f"SELECT {cols} FROM {source}"


def _band(x: str) -> str:
    return f"CAST(floor(log2({x})) AS INT)"


_GEO = "orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
_LAG = "@days(o_orderdate;l_shipdate)@"

VIEWS = {
    v.name: v
    for v in (
        View(
            "shipments", ("lineitem", "orders", "customer", "nation", "region"), f"lineitem JOIN {_GEO.replace('orders JOIN', 'orders ON l_orderkey = o_orderkey JOIN', 1)}",
            {"region": "r_name", "nation": "n_name", "segment": "c_mktsegment", "oyear": "CAST(year(o_orderdate) AS INT)", "syear": "CAST(year(l_shipdate) AS INT)", "lag_band": f"CASE WHEN l_shipdate < o_orderdate THEN 0 WHEN {_LAG} < 365 THEN 1 WHEN {_LAG} < 1095 THEN 2 ELSE 3 END", "price_band": _band("l_extendedprice / 500"), "net_band": _band("l_extendedprice * (1 - l_discount) / 500")},
            {"quantity": "CAST(l_quantity AS INT)", "disc_pct": "CAST(round(l_discount * 100) AS INT)", "tax_pct": "CAST(round(l_tax * 100) AS INT)", "ext": "l_extendedprice", "tot": "o_totalprice", "bal": "c_acctbal"},
            (("nation", "region"),),
        ),
        View(
            "partsales", ("lineitem", "part"), "lineitem JOIN part ON l_partkey = p_partkey",
            {"partkey": "l_partkey", "suppkey": "l_suppkey", "brand": "p_brand", "type": "p_type", "size": "p_size", "adj": "@piece(p_name; ;0)@", "noun": "@piece(p_name; ;1)@", "qty": "CAST(l_quantity AS INT)", "price_c": "CAST(floor(l_extendedprice / 100) AS INT)"},
            {}, (("partkey", "brand"), ("partkey", "type"), ("partkey", "size"), ("partkey", "adj"), ("partkey", "noun")),
        ),
        View(
            "orderbook", ("orders", "customer", "nation", "region"), _GEO,
            {"segment": "c_mktsegment", "nation": "n_name", "region": "r_name", "status": "o_orderstatus", "priority": "o_orderpriority", "oyear": "CAST(year(o_orderdate) AS INT)", "oquarter": "CAST(quarter(o_orderdate) AS INT)", "omonth": "CAST(month(o_orderdate) AS INT)"},
            {}, (("nation", "region"), ("omonth", "oquarter")),
        ),
        View(
            "activity", ("events",), "events",
            {"user_id": "user_id", "event_type": "event_type", "hr": "CAST(hour(ts) AS INT)", "daypart": "CAST(floor(hour(ts) / 6) AS INT)", "dom": "CAST(day(ts) AS INT)", "dow": "CAST(@dow(ts)@ AS INT)", "vband": _band("value + 1"), "k": "@key(props)@"},
            {"event_id": "event_id"}, (("hr", "daypart"), ("dom", "dow")),
        ),
        View(
            "corpus", ("documents", "labels"), "documents LEFT JOIN labels ON documents.doc_id = labels.doc_id",
            {"lang": "lang", "source": "source", "char_band": _band("n_chars"), "word_band": _band("@pieces(text; )@"), "quality": "quality", "toxic": "toxic"},
            {},
        ),
        View(
            "web", ("pages",), "pages",
            {"scheme": "@piece(url;:;0)@", "tld": "@tail(@piece(url;/;2)@)@", "sub": "@head(@piece(url;/;2)@)@", "html_band": _band("length(html)")},
            {},
        ),
        View("dialog", ("conversations",), "conversations", {"role": "role", "turn": "CAST(turn AS INT)", "len_band": _band("length(text) + 1")}, {}),
        View("vecbits", ("embeddings",), "embeddings", {"label": "label"} | {f"s{k}": f"CASE WHEN @at(embedding;{k})@ > 0 THEN 1 ELSE 0 END" for k in range(8)}, {}),
    )
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The view as a plan over the Parquet tables."""
    view = VIEWS[name]
    return spark.sql(view.sql("spark"), **{t: table(spark, sf_dir, t) for t in view.tables})
