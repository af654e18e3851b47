"""Experiment workloads on the given tables: planted or derived targets, public bounds."""

from __future__ import annotations

import warnings
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from privgrove.operators.schema import DatasetSpec, FeatureSpec, TargetSpec, onehot
from privgrove.sources.io import load

# Public dictionaries.
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
EVENT_TYPES = ["click", "purchase", "refund", "signup", "view"]
PART_TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
LANGUAGES = ["de", "en", "es", "fr"]

LINE_KEY = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT))"


def u(text: str) -> str:
    """The keyed uniform as Spark SQL."""
    return f"((CAST(conv(substr(sha2({text}, 256), 1, 13), 16, 10) AS BIGINT) + 0.5) / 4503599627370496.0D)"


def planted(rule: str, flips: float, key: str) -> str:
    """A class by a rule, flipped for a fixed part of the rows."""
    draw = u(f"concat('plant|', {key})")
    return f"CASE WHEN ({rule}) <> ({draw} <= {flips}) THEN 1.0D ELSE -1.0D END"


@dataclass(frozen=True)
class Workload:
    """A dataset: where its rows come from, its spec, and the settings that fit its size."""

    name: str
    spec: DatasetSpec
    tables: tuple[str, ...]
    min_child: tuple[int, int]  # below 100,000 rows, and from there
    bins: tuple[int, int]
    classes: bool

    def source(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        frames = {t: load(spark, sf_dir, t) for t in self.tables}
        if self.tables == ("lineitem", "orders"):
            o = frames["orders"].select("o_orderkey", "o_totalprice", "o_orderdate")
            return frames["lineitem"].join(o, frames["lineitem"].l_orderkey == o.o_orderkey)
        if self.tables == ("orders", "customer", "nation"):
            c = frames["customer"].select("c_custkey", "c_acctbal", "c_mktsegment", "c_nationkey")
            n = frames["nation"].select("n_nationkey", "n_regionkey")
            return frames["orders"].join(c, frames["orders"].o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey)
        if self.tables == ("labels", "documents"):
            return frames["labels"].join(frames["documents"], "doc_id")
        return frames[self.tables[0]]

    def rows(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return self.spec.encode(self.source(spark, sf_dir))

    def settings(self, n: int) -> dict:
        large = n >= 100_000
        return {"min_child": self.min_child[large], "bins": self.bins[large]}


def line_features() -> tuple[FeatureSpec, ...]:
    return (
        FeatureSpec("quantity", "l_quantity", 1, 50),
        FeatureSpec("discount", "l_discount", 0, 0.1),
        FeatureSpec("tax", "l_tax", 0, 0.08),
        FeatureSpec("price", "l_extendedprice", 900, 105000),
        FeatureSpec("ship_day", "datediff(l_shipdate, DATE '1995-01-01')", 0, 2500),
        FeatureSpec("line", "l_linenumber", 1, 7),
        FeatureSpec("order_total", "o_totalprice", 1000, 500000),
        FeatureSpec("order_month", "month(o_orderdate)", 1, 12),
    )


W01_RULE = (
    "(CASE WHEN l_quantity > 20 AND l_discount > 0.025D THEN 1.2D ELSE -0.8D END) + (CASE WHEN l_shipdate < TIMESTAMP_NTZ '1998-06-01' THEN 0.6D ELSE -0.6D END)"
    " + (CASE WHEN l_extendedprice > 60000 THEN 0.5D ELSE -0.3D END) > 0"
)
W02_RULE = (
    "CAST(o_totalprice > 250000 AS INT) + CAST(o_orderpriority IN ('1-URGENT', '2-HIGH') AS INT) + CAST(c_mktsegment IN ('BUILDING', 'MACHINERY') AS INT)"
    " + CAST(c_acctbal > 5000 AS INT) >= 2"
)
K = "CAST(get_json_object(props, '$.k') AS DOUBLE)"
W03_RULE = f"least(value, 200D) / 100 + (CASE WHEN hour(ts) >= 12 THEN 0.5D ELSE -0.5D END) + ({K} - 50) / 50 > 0.5D"


def text_features() -> tuple[FeatureSpec, ...]:
    words = "split(text, '[ \\\\n]+')"
    share = lambda kind: f"length(regexp_replace(text, '[^{kind}]+', '')) / greatest(length(text), 1)"
    return (
        FeatureSpec("distinct_words", f"size(array_distinct({words})) / greatest(size({words}), 1)", 0, 1),
        FeatureSpec("words_per_char", f"size({words}) / greatest(length(text), 1)", 0, 0.3),
        FeatureSpec("punctuation", share(".,;:!?#&*$%|"), 0, 0.3),
        FeatureSpec("upper_case", share("A-Z"), 0, 0.7),
        FeatureSpec("digits", share("0-9"), 0, 0.1),
        FeatureSpec("log_length", "ln(greatest(length(text), 1))", 0, 12),
        *onehot("lang", LANGUAGES),
    )


def vector_features() -> tuple[FeatureSpec, ...]:
    return tuple(FeatureSpec(f"v{k}", f"element_at(embedding, {k + 1})", -1, 1, nullable=False) for k in range(64))


def part_features(parts: int) -> tuple[FeatureSpec, ...]:
    return (
        FeatureSpec("part", "p_partkey", 0, parts),
        FeatureSpec("size", "p_size", 1, 50),
        FeatureSpec("brand", "CAST(regexp_extract(p_brand, '([0-9]+)', 1) AS DOUBLE)", 1, 25),
        *[FeatureSpec(f"type={v}", f"CASE WHEN p_type LIKE '{v}%' THEN 1 ELSE 0 END", 0, 1) for v in PART_TYPES],
    )


def workloads(parts: int = 2000) -> dict[str, Workload]:
    """All of them by id; `parts` is the public number of part keys at the table's scale."""
    net = "l_extendedprice * (1 - l_discount) * (1 + l_tax)"
    lines = line_features()
    all_ = [
        Workload("w01", DatasetSpec(LINE_KEY, lines, TargetSpec(planted(W01_RULE, 0.08, LINE_KEY), kind="class")), ("lineitem", "orders"), (50, 500), (16, 64), True),
        Workload(
            "w02",
            DatasetSpec(
                "o_orderkey",
                (
                    FeatureSpec("order_total", "o_totalprice", 1000, 500000),
                    FeatureSpec("balance", "c_acctbal", -1000, 10000),
                    FeatureSpec("priority", "CAST(substr(o_orderpriority, 1, 1) AS DOUBLE)", 1, 5),
                    *onehot("c_mktsegment", SEGMENTS),
                    FeatureSpec("order_year", "year(o_orderdate)", 1995, 2001),
                    FeatureSpec("region", "n_regionkey", 0, 4),
                ),
                TargetSpec(planted(W02_RULE, 0.12, "CAST(o_orderkey AS STRING)"), kind="class"),
            ),
            ("orders", "customer", "nation"),
            (50, 500),
            (16, 64),
            True,
        ),
        Workload(
            "w03",
            DatasetSpec(
                "event_id",
                (FeatureSpec("value", "value", 0, 200), FeatureSpec("hour", "hour(ts)", 0, 23), FeatureSpec("k", K, 0, 99), *onehot("event_type", EVENT_TYPES)),
                TargetSpec(planted(W03_RULE, 0.05, "CAST(event_id AS STRING)"), kind="class"),
            ),
            ("events",),
            (50, 50),
            (16, 64),
            True,
        ),
        Workload(
            "w04",
            DatasetSpec(LINE_KEY, (lines[3], lines[1], lines[2], lines[0]), TargetSpec(net, 0, 115500)),
            ("lineitem",),
            (50, 500),
            (16, 64),
            False,
        ),
        Workload("w05", DatasetSpec("p_partkey", part_features(parts), TargetSpec("p_retailprice", 900, 1000)), ("part",), (10 if parts <= 2000 else 50, 50), (16 if parts <= 2000 else 32, 32), False),
        Workload("w06", DatasetSpec("doc_id", text_features(), TargetSpec("2.0D * quality - 1", kind="class")), ("labels", "documents"), (5, 50), (8, 16), True),
        Workload("w11a", DatasetSpec(LINE_KEY, lines, TargetSpec("CASE WHEN l_returnflag = 'R' THEN 1.0D ELSE -1.0D END", kind="class")), ("lineitem", "orders"), (50, 500), (16, 64), True),
        Workload("w12", DatasetSpec("vec_id", vector_features(), TargetSpec("CASE WHEN label < 5 THEN 1.0D ELSE -1.0D END", kind="class")), ("embeddings",), (10, 50), (8, 8), True),
    ]
    return {w.name: w for w in all_}


def for_tables(sf_dir: str, parts: int | None = None) -> dict[str, Workload]:
    """The workloads; `parts` is the public number of part keys, else that of the scale that the folder's name gives.

    Keys beyond it are clipped to the last bin, so a folder without a scale in its name is warned of.
    """
    if parts is None:
        try:
            scale = float(sf_dir.rstrip("/").rsplit("/sf", 1)[1])
        except (IndexError, ValueError):
            warnings.warn(f"{sf_dir} does not name its scale: 2,000 part keys are taken; give `parts`", stacklevel=2)
            scale = 0.01
        parts = max(200, round(200_000 * scale))
    return workloads(parts)
