"""Tables with explicit schemas, a registry of datasets and models, and the sinks of the engine."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from .shipping import ship

SCHEMAS = {
    "embeddings": "vec_id long, embedding array<float>, label int",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables. No inference over the data: parquet carries its schema."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, schema: T.StructType | str, form: str = "parquet", **options) -> DataFrame:
    """Read parquet, ORC, JSON or CSV under an explicit schema."""
    return spark.read.format(form).schema(schema).options(**options).load(path)


@dataclass(frozen=True)
class Model:
    """What an encoder promises: its dimensions, native bits a value, and whether prefixes were trained to be usable."""

    name: str
    encode: Callable[[DataFrame], DataFrame]
    dims: int
    native_bits: int = 32
    nested: bool = False
    encoder: object = None  # where counts of several models come from one scan of the texts


_DATASETS: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_MODELS: dict[str, Model] = {}


def register_dataset(name: str, load: Callable[[SparkSession, str], DataFrame]) -> None:
    """Make load(spark, sf_dir) -> (item_id, text) known under a name."""
    _DATASETS[name] = load


def register_model(model: Model) -> None:
    if model.native_bits not in (8, 16, 32, 64) or model.dims < 1:
        raise ValueError(f"{model.name}: {model.dims} dimensions of {model.native_bits} bits")
    _MODELS[model.name] = model


def dataset(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    df = _DATASETS[name](spark, sf_dir)
    if df.columns[:2] != ["item_id", "text"]:
        raise ValueError(f"dataset {name} has columns {df.columns}, not item_id and text")
    return df


def datasets() -> list[str]:
    return sorted(_DATASETS)


def model(name: str) -> Model:
    return _MODELS[name]


def models() -> list[str]:
    return sorted(_MODELS)


def write_vectors(vectors: DataFrame, path: str, partition: tuple[str, ...] = ("tier",)) -> None:
    """Store vectors, codes or texts once; a tier's folder holds its own shell, so nested tiers are read as tier <= t."""
    vectors.write.mode("overwrite").partitionBy(*partition).parquet(path)


def write_metrics(records: DataFrame, path: str) -> None:
    """Metric records as JSON lines."""
    records.write.mode("overwrite").json(path)
