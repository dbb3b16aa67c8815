"""Given tables with explicit schema checks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_all(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    return {n: load(spark, sf_dir, n) for n in NAMES}


def check_schema(df: DataFrame, schema: T.StructType | str) -> DataFrame:
    """``df`` itself, if it has the columns of ``schema`` with their types (others are allowed); else ValueError."""
    want = T.StructType.fromDDL(schema) if isinstance(schema, str) else schema
    have = {f.name: f.dataType for f in df.schema}
    wrong = [f"{f.name}: {have.get(f.name)} is not {f.dataType.simpleString()}" for f in want if have.get(f.name) != f.dataType]
    if wrong:
        raise ValueError("; ".join(wrong))
    return df


# Schemas of the derived tables.
CONCEPT_EDGES = "src string, rel int, dst string"
CONCEPT_TYPES = "concept_id string, sty string"
TYPE_NET = "sty_src string, srel int, sty_dst string"
SENTENCES = "sent_id long, doc_id long, split string, text string"
TOKENS = "sent_id long, tok int, form string"
MENTIONS = "sent_id long, tok_from int, tok_to int, concept_id string"
TRIGGERS = "sent_id long, trig_id long, tok_from int, tok_to int, etype string"
ARGUMENTS = "sent_id long, trig_id long, role string, kind string, ref long"
ENTITIES = "sent_id long, ent_id long, etype string, tok_from int, tok_to int"
EVENTS = "sent_id long, event_id string, etype string, trig_id long, level int, args array<struct<role:string,kind:string,ref:string>>"
