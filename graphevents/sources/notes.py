"""The order-notes corpus: sentences rendered from order lines, with gold triggers, entities and arguments.

Four templates, by the line's rank in its order, give a simple event, a regulation of one, a binding, and a regulation of a
regulation. The rules are row expressions in the SQL that Spark and DuckDB share, so an oracle can render the same text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .tables import load

SIMPLE = ("Return", "Accept", "Hold")
REGULATION = ("Positive", "Negative", "Regulation")

# Words of the templates. Adjectives and the distractor are not in the dictionary.
EXPRESSIONS = {
    "simple_type": "CASE l_returnflag WHEN 'R' THEN 'Return' WHEN 'A' THEN 'Accept' ELSE 'Hold' END",
    "verb": "CASE l_returnflag WHEN 'R' THEN 'returns' WHEN 'A' THEN 'accepts' ELSE 'holds' END",
    "noun": "CASE l_returnflag WHEN 'R' THEN 'return' WHEN 'A' THEN 'acceptance' ELSE 'holding' END",
    "adjective": "CASE l_returnflag WHEN 'R' THEN 'returned' WHEN 'A' THEN 'accepted' ELSE 'withheld' END",
    "cust_type": "CASE WHEN c_mktsegment IN ('AUTOMOBILE', 'MACHINERY') THEN 'Positive' WHEN c_mktsegment IN ('HOUSEHOLD', 'FURNITURE') THEN 'Negative' ELSE 'Regulation' END",
    "supp_type": "CASE s_nationkey % 3 WHEN 0 THEN 'Positive' WHEN 1 THEN 'Negative' ELSE 'Regulation' END",
    "reg_noun": "CASE s_nationkey % 3 WHEN 0 THEN 'increase' WHEN 1 THEN 'decrease' ELSE 'control' END",
    "q": "CAST(floor(l_orderkey / 20) AS BIGINT)",
}
SECOND = {
    "reg_verb": "CASE WHEN CAST(floor(q / 4) AS BIGINT) % 2 = 1 THEN 'affects' WHEN cust_type = 'Positive' THEN 'raises' WHEN cust_type = 'Negative' THEN 'cuts' ELSE 'steers' END",
    "plain": "CASE WHEN q % 4 = 3 THEN 0 ELSE 1 END",
    "d": "CASE WHEN q % 11 = 5 THEN 3 ELSE 0 END",
    "kind": "CASE WHEN rn % 4 = 3 AND next_name IS NULL THEN 1 ELSE CAST(rn % 4 AS INT) END",
    "split": "CASE WHEN o_custkey % 10 < 7 THEN 'train' WHEN o_custkey % 10 = 7 THEN 'dev' ELSE 'test' END",
}
THIRD = {
    "phrase": "CASE WHEN plain = 1 THEN concat('the ', noun, ' of ', p_name) ELSE concat('the ', adjective, ' ', p_name) END",
    "front": "CASE WHEN d = 3 THEN 'after expression , ' ELSE '' END",
}
TEXT = (
    "concat(front, CASE kind WHEN 1 THEN concat(s_name, ' ', verb, ' ', p_name, ' .') "
    "WHEN 2 THEN concat(c_name, ' ', reg_verb, ' ', phrase, ' .') "
    "WHEN 3 THEN concat(s_name, ' bundles ', p_name, ' with ', next_name, ' .') "
    "ELSE concat(c_name, ' ', reg_verb, ' the ', reg_noun, ' of ', phrase, ' by ', s_name, ' .') END)"
)
#: Places of the parts of a sentence, counted in tokens. Part names have two words.
PLACES = {
    "simple_at": "CASE kind WHEN 1 THEN d + 1 WHEN 2 THEN d + 3 WHEN 0 THEN d + 6 END",
    "part_at": "CASE kind WHEN 1 THEN d + 2 WHEN 2 THEN d + 4 + plain WHEN 3 THEN d + 2 ELSE d + 7 + plain END",
    "next_at": "CASE WHEN kind = 3 THEN d + 5 END",
    "supp_at": "CASE WHEN kind = 0 THEN d + 10 + plain ELSE d END",
}
COLUMNS = ("l_orderkey", "l_partkey", "l_suppkey", "o_custkey")


#: Rows of a dimension that are sent to all executors at most, some 60 bytes each; a larger one meets the lines by a shuffle.
SENT = 1_500_000


def _sent(dimension: DataFrame) -> DataFrame:
    """A small dimension travels to the lines, which stay where their order is: a shuffle of all lines for each dimension is spared."""
    return F.broadcast(dimension) if dimension.limit(SENT + 1).count() <= SENT else dimension


def lines(spark: SparkSession, sf_dir: str, stride: int = 1) -> DataFrame:
    """One row a sentence with all that the rules need. Fact tables meet on the order key; the rank window uses the same key, so
    the join's shuffle serves it, too."""
    t = lambda n: load(spark, sf_dir, n)
    orders = t("orders").select("o_orderkey", "o_custkey")
    item = t("lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate", "l_returnflag")
    if stride > 1:
        orders, item = orders.filter(F.col("o_orderkey") % stride == 0), item.filter(F.col("l_orderkey") % stride == 0)
    rows = item.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    rows = rows.join(_sent(t("part").select("p_partkey", "p_name")), F.col("l_partkey") == F.col("p_partkey"))
    rows = rows.join(_sent(t("customer").select("c_custkey", "c_name", "c_mktsegment")), F.col("o_custkey") == F.col("c_custkey"))
    rows = rows.join(_sent(t("supplier").select("s_suppkey", "s_name", "s_nationkey")), F.col("l_suppkey") == F.col("s_suppkey"))
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate")
    rows = rows.withColumns({"rn": F.row_number().over(order), "next_name": F.lead("p_name").over(order), "next_part": F.lead("l_partkey").over(order)})
    for step in (EXPRESSIONS, SECOND, THIRD, {"text": TEXT}, PLACES):
        rows = rows.withColumns({k: F.expr(v) for k, v in step.items()})
    return rows.withColumn("sent_id", F.col("l_orderkey") * 100 + F.col("rn"))


def sentences(rows: DataFrame) -> DataFrame:
    return rows.select("sent_id", F.col("l_orderkey").alias("doc_id"), "split", "text")


def _parts(rows: DataFrame, *parts: tuple[str, dict[str, str]]) -> DataFrame:
    """A row for each part whose condition holds; parts are (condition, columns)."""
    structs = [F.when(F.expr(cond), F.struct(*[F.expr(e).alias(c) for c, e in cols.items()])) for cond, cols in parts]
    out = rows.select("sent_id", "split", F.explode(F.array(*structs)).alias("x")).filter("x is not null")
    return out.select("sent_id", "split", "x.*")


TRIGGER_PARTS = (
    ("kind IN (0, 1, 2)", {"trig_id": "sent_id * 10 + 1", "tok_from": "CAST(simple_at AS INT)", "tok_to": "CAST(simple_at AS INT)", "etype": "simple_type"}),
    ("kind IN (0, 2)", {"trig_id": "sent_id * 10 + 2", "tok_from": "CAST(d + 1 AS INT)", "tok_to": "CAST(d + 1 AS INT)", "etype": "cust_type"}),
    ("kind = 0", {"trig_id": "sent_id * 10 + 3", "tok_from": "CAST(d + 3 AS INT)", "tok_to": "CAST(d + 3 AS INT)", "etype": "supp_type"}),
    ("kind = 3", {"trig_id": "sent_id * 10 + 4", "tok_from": "CAST(d + 1 AS INT)", "tok_to": "CAST(d + 1 AS INT)", "etype": "'Binding'"}),
)
ENTITY_PARTS = (
    ("true", {"ent_id": "sent_id * 10 + 5", "etype": "'part'", "tok_from": "CAST(part_at AS INT)", "tok_to": "CAST(part_at + 1 AS INT)"}),
    ("kind = 3", {"ent_id": "sent_id * 10 + 6", "etype": "'part'", "tok_from": "CAST(next_at AS INT)", "tok_to": "CAST(next_at + 1 AS INT)"}),
    ("kind IN (0, 1, 3)", {"ent_id": "sent_id * 10 + 7", "etype": "'supplier'", "tok_from": "CAST(supp_at AS INT)", "tok_to": "CAST(supp_at AS INT)"}),
    ("kind IN (0, 2)", {"ent_id": "sent_id * 10 + 8", "etype": "'customer'", "tok_from": "CAST(d AS INT)", "tok_to": "CAST(d AS INT)"}),
)
ARGUMENT_PARTS = (
    ("kind IN (0, 1, 2)", {"trig_id": "sent_id * 10 + 1", "role": "'Theme'", "kind_": "'entity'", "ref": "sent_id * 10 + 5"}),
    ("kind = 2", {"trig_id": "sent_id * 10 + 2", "role": "'Theme'", "kind_": "'trigger'", "ref": "sent_id * 10 + 1"}),
    ("kind = 0", {"trig_id": "sent_id * 10 + 2", "role": "'Theme'", "kind_": "'trigger'", "ref": "sent_id * 10 + 3"}),
    ("kind IN (0, 2)", {"trig_id": "sent_id * 10 + 2", "role": "'Cause'", "kind_": "'entity'", "ref": "sent_id * 10 + 8"}),
    ("kind = 0", {"trig_id": "sent_id * 10 + 3", "role": "'Theme'", "kind_": "'trigger'", "ref": "sent_id * 10 + 1"}),
    ("kind = 0", {"trig_id": "sent_id * 10 + 3", "role": "'Cause'", "kind_": "'entity'", "ref": "sent_id * 10 + 7"}),
    ("kind = 3", {"trig_id": "sent_id * 10 + 4", "role": "'Theme'", "kind_": "'entity'", "ref": "sent_id * 10 + 5"}),
    ("kind = 3", {"trig_id": "sent_id * 10 + 4", "role": "'Theme'", "kind_": "'entity'", "ref": "sent_id * 10 + 6"}),
)


def triggers(rows: DataFrame) -> DataFrame:
    return _parts(rows, *TRIGGER_PARTS)


def entities(rows: DataFrame) -> DataFrame:
    return _parts(rows, *ENTITY_PARTS)


def arguments(rows: DataFrame) -> DataFrame:
    return _parts(rows, *ARGUMENT_PARTS).withColumnRenamed("kind_", "kind")


def part_structs(parts, *names: str) -> F.Column:
    """The parts of a sentence whose condition holds, as an array in its row."""
    structs = [F.when(F.expr(cond), F.struct(*[F.expr(cols[n]).alias(n.rstrip("_")) for n in names])) for cond, cols in parts]
    return F.filter(F.array(*structs), lambda x: x.isNotNull())


def nested(rows: DataFrame) -> DataFrame:
    """``sent_id, split, t, a``: the triggers and arguments of a sentence in its row, as ``decode.nested`` gathers them, without a shuffle."""
    return rows.select("sent_id", "split", part_structs(TRIGGER_PARTS, "trig_id", "etype", "tok_from", "tok_to").alias("t"), part_structs(ARGUMENT_PARTS, "trig_id", "role", "kind_", "ref").alias("a"))


def terminals(rows: DataFrame) -> DataFrame:
    """Concepts of the sentences by their keys: customers, suppliers and parts of the orders."""
    ids = F.array(F.concat(F.lit("C:"), "o_custkey"), F.concat(F.lit("S:"), "l_suppkey"), F.concat(F.lit("P:"), "l_partkey"))
    return rows.select(F.explode(ids).alias("node")).distinct()


#: Classes of terminals, in the order of their codes.
CODED = ("C:", "S:", "P:")


def code(prefix: str, key) -> F.Column:
    """A terminal as one number, which is sent and compared at a fraction of its name's size."""
    return F.shiftleft(key.cast("long"), 2) + F.lit(CODED.index(prefix))


def name_of(code) -> F.Column:
    return F.concat(F.element_at(F.array(*[F.lit(p) for p in CODED]), (code.bitwiseAND(F.lit(3)) + 1).cast("int")), F.shiftright(code, 2).cast("string"))


def terminal_codes(rows: DataFrame) -> DataFrame:
    """``code`` of each concept in ``terminals``."""
    ids = F.array(code("C:", F.col("o_custkey")), code("S:", F.col("l_suppkey")), code("P:", F.col("l_partkey")))
    return rows.select(F.explode(ids).alias("code")).distinct()


def sql_cte(stride: int = 1) -> str:
    """The same rendering as DuckDB common table expressions: ``note_lines``, ``note_sentences``, ``note_triggers``, ``note_entities``,
    ``note_arguments``."""
    where = f" WHERE l_orderkey % {stride} = 0" if stride > 1 else ""
    level = (
        f"note_0 AS (SELECT l_orderkey, l_partkey, l_suppkey, l_returnflag, o_custkey, p_name, c_name, c_mktsegment, s_name, s_nationkey,"
        f" CAST(row_number() OVER w AS INT) AS rn, lead(p_name) OVER w AS next_name, lead(l_partkey) OVER w AS next_part"
        f" FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey"
        f" JOIN supplier ON l_suppkey = s_suppkey{where}"
        f" WINDOW w AS (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate))"
    )
    parts, last = [level], "note_0"
    for i, step in enumerate((EXPRESSIONS, SECOND, THIRD, {"text": TEXT}, PLACES), 1):
        cols = ", ".join(f"{v} AS {k}" for k, v in step.items())
        parts.append(f"note_{i} AS (SELECT *, {cols} FROM {last})")
        last = f"note_{i}"
    parts.append(f"note_lines AS MATERIALIZED (SELECT *, l_orderkey * 100 + rn AS sent_id FROM {last})")
    parts.append("note_sentences AS MATERIALIZED (SELECT sent_id, l_orderkey AS doc_id, split, text FROM note_lines)")
    for name, pieces in (("triggers", TRIGGER_PARTS), ("entities", ENTITY_PARTS), ("arguments", ARGUMENT_PARTS)):
        union = " UNION ALL ".join("SELECT sent_id, split, " + ", ".join(f"{e} AS {c.rstrip('_')}" for c, e in cols.items()) + f" FROM note_lines WHERE {cond}" for cond, cols in pieces)
        parts.append(f"note_{name} AS MATERIALIZED ({union})")
    return ", ".join(parts)
