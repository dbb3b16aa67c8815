"""From triggers and arguments to events. Nested events refer to their arguments by id, so depth needs no nested types."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SIMPLE = ("Accept", "Hold", "Return")
REGULATION = ("Negative", "Positive", "Regulation")
BINDING = ("Binding",)


def unmerge_simple(triggers: DataFrame, arguments: DataFrame) -> DataFrame:
    """``sent_id, trig_id, etype, theme``: one event a theme."""
    t = triggers.filter(F.col("etype").isin(*SIMPLE)).select("sent_id", "trig_id", "etype")
    a = arguments.filter("role = 'Theme' and kind = 'entity'").select("sent_id", "trig_id", F.col("ref").alias("theme"))
    return t.join(a, ["sent_id", "trig_id"])


def unmerge_binding(triggers: DataFrame, arguments: DataFrame) -> DataFrame:
    """``sent_id, trig_id, etype, themes``: one event a trigger with all its themes."""
    t = triggers.filter(F.col("etype").isin(*BINDING)).select("sent_id", "trig_id", "etype")
    a = arguments.filter("role = 'Theme' and kind = 'entity'").groupBy("sent_id", "trig_id").agg(F.sort_array(F.collect_set("ref")).alias("themes"))
    return t.join(a, ["sent_id", "trig_id"])


def unmerge_regulation(triggers: DataFrame, arguments: DataFrame) -> DataFrame:
    """``sent_id, trig_id, etype, theme_kind, theme, cause_kind, cause``: themes times causes; a cause is optional, a theme is not."""
    t = triggers.filter(F.col("etype").isin(*REGULATION)).select("sent_id", "trig_id", "etype")
    part = lambda role, name: arguments.filter(F.col("role") == role).select("sent_id", "trig_id", F.col("kind").alias(f"{name}_kind"), F.col("ref").alias(name))
    return t.join(part("Theme", "theme"), ["sent_id", "trig_id"]).join(part("Cause", "cause"), ["sent_id", "trig_id"], "left")


def nested(triggers: DataFrame, arguments: DataFrame) -> DataFrame:
    """``sent_id, t, a``: a row a sentence with its triggers (trig_id, etype and what else there is) and its arguments (trig_id, role, kind, ref)."""
    more = [c for c in ("tok_from", "tok_to") if c in triggers.columns]
    t = triggers.groupBy("sent_id").agg(F.collect_list(F.struct("trig_id", "etype", *more)).alias("t"))
    a = arguments.groupBy("sent_id").agg(F.collect_list(F.struct("trig_id", "role", "kind", "ref")).alias("a"))
    return t.join(a, "sent_id", "left").withColumn("a", F.coalesce("a", F.array()))


def events_of(rows: DataFrame, max_depth: int = 5, t: str = "t", a: str = "a", out: str = "events") -> DataFrame:
    """``rows`` (``nested``) with ``out``, all well-formed events of each sentence, bottom up: event_id, etype, trig_id, level, theme, cause.

    Level 0 has only entity arguments. An argument that is a trigger stands for each of its events that are known already; the next level is
    made of regulations that need an event of the level before. References in a circle, or to triggers without events, never get a level
    and so are left out. ``theme`` is a comma-joined list of argument ids (``e<id>`` for entities). A sentence is decoded where its row is.
    """
    quoted = lambda names: ", ".join(f"'{n}'" for n in names)
    of = lambda x, rest: f"filter({a}, y -> y.trig_id = {x}.trig_id and {rest})"
    made = lambda x, theme, cause: f"named_struct('trig_id', {x}.trig_id, 'etype', {x}.etype, 'theme', {theme}, 'cause', {cause})"
    entity, none = "y.role = 'Theme' and y.kind = 'entity'", "cast(null as string)"
    simple = f"flatten(transform(filter({t}, x -> x.etype in ({quoted(SIMPLE)})), x -> transform({of('x', entity)}, z -> {made('x', "concat('e', z.ref)", none)})))"
    themes = f"array_join(transform(array_sort(array_distinct(transform({of('x', entity + ' and y.ref is not null')}, z -> z.ref))), z -> concat('e', z)), ',')"
    binding = f"transform(filter({t}, x -> x.etype in ({quoted(BINDING)}) and size({of('x', entity)}) > 0), x -> {made('x', themes, none)})"
    cause = of("x", "y.role = 'Cause'")
    parts = "named_struct('trig_id', x.trig_id, 'etype', x.etype, 'theme_kind', th.kind, 'theme', th.ref, 'cause_kind', c.kind, 'cause', c.ref)"
    theme = of("x", "y.role = 'Theme'")
    regulations = f"flatten(transform(filter({t}, x -> x.etype in ({quoted(REGULATION)})), x -> flatten(transform({theme}, th -> transform(if(size({cause}) > 0, {cause}, array(get({a}, -1))), c -> {parts})))))"
    flat = f"transform(filter(_reg, r -> r.theme_kind = 'entity' and (r.cause_kind is null or r.cause_kind = 'entity')), r -> {made('r', "concat('e', r.theme)", "concat('e', r.cause)")})"
    identified = lambda found, level: f"transform({found}, m -> named_struct('event_id', concat(m.etype, '(', m.trig_id, ';', m.theme, ';', coalesce(m.cause, '-'), ')'), 'etype', m.etype, 'trig_id', m.trig_id, 'level', {level}, 'theme', m.theme, 'cause', m.cause))"
    rows = rows.withColumn("_reg", F.expr(regulations))
    rows = rows.withColumn(out, F.expr(identified(f"concat({simple}, {binding}, {flat})", 0)))
    rows = rows.withColumn("_open", F.expr("filter(_reg, r -> r.theme_kind = 'trigger' or r.cause_kind = 'trigger')"))

    def side(name: str) -> str:
        """The ids and levels that a theme or cause stands for."""
        one = "array(named_struct('id', {}, 'lv', -1))".format
        known = f"transform(filter({out}, k -> r.{name}_kind = 'trigger' and k.trig_id = r.{name}), k -> named_struct('id', k.event_id, 'lv', k.level))"
        entities = f"when r.{name}_kind = 'entity' then {one(f"concat('e', r.{name})")}"
        return f"case {entities} {'' if name == 'theme' else f'when r.cause_kind is null then {one(none)}'} else {known} end"

    for level in range(1, max_depth + 1):
        made_of = "named_struct('trig_id', r.trig_id, 'etype', r.etype, 'theme', th.id, 'cause', c.id, 'ok', th.id is not null and (r.cause_kind is null or c.id is not null), 'newest', greatest(th.lv, c.lv))"
        found = f"flatten(transform(_open, r -> flatten(transform({side('theme')}, th -> transform({side('cause')}, c -> {made_of})))))"
        # An event inside itself: its trigger occurs in an argument's id already.
        found = f"filter({found}, m -> m.ok and m.newest = {level - 1} and not contains(concat_ws('|', m.theme, m.cause), concat('(', m.trig_id, ';')))"
        rows = rows.withColumn(out, F.expr(f"if(size(_open) = 0, {out}, concat({out}, {identified(found, level)}))"))
    return rows.drop("_reg", "_open")


def unmerge(triggers: DataFrame, arguments: DataFrame, max_depth: int = 5) -> DataFrame:
    """``sent_id, event_id, etype, trig_id, level, theme, cause``: the events of ``events_of``, one a row."""
    return flat(events_of(nested(triggers, arguments), max_depth))


def one_a_row(rows: DataFrame, column: str, *fields: str) -> DataFrame:
    """``sent_id`` and the fields of each struct in an array. The outer form is filtered afterwards: a plain explode makes the optimiser move
    a test of the array's size below all that the array is made of, and write that out once a reference."""
    return rows.select("sent_id", F.explode_outer(column).alias("e")).filter("e is not null").select("sent_id", *[f"e.{c}" for c in fields])


def flat(rows: DataFrame, events: str = "events") -> DataFrame:
    return one_a_row(rows, events, "event_id", "etype", "trig_id", "level", "theme", "cause")


def dropped(triggers: DataFrame, events: DataFrame) -> DataFrame:
    """``sent_id, trig_id``: triggers without a well-formed event."""
    return triggers.select("sent_id", "trig_id").join(events.select("sent_id", "trig_id").distinct(), ["sent_id", "trig_id"], "left_anti")
