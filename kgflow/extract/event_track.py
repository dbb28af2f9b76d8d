"""Event track: trigger, roles and time out of statements."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SHAPE = r"^At ([0-9:. \-]+): (?:access for |plan of )?(acct [0-9]+) (seat [0-9]+) (was activated|is deprecated|was replaced by|opened|viewed)(?: (?:tier|item) ([0-9]+))?"
#: Words that announce a change of state.
EVOLUTIONARY = ("activated", "deprecated", "removed", "replaced", "retired", "superseded")
STATE_RELATIONS = ("status", "plan")


def found(i: int) -> Column:
    return F.regexp_extract("text", SHAPE, i)


def shaped() -> Column:
    """Whether the text has an event's structure."""
    return F.coalesce(F.regexp_replace(found(4), r"^(was|is) | by$", "") != "", F.lit(False))


def events(stmts: DataFrame) -> DataFrame:
    """Rows of stmts with trigger, alias, qualifier, object and valid_time; statements of another shape go."""
    trigger = F.regexp_replace(found(4), r"^(was|is) | by$", "")
    return (
        stmts.withColumn("trigger", trigger).where("trigger <> ''")
        .withColumn("alias", found(2)).withColumn("qualifier", found(3))
        .withColumn("object", F.nullif(found(5), F.lit("")))
        .withColumn("valid_time", F.trim(found(1)).cast("timestamp_ntz"))
    )


def as_structs(ev: DataFrame) -> DataFrame:
    """(event_id, trigger, roles map<string, array<string>>, time struct) per event."""
    roles = F.map_filter(
        F.create_map(F.lit("subject"), F.array(F.concat_ws(" ", "alias", "qualifier")), F.lit("object"), F.array("object")),
        lambda k, v: F.exists(v, lambda x: x.isNotNull()),
    )
    return ev.select(F.col("stmt_id").alias("event_id"), "trigger", roles.alias("roles"), F.struct(F.col("valid_time").alias("start"), F.col("valid_time").alias("end"), F.lit("instant").alias("granularity")).alias("time"), "batch_id")


def state_facts(ev: DataFrame, coref: bool = True) -> DataFrame:
    """(head, relation, tail, valid_time, ord, stmt_id, batch_id): the state each event asserts.

    Without coreference the short alias alone is the head."""
    head = F.concat_ws(" ", "alias", "qualifier") if coref else F.col("alias")
    relation = F.when(F.col("trigger").isin("activated", "deprecated"), "status").when(F.col("trigger") == "replaced", "plan")
    tail = F.when(F.col("trigger") == "activated", F.lit("active")).when(F.col("trigger") == "deprecated", F.lit("deprecated")).otherwise(F.concat(F.lit("tier "), F.col("object")))
    return ev.select(head.alias("head"), relation.alias("relation"), tail.alias("tail"), "valid_time", F.array(F.col("seq").cast("bigint")).alias("ord"), "stmt_id", "batch_id").where("relation is not null")
