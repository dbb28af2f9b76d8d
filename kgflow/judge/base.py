"""Decision points: the places where a model would be asked, with replaceable backends.

Requests are told apart by the md5 of their canonical input, and answered once per distinct
request: from a verdict table where one is given (replay), else by rules as columns, else by a
batch client (external), so cost follows distinct undecided requests.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgflow.functions.ids import joined_id

KINDS = {
    "infer_type": (),
    "entity_pair": ("MERGE", "HIERARCHY", "SEPARATE"),
    "event_pair": ("MERGE", "HIERARCHY", "SEPARATE"),
    "evidence_gate": ("ACCEPTED", "REJECTED"),
    "intent": ("INFORMATIONAL", "EVOLUTIONARY"),
    "schema_review": ("PASS", "POOL"),
    "support": ("fully_supported", "partially_supported", "not_supported"),
    "deletion": ("justified", "unjustified"),
}


@dataclass(frozen=True)
class DecisionPoint:
    kind: str
    inputs: tuple[str, ...]
    rule: Column | None = None
    client: Callable[[Iterator], Iterator] | None = None

    def request(self) -> Column:
        return joined_id(F.lit(self.kind), *self.inputs)

    def decide(self, df: DataFrame, replay: DataFrame | None = None) -> DataFrame:
        """df with request and verdict; replay: (request, verdict), one row per request."""
        out = df.withColumn("request", self.request())
        fallback = self.rule if self.rule is not None else F.lit(None).cast("string")
        if replay is None and self.client is None:
            return out.withColumn("verdict", fallback)
        known = replay.select("request", F.col("verdict").alias("_given")) if replay is not None else None
        if self.client is not None:
            open_ = out.select("request", *self.inputs).dropDuplicates(["request"])
            if known is not None:
                open_ = open_.join(known, "request", "left_anti")
            asked = open_.mapInPandas(self.client, "request string, _given string")
            known = asked if known is None else known.unionByName(asked)
        return out.join(known, "request", "left").withColumn("verdict", F.coalesce("_given", fallback)).drop("_given")


def prompt(kind: str, rows: Column, shots: list[tuple[str, str]] = ()) -> Column:
    """Text of a request to an external model: task, worked examples, then the rows."""
    if kind not in KINDS:
        raise ValueError(kind)
    head = f"Task: {kind}. Answers: {', '.join(KINDS[kind]) or 'free'}.\n" + "".join(f"Input: {a}\nAnswer: {b}\n" for a, b in shots)
    return F.concat(F.lit(head), F.lit("Input: "), rows, F.lit("\nAnswer:"))


def requests_saved(df: DataFrame, point: DecisionPoint) -> DataFrame:
    """(decisions, requests): how many calls de-duplication leaves."""
    return df.select(point.request().alias("r")).agg(F.count("*").alias("decisions"), F.countDistinct("r").alias("requests"))
