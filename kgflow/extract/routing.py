"""Which track a statement takes: plain triples by default, events where time, a change of state
or more than two arguments matter."""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TIME = r"\b(19|20)[0-9]{2}(-[0-9]{2}-[0-9]{2})?\b"
CHANGE = r"(?i)\b(activated|deprecated|removed|replaced|retired|announced|superseded)\b"
#: Of which every text that CHANGE finds has one, in lower case; cheaper to look for than words. All end in "ed".
PARTS = ("ated", "removed", "replaced", "retired", "announced", "superseded")


def track(text: Column | str) -> Column:
    text = F.col(text) if isinstance(text, str) else text
    commas = F.length(text) - F.length(F.replace(F.replace(text, F.lit(","), F.lit("")), F.lit(";"), F.lit("")))
    year = (F.contains(text, F.lit("19")) | F.contains(text, F.lit("20"))) & text.rlike(TIME)
    change = F.contains(F.lower(text), F.lit("ed")) & reduce(or_, (F.contains(F.lower(text), F.lit(x)) for x in PARTS)) & text.rlike(CHANGE)
    return F.when(year | change | (commas >= 2), "event").otherwise("static")


def route(stmts: DataFrame, tracks: str = "routed") -> DataFrame:
    """stmts with a column track; tracks: routed, static (never events) or both (each statement twice)."""
    if tracks == "static":
        return stmts.withColumn("track", F.lit("static"))
    if tracks == "both":
        return stmts.withColumn("track", F.explode(F.array(F.lit("static"), F.lit("event"))))
    return stmts.withColumn("track", track("text"))
