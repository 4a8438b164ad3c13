"""Addresses: normalisation, parsing into ordered parts, reassembly."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Abbreviation -> word.
ABBREVIATIONS = {"st": "street", "rd": "road", "ave": "avenue", "dr": "drive", "blk": "block"}
STATES = ["AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST"]


def normalise(c: Column, words: dict[str, str] | None = None) -> Column:
    """Lower case, no punctuation, single spaces, abbreviations written out."""
    tokens = F.split(F.trim(F.regexp_replace(F.lower(c), r"[^\p{L}\p{N}]+", " ")), " ")
    table = F.create_map(*[F.lit(x) for kv in (words or ABBREVIATIONS).items() for x in kv])
    return F.array_join(F.transform(tokens, lambda t: F.coalesce(F.try_element_at(table, t), t)), " ")


def parse(c: Column) -> Column:
    """struct<block, street, state, country, full>; a part that isn't there is null."""
    n = normalise(c)
    states = "|".join(s.lower() for s in STATES)
    part = lambda pattern, g: F.nullif(F.regexp_extract(n, pattern, g), F.lit(""))
    return F.struct(
        part(r"^(\d+) ", 1).alias("block"), F.nullif(F.trim(F.regexp_replace(F.regexp_replace(n, rf" ?({states})$", ""), r"^\d+ ", "")), F.lit("")).alias("street"),
        part(rf"({states})$", 1).alias("state"), F.lit(None).cast("string").alias("country"), n.alias("full"),
    )


def render(s: Column) -> Column:
    """Block, street, state and country in that order; missing parts are skipped."""
    return F.concat_ws(", ", F.concat_ws(" ", s["block"], s["street"]), s["state"], s["country"])
