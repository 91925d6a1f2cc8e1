"""Native span search: every match of a pattern in a text, with code-point offsets, from DataFrame functions alone.

A pattern's matches are fenced by a separator, the text is split there, and the running length of the parts gives each
match's offsets.  The separator (U+0001) is first turned into another character of no pattern, which keeps all
offsets; patterns may use neither.  Patterns are Java regular expressions without loops of groups that could
backtrack (possessive where they repeat), so long runs neither recurse deeply nor take quadratic time.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

FENCE, STANDIN = "\x01", "\x02"
HELD = 128  # matches gathered in one array, so that appending copies few of them


def fenced(text: Column, pattern: str | Column) -> Column:
    """The text's parts: at odd places (0-based) the matches, in order."""
    clean = F.when(F.contains(text, F.lit(FENCE)), F.translate(text, FENCE, STANDIN)).otherwise(text)
    return F.split(F.regexp_replace(clean, pattern if isinstance(pattern, Column) else F.lit(pattern), F.lit(f"{FENCE}$0{FENCE}")), FENCE, -1)


def matches(text: Column, pattern: str | Column) -> Column:
    """Array of struct(s, e, v): start and end (exclusive, code points) and text of each leftmost non-overlapping match."""
    parts = fenced(text, pattern)  # evaluated again by the walk, but only for texts that have a match
    empty = F.array().cast("array<struct<s:int,e:int,v:string>>")

    def step(acc: Column, part: Column) -> Column:
        end = acc["at"] + F.char_length(part)
        hit, full = F.array(F.struct(acc["at"].alias("s"), end.alias("e"), part.alias("v"))), F.size(acc["found"]) >= HELD
        odd = acc["i"] % 2 == 1
        return F.struct(
            end.alias("at"),
            (acc["i"] + 1).alias("i"),
            F.when(odd & full, hit).when(odd, F.concat(acc["found"], hit)).otherwise(acc["found"]).alias("found"),
            F.when(odd & full, F.concat(acc["done"], F.array(acc["found"]))).otherwise(acc["done"]).alias("done"),
        )

    start = F.struct(F.lit(0).alias("at"), F.lit(0).alias("i"), empty.alias("found"), F.array().cast("array<array<struct<s:int,e:int,v:string>>>").alias("done"))
    walked = F.aggregate(parts, start, step, lambda acc: F.flatten(F.concat(acc["done"], F.array(acc["found"]))))
    return F.when(F.size(parts) > 1, walked).otherwise(empty)


def joined(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined; spans are structs with k (kind), s and e."""
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["k"], x["s"].cast("string"), x["e"].cast("string"))), ",")


def of_kind(found: Column, kind: str, order: int) -> Column:
    """Spans as struct(s, o, e, k): start, the kind's place in the listing, end, kind."""
    return F.transform(found, lambda x: F.struct(x["s"].alias("s"), F.lit(order).alias("o"), x["e"].alias("e"), F.lit(kind).alias("k")))


def masked(text: Column, spans: Column) -> Column:
    """The text with each span (sorted by start) replaced by its kind in brackets; overlapping spans give one mask."""
    state = F.aggregate(
        spans,
        F.struct(F.lit("").alias("out"), F.lit(0).alias("at")),
        lambda acc, x: F.when(x["s"] < acc["at"], F.struct(acc["out"].alias("out"), F.greatest(acc["at"], x["e"]).alias("at"))).otherwise(
            F.struct(F.concat(acc["out"], F.substring(text, acc["at"] + 1, x["s"] - acc["at"]), F.lit("["), F.upper(x["k"]), F.lit("]")).alias("out"), x["e"].alias("at"))
        ),
    )
    done = F.concat(state["out"], F.substring(text, state["at"] + 1, F.char_length(text)))
    return F.when(F.size(spans) > 0, done).otherwise(text)


def blanked(text: Column, spans: Column) -> Column:
    """The text with each span (sorted by start) replaced by as many spaces, so that all offsets stay."""

    def step(acc: Column, x: Column) -> Column:
        start = F.greatest(acc["at"], x["s"])
        kept, gap = F.substring(text, acc["at"] + 1, start - acc["at"]), F.repeat(F.lit(" "), F.greatest(F.lit(0), x["e"] - start))
        return F.struct(F.concat(acc["out"], kept, gap).alias("out"), F.greatest(acc["at"], x["e"]).alias("at"))

    state = F.aggregate(spans, F.struct(F.lit("").alias("out"), F.lit(0).alias("at")), step)
    return F.concat(state["out"], F.substring(text, state["at"] + 1, F.char_length(text)))
