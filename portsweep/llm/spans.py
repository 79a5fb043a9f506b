"""Match positions from built-in functions: Spark's regexp functions give texts but not places, so the gaps are measured."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NONE = "cast(array() as array<struct<s:int,e:int,m:string>>)"


def add_matches(df: DataFrame, name: str, text: str, pattern: str, when: Column) -> DataFrame:
    """Column `name`: array of (s, e, m), the leftmost non-overlapping matches of pattern in column `text`.

    s and e count code points, e is exclusive. `when` is a cheap test that every text with a match passes. Patterns keep
    repetition possessive, so that no text makes the matcher backtrack or recurse deeply.
    """
    found, gaps = f"__m_{name}", f"__g_{name}"
    df = df.withColumn(found, F.when(when, F.regexp_extract_all(F.col(text), F.lit(pattern), F.lit(0))))
    df = df.withColumn(gaps, F.when(F.size(found) > 0, F.transform(F.split(F.col(text), pattern, -1), lambda x: F.length(x))))
    steps = F.zip_with(F.slice(gaps, 1, F.size(found)), F.col(found), lambda g, m: F.struct(g.alias("g"), F.length(m).alias("n")))
    start = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<int>)").alias("out"))
    places = F.aggregate(steps, start, lambda a, x: F.struct((a["at"] + x["g"] + x["n"]).alias("at"), F.concat(a["out"], F.array(a["at"] + x["g"])).alias("out")), lambda a: a["out"])
    spans = F.zip_with(places, F.col(found), lambda s, m: F.struct(s.alias("s"), (s + F.length(m)).alias("e"), m.alias("m")))
    return df.withColumn(name, F.when(F.size(found) > 0, spans).otherwise(F.expr(NONE))).drop(found, gaps)


def tagged(name: str, kind: int) -> Column:
    """The matches in column `name` as (kind, s, e, m)."""
    return F.transform(name, lambda x: F.struct(F.lit(kind).alias("kind"), x["s"].alias("s"), x["e"].alias("e"), x["m"].alias("m")))


def listed(spans: Column, kinds: tuple[str, ...]) -> Column:
    """kind:start:end of sorted spans, comma-joined."""
    names = F.array(*[F.lit(k) for k in kinds])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["s"], x["e"])), ",")
