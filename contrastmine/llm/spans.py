"""Places of regular-expression matches in code points, with DataFrame functions only.

Spark gives the matches of a pattern and the text between them, but not where they lie. Both lists together hold every
character once, so running sums of their lengths are the places. The sums are two-level, over blocks of about the square
root of the number of matches, so that a very long text with many matches stays cheap."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def quoted(pattern: str) -> str:
    """A pattern as a SQL string literal."""
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def let(value: Column, body) -> Column:
    """body(value), with the value computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def length_sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0), lambda s, x: s + x)


SPAN = "array<struct<start:int,stop:int,hit:string,part:string>>"


def located(text: Column, pattern: str, group: int = 0, guard: Column | None = None) -> Column:
    """Array of (start, stop, hit, part) of all leftmost, non-overlapping matches; part is the given group. Empty where the guard is false."""

    def place(t: Column) -> Column:
        hits = F.regexp_extract_all(t, F.lit(pattern), F.lit(0))
        parts = F.regexp_extract_all(t, F.lit(pattern), F.lit(group)) if group else hits

        def spans(x: Column) -> Column:
            n = F.size(x.hits)
            block = F.ceil(F.sqrt(n)).cast("int")
            steps = F.zip_with(F.slice(x.rest, 1, n), x.hits, lambda r, h: F.length(r) + F.length(h))

            def with_steps(y: Column) -> Column:
                sums = F.transform(F.sequence(F.lit(0), n - 1, block), lambda k: length_sum(F.slice(y, k + 1, block)))

                def with_sums(z: Column) -> Column:
                    def one(h: Column, i: Column) -> Column:
                        whole = F.floor(i / block).cast("int")
                        before = length_sum(F.slice(z, 1, whole)) + length_sum(F.slice(y, whole * block + 1, i - whole * block))
                        start = before + F.length(F.get(x.rest, i))
                        return F.struct(start.alias("start"), (start + F.length(h)).alias("stop"), h.alias("hit"), F.get(x.parts, i).alias("part"))

                    return F.transform(x.hits, one)

                return let(sums, with_sums)

            return let(steps, with_steps)

        found = F.struct(hits.alias("hits"), parts.alias("parts"), F.split(t, pattern, -1).alias("rest"))
        return let(found, lambda x: F.when(F.size(x.hits) > 0, spans(x)).otherwise(F.array().cast(SPAN)))

    placed = place(text)
    return placed if guard is None else F.when(guard, placed).otherwise(F.array().cast(SPAN))


def written(kind: str, spans: Column) -> Column:
    """kind:start:stop of each span."""
    return F.transform(spans, lambda s: F.concat_ws(":", F.lit(kind), s.start.cast("string"), s.stop.cast("string")))


def masked(text: Column, spans: Column, mark: str) -> Column:
    """The text with every stretch that spans cover, overlapping or not, replaced by one mark. spans: array of (start, stop)."""
    first = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def fold(acc: Column, s: Column) -> Column:
        fresh = s.start >= acc.at
        out = F.when(fresh, F.concat(acc.out, F.substring(text, acc.at + 1, s.start - acc.at), F.lit(mark))).otherwise(acc.out)
        return F.struct(F.greatest(acc.at, s.stop).alias("at"), out.alias("out"))

    done = F.aggregate(F.array_sort(spans), first, fold, lambda acc: F.concat(acc.out, F.substring(text, acc.at + 1, F.length(text))))
    return F.when(F.size(spans) > 0, done).otherwise(text)
