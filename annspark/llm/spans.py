"""Spans of pattern matches in whole texts, with built-in SQL functions only.

Spark gives the matches of a pattern but not their places. Splitting the text by
the same pattern gives the pieces between them, so each start is the summed
length of what stands before. Lengths count code points; ends are exclusive.

A pattern here must equal its contract's pattern in what it matches, but may
carry look-behinds and possessive quantifiers: both keep a scan linear in the
text and Java's matcher from recursing on long runs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SPAN = "struct<start: bigint, end: bigint, value: string, left: string, right: string>"
#: Matches placed together.
RUN = 128
#: Characters of left and right context kept beside a match.
LEFT = RIGHT = 48


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def located(text: str, found: str, pattern: str) -> Column:
    """array<SPAN> of the matches ``found`` (a column) of ``pattern`` in ``text`` (a column).

    An array that grows is copied at each step, so matches are placed in runs of
    RUN, and the runs are put together at the end.
    """
    none = f"cast(array() AS array<{SPAN}>)"
    place = (
        "(a, m) -> named_struct('at', a.at + length(m.piece) + length(m.value), 'out', array_append(a.out, named_struct("
        "'start', a.at + length(m.piece), 'end', a.at + length(m.piece) + length(m.value), "
        f"'value', m.value, 'left', substring(m.piece, -{LEFT}), 'right', m.right)))"
    )
    run = f"aggregate(slice(ms, j * {RUN} + 1, {RUN}), named_struct('at', s.at, 'out', {none}), {place})"
    return F.expr(f"""
        CASE WHEN size(`{found}`) > 0 THEN
            transform(
                transform(array(split(`{text}`, {_quoted(pattern)}, -1)), ps -> zip_with(
                    zip_with(slice(ps, 1, size(`{found}`)), `{found}`, (x, y) -> named_struct('piece', x, 'value', y)),
                    slice(ps, 2, size(`{found}`)), (m, z) -> named_struct('piece', m.piece, 'value', m.value, 'right', substring(z, 1, {RIGHT})))),
                ms -> aggregate(
                    sequence(0, cast((size(ms) - 1) div {RUN} AS int)), named_struct('at', 0L, 'out', cast(array() AS array<array<{SPAN}>>)),
                    (s, j) -> transform(array({run}), r -> named_struct('at', r.at, 'out', array_append(s.out, r.out)))[0],
                    s -> flatten(s.out)))[0]
        ELSE {none} END""")


def with_spans(df: DataFrame, text: str, patterns: dict[str, tuple[str, str]]) -> DataFrame:
    """Add a column for each name in ``patterns``: (pattern, SQL condition on the match m).

    A match that fails its condition is dropped after matching, without a retry.
    """
    raw = df.select("*", *[F.expr(f"regexp_extract_all(`{text}`, {_quoted(p)}, 0)").alias(f"{name}__raw") for name, (p, _) in patterns.items()])
    placed = raw.select(*df.columns, *[located(text, f"{name}__raw", p).alias(f"{name}__at") for name, (p, _) in patterns.items()])
    return placed.select(*df.columns, *[F.expr(f"filter(`{name}__at`, m -> {test})").alias(name) for name, (_, test) in patterns.items()])


def merged(names: dict[str, str]) -> Column:
    """One sorted array of (start, k, end, kind) of the span columns: column -> kind, in listed order."""
    parts = [F.expr(f"transform(`{c}`, m -> named_struct('start', m.start, 'k', {k}, 'end', m.end, 'kind', '{kind}'))") for k, (c, kind) in enumerate(names.items())]
    return F.array_sort(F.concat(*parts))


def joined(spans: Column) -> Column:
    """kind:start:end of each span, joined by commas."""
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))


def clear_of(extra: str, base: str) -> Column:
    """The spans of column ``extra`` that overlap none of the (start, k, end, kind) array ``base``."""
    return F.expr(f"filter(`{extra}`, c -> not exists(`{base}`, b -> b.start < c.end and c.start < b.end))")


def replaced(text: str, spans: str, marks: dict[str, str]) -> Column:
    """``text`` with each span of the sorted array column ``spans`` replaced by its kind's mark.

    Of overlapping spans the joint stretch is replaced once, by the first one's mark.
    """
    mark = "CASE s.kind " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in marks.items()) + " ELSE '' END"
    return F.expr(f"""
        CASE WHEN size(`{spans}`) > 0 THEN
            aggregate(`{spans}`, named_struct('at', 0L, 'out', cast(array() AS array<string>)),
                (a, s) -> named_struct(
                    'at', greatest(a.at, s.end),
                    'out', CASE WHEN s.start < a.at THEN a.out
                        ELSE concat(a.out, array(substring(`{text}`, cast(a.at + 1 AS int), cast(s.start - a.at AS int)), {mark})) END),
                a -> concat(array_join(a.out, ''), substring(`{text}`, cast(a.at + 1 AS int))))
        ELSE `{text}` END""")
