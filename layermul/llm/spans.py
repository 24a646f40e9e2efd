"""Native match spans: where a regex matches, from the pieces around the matches."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = "array<struct<start:bigint,rank:int,end:bigint,kind:string>>"


def quoted(s: str) -> str:
    """A SQL raw string literal."""
    return "r'" + s.replace("'", "\\x27") + "'"


def match_spans(text: str, pattern: str, kind: str, rank: int, group: int = 0, least: int = 0) -> Column:
    """Leftmost non-overlapping matches of `pattern` in the SQL expression `text` as
    array<struct<start, rank, end, kind>> in code points, end exclusive. Matches whose `group` is
    shorter than `least` are dropped after matching, without a retry. Patterns match no empty text."""
    p = quoted(pattern)
    held = f"length(g) >= {least}" if least else "true"
    return F.expr(
        f"""aggregate(
              zip_with(zip_with(regexp_extract_all({text}, {p}, 0), regexp_extract_all({text}, {p}, {group}),
                                (m, g) -> named_struct('m', m, 'g', g)),
                       slice(split({text}, {p}, -1), 1, size(regexp_extract_all({text}, {p}, 0))),
                       (a, s) -> named_struct('m', a.m, 'g', a.g, 's', s)),
              named_struct('at', 0L, 'out', cast(array() as {SPAN})),
              (acc, x) -> named_struct(
                'at', acc.at + length(x.s) + length(x.m),
                'out', if({held.replace("(g)", "(x.g)")},
                          concat(acc.out, array(named_struct('start', acc.at + length(x.s), 'rank', {rank},
                                 'end', acc.at + length(x.s) + length(x.m), 'kind', '{kind}'))), acc.out)),
              acc -> acc.out)"""
    )


def span_text(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined in the given order."""
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def ascii_lower(text: Column) -> Column:
    """A-Z only, whatever the locale."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def span_sql(rules: list[tuple[str, str, int, int]], source: str) -> str:
    """DuckDB twin: CTE text whose last table `spanned` is `source` (with a column text) plus list
    column s of all spans of rules (pattern, kind, group, least), ranked by place, sorted."""

    def q(pattern: str) -> str:
        return "'" + pattern.replace("'", "''") + "'"

    cols = ", ".join(
        f"list_transform(regexp_extract_all(text, {q(p)}), lambda m: length(m)) AS m{i}, "
        f"list_transform(regexp_extract_all(text, {q(p)}, {g}), lambda m: length(m)) AS g{i}, "
        f"list_transform(string_split_regex(text, {q(p)}), lambda m: length(m)) AS p{i}"
        for i, (p, _, g, _) in enumerate(rules)
    )
    one = (
        "list_filter(list_transform(range(1, len(m{i}) + 1), lambda i: {{"
        "'start': (list_sum(list_slice(p{i}, 1, i)) + coalesce(list_sum(list_slice(m{i}, 1, i - 1)), 0))::BIGINT, 'rank': {i}, "
        "'end': (list_sum(list_slice(p{i}, 1, i)) + list_sum(list_slice(m{i}, 1, i)))::BIGINT, 'kind': '{kind}', 'size': g{i}[i]}}), "
        "lambda x: x.size >= {least})"
    )
    lists = ", ".join(one.format(i=i, kind=k, least=least) for i, (_, k, _, least) in enumerate(rules))
    return f"""cut AS (SELECT *, {cols} FROM {source}),
      spanned AS (SELECT *, list_sort(flatten([{lists}])) AS s FROM cut)"""
