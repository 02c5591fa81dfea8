"""The compression as SQL text, for any engine."""

from __future__ import annotations

from lincompress.plans.design import ModelSpec


def compress_stats_sql(spec: ModelSpec, table: str) -> str:
    keys = list(spec.keys.items())
    parts = [sql.replace("`", '"') + f' AS "{name}"' for name, sql in keys] + ["count(*) AS cnt"]
    for y in spec.outcomes:
        parts += [f'sum("{y}") AS "sy_{y}"', f'sum("{y}" * "{y}") AS "syy_{y}"']
    tail = " GROUP BY " + ", ".join(str(i + 1) for i in range(len(keys))) if keys else ""
    return f"SELECT {', '.join(parts)} FROM {table}{tail}"
