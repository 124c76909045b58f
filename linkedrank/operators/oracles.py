"""DuckDB SQL of queries over a linked schema, built from the same portable definitions."""

from __future__ import annotations

from linkedrank.functions.scoring import S
from linkedrank.operators.evaluate import StandingQuery
from linkedrank.plans import networks
from linkedrank.plans.catalog import LinkedSchema

DUCK_TOKENS = "list_filter(regexp_split_to_array(lower(text), '[^\\p{L}\\p{N}]+'), lambda x: x <> '')"


def relation_ctes(schema: LinkedSchema, query: StandingQuery, ceilings: bool = True, filters: dict[str, str] | None = None) -> list[str]:
    """CTEs r_, c_, t_, m_, f_ per relation: rows, counts, statistics, matched and free sets."""
    out, m = [], query.margins
    for name, spec in schema.relations.items():
        links = "".join(f", {x}" for x in schema.link_columns(name))
        keep = f" WHERE {filters[name]}" if filters and name in filters else ""
        out.append(f"r_{name} AS (SELECT * FROM ({schema.duck(name)}){keep})")
        if not spec.has_text:
            out.append(f"f_{name} AS (SELECT key{links} FROM r_{name})")
            continue
        tf = "".join(f", len(list_filter(terms, lambda x: x = '{w}')) AS tf_{i}" for i, w in enumerate(query.words))
        out.append(f"c_{name} AS (SELECT key{links}, length(text) AS dl{tf} FROM (SELECT *, {DUCK_TOKENS} AS terms FROM r_{name}))")
        df = "".join(f", count(*) FILTER (tf_{i} > 0) AS df_{i}" for i in range(len(query.words)))
        out.append(f"t_{name} AS (SELECT count(*) AS n, avg(dl) AS avdl{df} FROM c_{name})")

        def total(df_margin: float, avdl_margin: float) -> str:
            length = f"({1 - S} + dl * {S} / (avdl * {1 + avdl_margin}))"
            return " + ".join(
                f"CASE WHEN tf_{i} > 0 THEN (1 + ln(1 + ln(greatest(tf_{i}, 1)))) / {length} * greatest(0, ln(n / (df_{i} * {1 - df_margin} + 1))) ELSE 0 END"
                for i in range(len(query.words)))

        some = " OR ".join(f"tf_{i} > 0" for i in range(len(query.words)))
        ceil = f", {total(m.df, m.avdl)} AS row_ceiling" if ceilings else ""
        out.append(f"m_{name} AS (SELECT key{links}, {total(0, 0)} AS row_score{ceil} FROM c_{name}, t_{name} WHERE {some})")
        out.append(f"f_{name} AS (SELECT key{links} FROM c_{name} WHERE NOT ({some}))")
    return out


def tree_ctes(schema: LinkedSchema, query: StandingQuery, matched: list[str], filters=None) -> tuple[list[str], list[networks.Network]]:
    nets = networks.generate(schema, matched, query.max_size)
    union = "\nUNION ALL ".join(networks.to_sql(n) for n in nets)
    return [*relation_ctes(schema, query, False, filters), f"trees AS ({union})"], nets


def topk(schema: LinkedSchema, query: StandingQuery, matched: list[str], filters=None) -> str:
    """Brute force: every network is a join, then sort."""
    ctes, _ = tree_ctes(schema, query, matched, filters)
    return ("WITH " + ",\n".join(ctes) + "\nSELECT network, size, tree_key, round(score, 6) AS score FROM trees"
            f" ORDER BY round(score, 6) DESC, size, network, tree_key LIMIT {query.k}")
