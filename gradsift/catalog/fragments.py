"""SQL that several oracles share, written from the definitions."""

from __future__ import annotations

from gradsift.functions.features import CENTRES, SCALES

#: Weights of the fixed linear rater over the six standardised text statistics.
RATER = (0.3, -1.0, 0.8, -0.6, -0.3, -0.1)


def u(id_expr: str, seed: int) -> str:
    return f"((('0x' || substr(md5('{seed}:' || {id_expr}), 1, 8))::BIGINT + 0.5::DOUBLE) / 4294967296::DOUBLE)"


def share(cls: str) -> str:
    return f"(length(t) - length(regexp_replace(t, '{cls}', '', 'g')))::DOUBLE / greatest(length(t), 1)"


def stats(source: str = "documents", id_col: str = "doc_id") -> str:
    """CTEs b (words) and f: x1..x6, the raw statistics."""
    return f"""
        b AS (SELECT *, coalesce(text, '') AS t, list_filter(string_split_regex(coalesce(text, ''), '[ \\n]'), lambda w: w <> '') AS ws FROM {source}),
        f AS (SELECT *, ln(1 + length(t)::DOUBLE) AS x1, {share('[A-Z]')} AS x2, len(list_distinct(ws))::DOUBLE / greatest(len(ws), 1) AS x3,
                     {share('[#*$%&|<>]')} AS x4, {share('[0-9]')} AS x5, length(t)::DOUBLE / greatest(len(ws), 1) AS x6 FROM b)"""


def z(i: int) -> str:
    return f"((x{i} - {CENTRES[i - 1]}::DOUBLE) / {SCALES[i - 1]}::DOUBLE)"


Z = [z(i) for i in range(1, 7)]
SCORE = " + ".join(f"{zi} * {w}::DOUBLE" for zi, w in zip(Z, RATER, strict=True))
#: f, then s (score) and r (rank, pct) of the documents.
RANKED = f"""{stats()},
        s AS (SELECT *, {SCORE} AS score FROM f),
        r AS (SELECT *, row_number() OVER (ORDER BY score DESC, doc_id) AS rank,
                     (row_number() OVER (ORDER BY score DESC, doc_id) - 1) / count(*) OVER ()::DOUBLE AS pct FROM s)"""


def gaussian(discard: float, mean: float, spread: float) -> str:
    return f"CASE WHEN pct < {discard} THEN 0::DOUBLE ELSE exp(-((pct - {mean}::DOUBLE) * (pct - {mean}::DOUBLE)) / {2 * spread * spread}::DOUBLE) END"


def exact_sample(discard: float, mean: float, spread: float, part: str, seed: int = 42, source: str = "r") -> str:
    """A SELECT of the doc_ids that exponential keys choose."""
    return f"""SELECT doc_id FROM (SELECT doc_id, -ln({u('doc_id', seed)}) / ({gaussian(discard, mean, spread)}) AS e FROM {source} WHERE pct >= {discard})
        ORDER BY e, doc_id LIMIT (SELECT {part} FROM {source})"""


ROWS = f"""
        l AS (SELECT concat_ws('-', l_orderkey, l_partkey, l_suppkey, l_linenumber, strftime(l_shipdate, '%Y%m%d')) AS sample_id,
                     l_quantity::DOUBLE / 50 AS a1, l_discount::DOUBLE * 10 AS a2, l_tax::DOUBLE * 10 AS a3, l_extendedprice::DOUBLE / 100000 AS y FROM lineitem),
        v AS (SELECT *, {u('sample_id', 7)} < 0.1 AS val FROM l),
        t AS (SELECT *, ('0x' || substr(md5('42:' || sample_id), 1, 8))::BIGINT % (SELECT ceil(count(*) / 64.0)::BIGINT FROM v WHERE NOT val) AS batch_id FROM v WHERE NOT val)"""


def lin(theta, prefix: str = "a") -> str:
    return "(" + " + ".join(f"{prefix}{i + 1} * ({x}::DOUBLE)" for i, x in enumerate(theta)) + ")"
