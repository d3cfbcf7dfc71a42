"""SQL pieces over the zoo that oracles share (DuckDB dialect)."""

from __future__ import annotations

from xorvault.sources import zoo

#: Float variants whose tensors keep the base's order.
ORDERED = ("v0", "v1", "v2", "v3", "v4", "v5", "v7", "v8", "v9", "v12", "v12c", "v13")


def listed(variants: tuple[str, ...]) -> str:
    return ", ".join(f"'{v}'" for v in variants)


def elements(variants: tuple[str, ...] = ORDERED, families: str = "label >= 0") -> str:
    return f"el AS (SELECT *, 'm' || family || '_' || variant AS repo_id FROM ({zoo.elements_sql('duckdb', families)}) WHERE variant IN ({listed(variants)}))"


def tensors(variants: tuple[str, ...] = ORDERED) -> str:
    hexed = "string_agg(CASE WHEN dtype = 'F32' THEN printf('%02x%02x%02x%02x', bits & 255, (bits >> 8) & 255, (bits >> 16) & 255, bits >> 24) ELSE printf('%02x%02x', bits & 255, bits >> 8) END, '' ORDER BY idx)"
    return (
        elements(variants)
        + f""", tz AS (SELECT family, variant, repo_id, ordinal, any_value(dtype) AS dtype, count(*) AS n_elems, CAST(sum(CASE WHEN dtype = 'F32' THEN 4 ELSE 2 END) AS BIGINT) AS n_bytes, sha256(unhex({hexed})) AS tensor_hash FROM el GROUP BY ALL),
cnt AS (SELECT family, max(ordinal) + 1 AS n FROM tz GROUP BY 1),
tn AS (SELECT tz.*, CASE WHEN ordinal = 0 THEN 'embed_tokens.weight' WHEN ordinal = n - 1 THEN 'lm_head.weight' ELSE 'layers.' || ((ordinal - 1) // 2) || CASE WHEN ordinal % 2 = 1 THEN '.attn.weight' ELSE '.mlp.weight' END END AS name,
 CAST(n_elems // 64 AS VARCHAR) || 'x64' AS shape FROM tz JOIN cnt USING (family))"""
    )


def pairs(a: str = "v0", others: tuple[str, ...] = ("v2", "v3", "v4")) -> str:
    """pe: aligned elements (a, b, ordinal, idx, x, y) of each family's variants against one variant."""
    return f"pe AS (SELECT p.repo_id AS a, q.repo_id AS b, p.family, q.variant, p.ordinal, p.idx, p.dtype, p.bits AS x, q.bits AS y FROM el p JOIN el q ON p.family = q.family AND p.ordinal = q.ordinal AND p.idx = q.idx AND p.dtype = q.dtype WHERE p.variant = '{a}' AND q.variant IN ({listed(others)}))"


VALUE = "CASE WHEN {b} & 32768 <> 0 THEN -1.0 ELSE 1.0 END * CASE WHEN ({b} >> 7) & 255 = 0 THEN ({b} & 127) / 128.0 * pow(CAST(2 AS DOUBLE), -126) ELSE (1 + ({b} & 127) / CAST(128.0 AS DOUBLE)) * pow(CAST(2 AS DOUBLE), CAST(({b} >> 7) & 255 AS DOUBLE) - 127) END"
