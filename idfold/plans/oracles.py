"""One round of agglomeration as SQL, for checking the distributed engine: common table expressions."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class RoundSql:
    """Parameters as SQL expressions over ``n0`` (ids at the start)."""

    budget: str = "ceil(n0 / 10.0)::BIGINT"
    stride: str = "ceil(n0 / 100.0)::BIGINT"
    cap: str = "ceil(4.0 * n0 / ceil(n0 / 10.0))::BIGINT"
    gates: tuple[str, ...] = ("rarity", "gap", "bulk")
    value_rule: str = "mean"
    bulk_limit: str = "stride"
    strict: bool = False


def round_ctes(src: str, dst: str, p: RoundSql) -> list[str]:
    """CTEs from chain ``src(pos, value, size, accesses)`` to ``dst``; those between are dst_par,
    dst_links, dst_gate<k>, dst_runs and dst_stay."""
    out = [
        f"{dst}_par AS MATERIALIZED (SELECT n, least({p.stride}, n - {p.budget}) AS r, {p.cap} AS cap, norm FROM (SELECT count(*) AS n, sqrt(sum(accesses * accesses)::DOUBLE) AS norm FROM {src}),"
        " (SELECT count(*) AS n0 FROM chain))",
        f"{dst}_links AS MATERIALIZED (SELECT pos, r, cap, (CASE WHEN norm > 0 THEN 1 + accesses / norm ELSE 1.0 END) * (CASE WHEN norm > 0 THEN 1 + na / norm ELSE 1.0 END) AS rarity,"
        f" nv - value AS gap, size + ns AS bulk FROM (SELECT *, lead(value) OVER w AS nv, lead(size) OVER w AS ns, lead(accesses) OVER w AS na FROM {src} WINDOW w AS (ORDER BY pos)), {dst}_par WHERE nv IS NOT NULL AND r > 0)",
    ]
    last, order = f"{dst}_links", "pos"
    fallback = "false"
    for place, gate in enumerate(p.gates):
        width = f"greatest(1, floor({(2.0, 1.5, 1.0)[-len(p.gates) :][place]} * r))"
        here, rank = f"{dst}_gate{place + 1}", f"rank{place + 1}"
        final = place == len(p.gates) - 1
        if gate == "bulk":
            fits = "bulk < cap" if p.strict else "bulk <= cap"
            keep = f"{rank} <= {width}" if final and p.bulk_limit == "stride" else f"(NOT fallback OR {rank} <= {width})"
            out.append(
                f"{here} AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (ORDER BY CASE WHEN fallback THEN bulk ELSE 0 END, {order}) AS {rank} FROM"
                f" (SELECT *, NOT bool_or({fits}) OVER () AS fallback FROM {last}) WHERE ({fits}) OR fallback) WHERE {keep})"
            )
            fallback = "fallback"
        else:
            out.append(f"{here} AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (ORDER BY {gate}, {order}) AS {rank} FROM {last}) WHERE {rank} <= {width})")
        last, order = here, rank
    over = "run_size >= cap" if p.strict else "run_size > cap"
    stays = f"NOT ({over}) OR {fallback} OR in_run % 2 = 1" if "bulk" in p.gates else "true"
    out += [
        f"{dst}_island AS (SELECT *, pos - row_number() OVER (ORDER BY pos) AS run_id FROM {last})",
        f"{dst}_runs AS MATERIALIZED (SELECT i.*, row_number() OVER (PARTITION BY run_id ORDER BY i.pos) AS in_run,"
        f" (sum(b.size) OVER (PARTITION BY run_id) + first_value(a.size) OVER (PARTITION BY run_id ORDER BY i.pos))::BIGINT AS run_size"
        f" FROM {dst}_island i JOIN {src} a ON a.pos = i.pos JOIN {src} b ON b.pos = i.pos + 1)",
        f"{dst}_stay AS MATERIALIZED (SELECT pos FROM {dst}_runs WHERE {stays})",
        f"{dst}_to AS (SELECT c.*, c.pos - sum(CASE WHEN s.pos IS NULL THEN 0 ELSE 1 END) OVER (ORDER BY c.pos) AS np FROM {src} c LEFT JOIN {dst}_stay s ON s.pos + 1 = c.pos)",
    ]
    plain = "(2 * sum(value) + count(*)) // (2 * count(*))"
    weight = {"mean": None, "count_weighted": "accesses", "size_weighted": "size"}[p.value_rule]
    value = plain if weight is None else f"CASE WHEN sum({weight}) > 0 THEN (2 * sum(value * {weight}) + sum({weight})) // (2 * sum({weight})) ELSE {plain} END"
    out.append(
        f"{dst} AS MATERIALIZED (SELECT np::BIGINT AS pos, (CASE WHEN count(*) = 1 THEN max(value) ELSE {value} END)::BIGINT AS value, sum(size)::BIGINT AS size, sum(accesses)::BIGINT AS accesses FROM {dst}_to GROUP BY np)"
    )
    return out
