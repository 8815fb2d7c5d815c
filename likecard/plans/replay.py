"""The build and the probes of three-layer tier filters as SQL text, for engines
that check ours: the portable hash is an md5, so even false positives agree."""

from __future__ import annotations

from ..functions.hashing import portable_sql


def _spots(rows: str, sizes: str, kind: str, layer: int) -> str:
    """(tier, key, pos) of rows (tier, key) in the layer's filter of their tier."""
    salt = f"{kind}|' || tier || '|{layer}|"
    pairs = f"select tier, key, bits, hashes, {portable_sql(salt, 'key')} as a, ({portable_sql(salt, 'key', 16)} | 1) % bits as b from {rows} join {sizes} using (tier)"
    return f"select tier, key, (a + j * b) % bits as pos from (select *, unnest(range(0, hashes)) as j from ({pairs}))"


def _sizes(rows: str, fpr: float) -> str:
    bits = f"greatest(64, ceil(-ln({fpr}) / (ln(2) * ln(2)) * n))::bigint"
    return f"select tier, n, {bits} as bits, greatest(1, round({bits} / n * ln(2)))::bigint as hashes from (select tier, count(*) as n from {rows} group by tier)"


def _held(rows: str, sizes: str, words: str, kind: str, layer: int) -> str:
    """The rows whose every position is set."""
    return f"select tier, key from ({_spots(rows, sizes, kind, layer)}) left join (select tier, pos, true as hit from {words}) using (tier, pos) group by tier, key having bool_and(hit is not null)"


def build(tiered: str, kind: str, frontier: bool, fpr: float = 0.05, name: str = "") -> str:
    """CTEs whose names begin with `name`: k (key, tier; without covered keys
    under frontier), own and z1, b1, n1 (others that layer 1 holds), z2, b2, p2
    (members that layer 2 holds: the listed keys)."""
    x = name
    kept = f"select key, tier from {x}t" if not frontier else f"select a.key, a.tier from {x}t a left join {x}t b on b.key = substr(a.key, 1, length(a.key) - 1) where a.tier > 1 or coalesce(b.tier, 2) > 1"
    parts = [
        (f"{x}t", tiered),
        (f"{x}k", kept),
        (f"{x}own", f"select tier, key from {x}k where tier > 1"),
        (f"{x}z1", _sizes(f"{x}own", fpr)),
        (f"{x}b1", f"select distinct tier, pos from ({_spots(f'{x}own', f'{x}z1', kind, 1)})"),
        (f"{x}n0", f"select z.tier, k.key from {x}k k join {x}z1 z on k.tier = 1 or k.tier > z.tier"),
        (f"{x}n1", _held(f"{x}n0", f"{x}z1", f"{x}b1", kind, 1)),
        (f"{x}z2", _sizes(f"{x}n1", fpr)),
        (f"{x}b2", f"select distinct tier, pos from ({_spots(f'{x}n1', f'{x}z2', kind, 2)})"),
        (f"{x}p2", _held(f"{x}own", f"{x}z2", f"{x}b2", kind, 2)),
    ]
    return ", ".join(f"{n} as materialized ({q})" for n, q in parts)


def probe(patterns: str, kind: str, name: str = "") -> str:
    """CTEs over those of build: asked (tier, key) for a table of patterns (key),
    decided (tier, key, layer, accepted) and found (key, tier): the first tier that accepts, else 1."""
    x = name
    parts = [
        (f"{x}asked", f"select z.tier, p.key from (select distinct key from {patterns}) p, {x}z1 z"),
        (f"{x}i1", _held(f"{x}asked", f"{x}z1", f"{x}b1", kind, 1)),
        (f"{x}i2", _held(f"{x}i1", f"{x}z2", f"{x}b2", kind, 2)),
        (f"{x}decided", f"select q.tier, q.key, case when i1.key is null then 1 when z2.tier is null or i2.key is null then 2 else 3 end as layer, case when i1.key is null then false when z2.tier is null or i2.key is null then true else p2.key is not null end as accepted from {x}asked q left join {x}i1 i1 using (tier, key) left join {x}z2 z2 using (tier) left join {x}i2 i2 using (tier, key) left join {x}p2 p2 using (tier, key)"),
        (f"{x}found", f"select key, coalesce(min(tier) filter (where accepted), 1) as tier from {x}decided group by key"),
    ]
    return ", ".join(f"{n} as materialized ({q})" for n, q in parts)


def survivors(kind: str, build_name: str, name: str = "") -> str:
    """(kind, build, tier, layer, n_keys): keys that each layer starts from."""
    x, head = name, f"select '{kind}' as kind, '{build_name}' as build, cast(z1.tier as int) as tier"
    return f"{head}, 1 as layer, z1.n as n_keys from {x}z1 z1 union all {head}, 2, coalesce(z2.n, 0) from {x}z1 z1 left join {x}z2 z2 using (tier) union all {head}, 3, (select count(*) from {x}p2 p where p.tier = z1.tier) from {x}z1 z1 join {x}z2 z2 using (tier)"


def walked(patterns: str, kind: str, name: str = "") -> str:
    """CTEs of the monotone walk: up, the CTEs of probe over all prefixes, and
    walk (key, tier)."""
    x = name
    settled = f"select u.key, bool_or(f.tier = 1 or coalesce(g.tier < f.tier, false)) as one, max(case when length(u.p) = length(u.key) then f.tier end) as own from {x}up u join {x}found f on f.key = u.p left join {x}found g on g.key = substr(u.p, 1, length(u.p) - 1) and length(u.p) > 1 group by u.key"
    return f"{x}up as materialized (select key, substr(key, 1, i) as p from (select key, unnest(range(1, length(key) + 1)) as i from (select distinct key from {patterns}))), {x}pre as materialized (select distinct p as key from {x}up), {probe(f'{x}pre', kind, x)}, {x}walk as materialized (select key, case when one then 1 else own end as tier from ({settled}))"
