"""SQL that recomputes the sketches by brute force, for DuckDB."""

from __future__ import annotations

from .workloads import WORKLOADS

BITS, DOMAIN = 60, 2**60
MASK = DOMAIN - 1


def digest(seed: str, col: str) -> str:
    """The md5-60 hash of a column; ``seed`` is an SQL text expression."""
    return f"cast('0x' || substr(md5({seed} || coalesce(cast({col} as varchar), '\\N')), 1, 15) as bigint)"


def sides(name: str) -> str:
    """CTEs l(lk, jk) and r(jk, rk)."""
    w = WORKLOADS[name]
    return f"l as ({w.left}), r as ({w.right})"


def stats() -> str:
    return (
        "gs as (select a.jk, a.n as ln, b.n as rn from (select jk, count(*) as n from l where jk is not null group by jk) a "
        "join (select jk, count(*) as n from r where jk is not null group by jk) b on a.jk = b.jk), "
        "st as (select coalesce(max(ln * rn), 0) as maxprod, cast(coalesce(sum(ln * rn), 0) as bigint) as joined from gs)"
    )


def p_of(k: int, policy: str, p: float | None = None) -> str:
    return {
        "doubled": f"least(1.0::double, 2.0::double / {k}, 2.0::double * {k} / maxprod)",
        "printed": f"least(1.0::double / {k}, 1.0::double * {k} / maxprod)",
        "inverse_k": f"least(1.0::double, 2.0::double / {k})",
        "one": "1.0::double",
        "fixed": f"{p}::double",
    }[policy]


def found(name: str, k: int = 256, policy: str = "doubled", p: float | None = None, run: int = 1) -> str:
    """CTEs up to h(x_h, y_h, pair_h): distinct hits; th holds p and t."""
    return (
        f"{sides(name)}, {stats()}, "
        f"th as (select {p_of(k, policy, p)} as p, least({DOMAIN}, cast(ceil({p_of(k, policy, p)} * {float(DOMAIN)!r}::double) as bigint)) as t from st), "
        f"lh as (select jk, {digest(f"'L{run}:'", 'lk')} as x_h from l), rh as (select jk, {digest(f"'R{run}:'", 'rk')} as y_h from r), "
        f"h as (select distinct x_h, y_h, (x_h - y_h) & {MASK} as pair_h from lh join rh using (jk), th where ((x_h - y_h) & {MASK}) < th.t)"
    )


def kept(k: int) -> str:
    return f"ks as (select * from h order by pair_h, x_h, y_h limit {k})"


def estimate(name: str, k: int = 256, policy: str = "doubled", p: float | None = None, short: str | None = None, top: int | None = None, run: int = 1) -> str:
    """threshold, kept, kth_hash, z_hat (rounded) and status of one run."""
    short = short or f"{float(k * k)}"
    return (
        f"with {found(name, k, policy, p, run)}, {kept(k)}, e as (select count(*) as kept, max(pair_h) as kth from ks) "
        f"select th.t as threshold, e.kept, case when e.kept >= {k} then kth end as kth_hash, "
        f"cast(round(case when e.kept = 0 then 0.0 when e.kept >= {k} then {float((top or k) * DOMAIN)!r}::double / greatest(kth, 1) "
        f"when th.p >= 1 then e.kept else {short} end) as bigint) as z_hat, "
        f"case when e.kept = 0 then 'empty' when e.kept >= {k} then 'estimate' when th.p >= 1 then 'exact' else "
        f"'{'upper_bound' if short == f'{float(k * k)}' else 'scaled_count'}' end as status from e, th"
    )


def profile(name: str) -> str:
    return (
        f"with {sides(name)}, {stats()} select (select count(*) from l) as n1, (select count(*) from r) as n2, "
        "(select count(distinct lk) from l) as n_a, (select count(distinct rk) from r) as n_c, joined, maxprod from st"
    )


def exact(name: str) -> str:
    return f"with {sides(name)} select count(*) as z from (select distinct lk, rk from l join r using (jk))"
