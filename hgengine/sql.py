"""SQL that states the same results independently, for DuckDB: memberships and unrolled rounds."""

from __future__ import annotations

INC = {
    "basket": "select l_partkey as vid, l_orderkey as hid, count(*)::int as multiplicity from lineitem group by all",
    "dual": "select l_orderkey as vid, l_partkey as hid, count(*)::int as multiplicity from lineitem group by all",
    "buyers": "select o_custkey as vid, l_partkey as hid, count(*)::int as multiplicity from lineitem join orders on o_orderkey = l_orderkey group by all",
    "vendor": "select l_suppkey as vid, l_orderkey as hid, count(*)::int as multiplicity from lineitem group by all",
    "supply": "select l_partkey as vid, l_suppkey as hid, count(*)::int as multiplicity from lineitem group by all",
    "hour": "select user_id as vid, epoch(date_trunc('hour', ts))::bigint as hid, count(*)::int as multiplicity from events group by all",
    "words": "select w as vid, doc_id as hid, count(*)::int as multiplicity from (select doc_id, unnest(string_split(lower(text), ' ')) as w from documents) where w <> '' group by all",
    "nation": "select c_custkey as vid, c_nationkey::bigint as hid, count(*)::int as multiplicity from customer group by all",
}


def inc(name: str) -> str:
    return f"inc as materialized ({INC[name]})"


def pagerank(name: str, rounds: int, alpha: float = 0.15, weight: str | None = None, init: str = "exact", restart: str = "1.0", vertices: str = "select distinct vid from inc") -> list[str]:
    """CTEs e1, v1, ... with (hid, rank) and (vid, rank, share); static tables w, k, tw, vs."""
    alpha = f"{alpha}::double"
    ctes = [
        inc(name),
        f"w as materialized ({weight or 'select distinct hid, 1.0::double as weight from inc'})",
        "k as materialized (select hid, count(*)::double as k from inc group by hid)",
        "tw as materialized (select vid, sum(weight) as total from inc join w using (hid) group by vid)",
        f"vs as materialized (select vid, ({restart})::double as restart from ({vertices}))",
        f"v0 as materialized (select vid, 1.0::double as rank, {'1.0::double' if init == 'message' else 'total'} as share from vs left join tw using (vid))",
    ]
    for r in range(1, rounds + 1):
        ctes.append(f"e{r} as materialized (select hid, any_value(weight) * sum(rank / share) as rank from inc join v{r - 1} using (vid) join w using (hid) group by hid)")
        ctes.append(f"v{r} as materialized (select vs.vid, {alpha} * any_value(restart) + (1 - {alpha}) * coalesce(sum(e.rank / k.k), 0) as rank, any_value(tw.total) as share from vs left join tw using (vid) left join inc using (vid) left join e{r} e using (hid) left join k using (hid) group by vs.vid)")
    return ctes


def labels(name: str, rounds: int, pick: str = "max") -> list[str]:
    least = "greatest" if pick == "max" else "least"
    ctes = [inc(name), "v0 as materialized (select distinct vid, vid as label from inc)"]
    for r in range(1, rounds + 1):
        ctes.append(f"e{r} as materialized (select hid, {pick}(label) as label from inc join v{r - 1} using (vid) group by hid)")
        ctes.append(f"v{r} as materialized (select v.vid, {least}(any_value(v.label), {pick}(e.label)) as label from v{r - 1} v join inc using (vid) join e{r} e using (hid) group by v.vid)")
    return ctes


def paths(name: str, rounds: int, source: str, cost: str = "1.0") -> list[str]:
    """hops as least over rounds; source: SQL of one vid. cost may use hid."""
    ctes = [inc(name), f"v0 as materialized (select distinct vid, case when vid = ({source}) then 0.0::double end as hops from inc)"]
    for r in range(1, rounds + 1):
        ctes.append(f"e{r} as materialized (select hid, min(hops + {cost}) as hops from inc join v{r - 1} using (vid) group by hid)")
        ctes.append(f"v{r} as materialized (select v.vid, least(any_value(v.hops), min(e.hops)) as hops from v{r - 1} v join inc using (vid) join e{r} e using (hid) group by v.vid)")
    return ctes


def query(ctes: list[str], select: str) -> str:
    return "with " + ",\n".join(ctes) + f"\n{select}"


MOD = 2147483647


def modular(x: str, parts: int) -> str:
    return f"((({x}) % {MOD}) * 1597334677 % {MOD} % {parts})::int"


def modular2(x: str, y: str, parts: int) -> str:
    return f"(((({x}) % {MOD} + ({y}) % {MOD} * 7919) % {MOD}) * 1597334677 % {MOD} % {parts})::int"
