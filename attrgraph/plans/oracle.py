"""DuckDB SQL for the graph queries: common table expressions put together by name."""

from __future__ import annotations

G2_PAIRS = """select x.l_partkey as a, y.l_partkey as b
  from (select distinct l_orderkey, l_partkey from lineitem) x join (select distinct l_orderkey, l_partkey from lineitem) y
  on x.l_orderkey = y.l_orderkey and x.l_partkey < y.l_partkey group by 1, 2 having count(*) >= {n}"""
COPURCHASE, COPURCHASE_2 = G2_PAIRS.format(n=1), G2_PAIRS.format(n=2)
CUSTOMER_SUPPLIER = """select distinct o_custkey * 2 as a, l_suppkey * 2 + 1 as b from orders join lineitem on l_orderkey = o_orderkey
  where o_orderdate >= timestamp '2001-01-01'"""
PART_SUPPLIER = "select distinct l_partkey * 2 as a, l_suppkey * 2 + 1 as b from lineitem"
_LINES = """select distinct doc_id, md5(trim(line)) as k from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where length(trim(line)) > 20"""
OVERLAP = f"""select x.doc_id as a, y.doc_id as b from ({_LINES}) x join ({_LINES}) y on x.k = y.k and x.doc_id < y.doc_id
  where x.k in (select k from ({_LINES}) group by k having count(*) between 2 and 50) group by 1, 2"""
OVERLAP_ALL = f"select x.doc_id as a, y.doc_id as b from ({_LINES}) x join ({_LINES}) y on x.k = y.k and x.doc_id < y.doc_id group by 1, 2"
COACTIVITY = """select x.user_id as a, y.user_id as b from (select distinct date_trunc('minute', ts) as t, user_id from events) x
  join (select distinct date_trunc('minute', ts) as t, user_id from events) y on x.t = y.t and x.user_id < y.user_id group by 1, 2"""
KNN = """select q, other, dot, rank from (select x.vec_id as q, y.vec_id as other, list_inner_product(x.embedding::double[], y.embedding::double[]) as dot,
  row_number() over (partition by x.vec_id order by list_inner_product(x.embedding::double[], y.embedding::double[]) desc, y.vec_id) as rank
  from embeddings x join embeddings y on x.vec_id <> y.vec_id) where rank <= 10"""
TURNS = """select a, b from (select conv_id * 1000 + turn as a, lead(conv_id * 1000 + turn) over (partition by conv_id order by turn) as b
  from (select distinct conv_id, turn from conversations)) where b is not null"""
NATIONS = """select cast(n_nationkey as bigint) - 100 as a, cast(n_regionkey as bigint) - 1000 as b from nation
  union all select cast(c_nationkey as bigint) - 100, c_custkey from customer"""

TREE = """select cast(n_nationkey as bigint) - 100 as a, cast(n_regionkey as bigint) - 1000 as b from nation
  union all select cast(s_nationkey as bigint) - 100, s_suppkey from supplier"""
_TREE_NODES = """select s_suppkey as node_id, n_nationkey as nation, n_regionkey as region, cast(cast(floor((s_acctbal + 1000) / 1100) as bigint) as varchar) as balance from supplier join nation on n_nationkey = s_nationkey
  union all select cast(n_nationkey as bigint) - 100, n_nationkey, n_regionkey, null from nation
  union all select distinct cast(n_regionkey as bigint) - 1000, null, n_regionkey, null from nation"""
TREE_ATTRS = f"""select distinct node_id, attr, 1.0::double as value from (select node_id, unnest(['nation:' || cast(nation as varchar), 'region:' || cast(region as varchar), 'balance:' || balance]) as attr from ({_TREE_NODES})) where attr is not null"""

PART_ATTRS = """select distinct p_partkey as node_id, attr, 1.0::double as value from (select p_partkey, unnest([
  'size:' || cast((p_size - 1) // 5 as varchar), 'first:' || string_split(p_name, ' ')[1], 'last:' || string_split(p_name, ' ')[-1], 'brand:' || p_brand]) as attr from part)"""
CUSTOMER_ATTRS = """select distinct c_custkey as node_id, attr, 1.0::double as value from (select c_custkey, unnest([
  'nation:' || cast(c_nationkey as varchar), 'region:' || cast(n_regionkey as varchar), 'balance:' || cast(cast(floor((c_acctbal + 1000) / 1100) as bigint) as varchar)]) as attr
  from customer left join nation on n_nationkey = c_nationkey)"""
DOCUMENT_ATTRS = """select doc_id as node_id, cast(cast('0x' || substr(md5(t), 1, 6) as bigint) % 2048 as varchar) as attr, cast(count(*) as double) as value
  from (select doc_id, unnest(string_split(lower(text), ' ')) as t from documents) where t <> '' group by 1, 2"""


def graph(pairs: str) -> str:
    """raw, deg(node_id, deg), edges."""
    return f"""raw as materialized (select distinct least(a, b) as a, greatest(a, b) as b from ({pairs}) where a <> b),
both_ways as (select a as src, b as dst from raw union all select b, a from raw),
deg as materialized (select src as node_id, cast(count(*) as double) as deg from both_ways group by 1),
edges as materialized (select e.src, e.dst, 1.0::double as w, d.deg as src_deg, f.deg as dst_deg from both_ways e join deg d on d.node_id = e.src join deg f on f.node_id = e.dst)"""


def seeds(n: int, nodes: str = "deg") -> str:
    return f"seeds as materialized (select node_id as seed_id from {nodes} order by md5(cast(node_id as varchar)) limit {n})"


def unit_rows(attrs: str, name: str = "attrs") -> str:
    return f"""{name}_raw as materialized ({attrs}),
{name} as materialized (select r.node_id, attr, value / norm as value from {name}_raw r join (select node_id, sqrt(sum(value * value)) as norm from {name}_raw group by 1) n on n.node_id = r.node_id where norm > 0)"""


def push(start: str, out: str, eps: str = "0.001", alpha: float = 0.8, sigma: float = 1.0, budget: str | None = None, relative: bool = False, rounds: int = 32, edges: str = "edges") -> str:
    """Rounds of diffusion from (seed_id, node_id, mass); the last is named ``out`` (seed_id, node_id, deg, residual, reserve, ...)."""
    level = f"{eps} * mass" if relative else eps
    base = f"""{out}0 as materialized (select s.seed_id, s.node_id, d.deg, s.residual, 0.0::double as reserve, {level} as eps, {budget or f'mass / ({1 - alpha} * ({level}))'} as budget, 0.0::double as spent
  from (select seed_id, node_id, sum(mass) as residual, sum(sum(mass)) over (partition by seed_id) as mass from ({start}) group by 1, 2) s
  join (select src as node_id, max(src_deg) as deg from {edges} group by 1) d on d.node_id = s.node_id)"""
    parts = [base]
    for i in range(rounds):
        after = out if i == rounds - 1 else f"{out}{i + 1}"
        parts.append(f"""{out}_t{i} as materialized (select *, n_hot > 0 and n_hot / n_warm > {sigma} and spent + vol < budget as sweep from (
  select *, sum(hot) over (partition by seed_id) as n_hot, sum(warm) over (partition by seed_id) as n_warm, sum(warm * deg) over (partition by seed_id) as vol
  from (select *, case when residual > 0 and residual >= eps * deg then 1.0::double else 0 end as hot, case when residual > 0 then 1.0::double else 0 end as warm from {out}{i}))),
{out}_a{i} as materialized (select *, hot = 1 or (sweep and warm = 1) as active, spent + case when sweep then vol else 0 end as paid from {out}_t{i}),
{after} as materialized (select seed_id, node_id, max(deg) as deg, sum(residual) as residual, sum(reserve) as reserve, max(eps) as eps, max(budget) as budget, max(spent) as spent from (
  select seed_id, node_id, deg, case when active then 0 else residual end as residual, reserve + case when active then {1 - alpha} * residual else 0 end as reserve, eps, budget, paid as spent from {out}_a{i}
  union all select a.seed_id, e.dst, e.dst_deg, {alpha} * a.residual * e.w / e.src_deg, 0, a.eps, a.budget, a.paid from {out}_a{i} a join {edges} e on e.src = a.node_id where a.active) group by 1, 2)""")
    return ",\n".join(parts)


def walks(start: str, out: str, alpha: float = 0.8, steps: int = 20, share: str = "w / src_deg", edges: str = "edges") -> str:
    """(seed_id, node_id, score): exact diffusion with ``steps`` levels."""
    parts = [f"{out}_l0 as materialized (select seed_id, node_id, sum(mass) as m from ({start}) group by 1, 2)"]
    for i in range(1, steps + 1):
        parts.append(f"{out}_l{i} as materialized (select l.seed_id, e.dst as node_id, {alpha} * sum(l.m * ({share})) as m from {out}_l{i - 1} l join {edges} e on e.src = l.node_id group by 1, 2)")
    union = " union all ".join(f"select * from {out}_l{i}" for i in range(steps + 1))
    parts.append(f"{out} as materialized (select seed_id, node_id, {1 - alpha} * sum(m) as score from ({union}) group by 1, 2)")
    return ",\n".join(parts)


UNIT_START = "select seed_id, seed_id as node_id, 1.0::double as mass from seeds"


def factor_rows(attrs: str = "attrs") -> str:
    """z(node_id, attr, value): untruncated factor rows of unit rows, tall."""
    return f"""col_sum as materialized (select attr, sum(value) as s from {attrs} group by 1),
row_sum as materialized (select node_id, sum(value * s) as total from {attrs} a join col_sum c on c.attr = a.attr group by 1),
z as materialized (select a.node_id, attr, value / sqrt(total) as value from {attrs} a join row_sum r on r.node_id = a.node_id)"""


def pipeline(eps: str = "0.001", sigma: float = 0.1, rounds: int = 32, identity: bool = False, alpha: float = 0.8) -> str:
    """From seeds, edges and z: pi, psi, phi, rho, and aalc(seed_id, node_id, score)."""
    first = push(UNIT_START, "pi", eps, alpha, sigma, rounds=rounds)
    if identity:
        lifted = "phi as materialized (select seed_id, node_id, reserve * deg as mass from pi where reserve > 0)"
    else:
        lifted = """psi as materialized (select seed_id, attr, sum(reserve * value) as value from pi join z on z.node_id = pi.node_id where reserve > 0 group by 1, 2),
phi as materialized (select p.seed_id, p.node_id, greatest(sum(psi.value * z.value), 0) * max(p.deg) as mass from pi p join z on z.node_id = p.node_id join psi on psi.seed_id = p.seed_id and psi.attr = z.attr where p.reserve > 0 group by 1, 2 having sum(psi.value * z.value) > 0)"""
    second = push("select seed_id, node_id, mass from phi", "rho", eps, alpha, sigma, relative=True, rounds=rounds)
    return f"{first},\n{lifted},\n{second},\naalc as materialized (select seed_id, node_id, reserve / deg as score from rho where reserve > 0)"


def query(parts: list[str], select: str) -> str:
    return "with recursive " + ",\n".join(parts) + "\n" + select
