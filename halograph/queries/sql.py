"""Common table expressions for the checking SQL. They recompute everything from the base tables and in their own way."""

from __future__ import annotations

import re

P, B, FANOUTS, SEED, CS, NC, LS, D = 4, 64, (3, 3, 3), 1, 500, 128, 2, 1
TRAIN = int(0.3 * 2**32)
WIDTH = 4
TOP = len(FANOUTS)

VIEWS: dict[str, str] = {}


def view(name: str, text: str) -> None:
    VIEWS[name] = text


def sql(select: str) -> str:
    """The statement with the views that it needs, in order."""
    order: list[str] = []

    def visit(text: str) -> None:
        for word in dict.fromkeys(re.findall(r"\b\w+\b", text)):
            if word in VIEWS and word not in order:
                visit(VIEWS[word])
                if word not in order:
                    order.append(word)

    visit(select)
    if not order:
        return select
    recursive = ", ".join(f"{n} AS MATERIALIZED ({VIEWS[n]})" for n in order)
    return f"WITH {recursive} {select}"


def md5(*parts) -> str:
    return f"md5(concat_ws('|', {', '.join(map(str, parts))}))"


def draw(*parts) -> str:
    return f"CAST(('0x' || substr({md5(*parts)}, 1, 8)) AS BIGINT)"


def race(weight: str, *parts) -> str:
    return f"-ln(({draw(*parts)} + 0.5::DOUBLE) / 4294967296::DOUBLE) / {weight}"


def feature(vid: str, dim: str) -> str:
    return f"(({draw(1, chr(39) + 'x' + chr(39), vid, dim)} % 1024) - 512) / 1024.0::DOUBLE"


view("v_pairs", "SELECT o_custkey AS a, l_partkey + (SELECT count(*) FROM customer) AS b, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2")
view("v_edges", "SELECT src, dst, CAST(sum(w) AS BIGINT) AS w FROM (SELECT a AS src, b AS dst, w FROM v_pairs UNION ALL SELECT b, a, w FROM v_pairs) WHERE src <> dst GROUP BY src, dst")
view("v_verts", "SELECT c_custkey AS vid FROM customer UNION ALL SELECT p_partkey + (SELECT count(*) FROM customer) FROM part")
view("v_parts", f"SELECT vid, CAST(vid % {P} AS INTEGER) AS part FROM v_verts")
view("v_deg", "SELECT dst AS vid, count(*) AS deg FROM v_edges GROUP BY dst")
view("v_placed", f"SELECT e.*, CAST(src % {P} AS INTEGER) AS p_src, CAST(dst % {P} AS INTEGER) AS p_dst, g.deg AS deg_src FROM v_edges e JOIN v_deg g ON g.vid = e.src")
view("v_train", f"SELECT vid FROM v_verts WHERE {draw(1, chr(39) + 'split' + chr(39), 'vid')} < {TRAIN}")


def _seeds(epoch: int) -> str:
    order = md5(1, "'seed'", epoch, "vid")
    return f"SELECT CAST({epoch} AS INTEGER) AS epoch, CAST(vid % {P} AS INTEGER) AS rank, CAST(floor((row_number() OVER (PARTITION BY vid % {P} ORDER BY {order}, vid) - 1) / {B}) AS INTEGER) AS it, vid FROM v_train"


def _chain(tag: str, seeds: str, local: bool) -> None:
    """Views {tag}_b0.. and {tag}_f0..: blocks and frontiers by layer."""
    view(f"{tag}_f{TOP}", f"SELECT epoch, rank, it, vid, rank AS part FROM {seeds}")
    keep = "f.part = f.rank" if local else "TRUE"
    for k, fanout in enumerate(FANOUTS):
        layer = TOP - 1 - k
        order = md5(1, "'hop'", "f.epoch", "f.it", layer, "p.src", "p.dst")
        view(
            f"{tag}_b{layer}",
            f"SELECT epoch, rank, it, CAST({layer} AS INTEGER) AS layer, src, dst, w, p_src FROM (SELECT f.epoch, f.rank, f.it, p.src, p.dst, p.w, p.p_src,"
            f" row_number() OVER (PARTITION BY f.epoch, f.rank, f.it, p.dst ORDER BY {order}, p.src) AS n FROM {tag}_f{layer + 1} f JOIN v_placed p ON p.dst = f.vid WHERE {keep}) WHERE n <= {fanout}",
        )
        view(f"{tag}_f{layer}", f"SELECT epoch, rank, it, vid, part FROM {tag}_f{layer + 1} f WHERE {keep} UNION SELECT epoch, rank, it, src, p_src FROM {tag}_b{layer}")
    view(f"{tag}_blocks", " UNION ALL ".join(f"SELECT * FROM {tag}_b{k}" for k in range(TOP)))
    view(f"{tag}_frontier", " UNION ALL ".join(f"SELECT *, CAST({k} AS INTEGER) AS layer, CASE WHEN part = rank THEN 'solid' ELSE 'halo' END AS kind FROM {tag}_f{k}" for k in range(TOP + 1)))


view("v_seeds", _seeds(0))
view("v_seeds1", _seeds(1))
_chain("lo", "v_seeds", True)
_chain("nx", "v_seeds1", True)
_chain("gl", "v_seeds", False)
view("v_rounds", "SELECT max(it) + 1 AS m FROM v_seeds")
view("v_halo", "SELECT DISTINCT p_dst AS part, src AS vid FROM v_placed WHERE p_src <> p_dst")
view("v_eligible", f"SELECT DISTINCT f.epoch, f.it, f.layer, f.rank AS from_rank, p.p_dst AS to_rank, f.vid FROM lo_frontier f JOIN v_placed p ON p.src = f.vid WHERE f.kind = 'solid' AND f.layer < {TOP} AND p.p_dst <> f.rank")
view("nx_eligible", VIEWS["v_eligible"].replace("lo_", "nx_"))
ABOUT = (1, "'push'", "epoch", "it", "layer", "from_rank", "to_rank", "e.vid")


def capped(source: str, order: str, limit: int = NC, group: str = "epoch, it, layer, from_rank, to_rank") -> str:
    return (
        f"SELECT epoch, it, layer, from_rank, to_rank, vid FROM (SELECT e.*, row_number() OVER (PARTITION BY {group} ORDER BY {order}, e.vid, to_rank) AS n FROM {source} e JOIN v_deg g ON g.vid = e.vid) WHERE n <= {limit}"
    )


view("v_capped", capped("v_eligible", race("g.deg", *ABOUT)))
view("nx_capped", capped("nx_eligible", race("g.deg", *ABOUT)))


def pushed(source: str = "v_capped", d: int = D) -> str:
    return f"SELECT epoch, it AS sent_it, CAST(it + {d} AS INTEGER) AS arrive_it, from_rank, to_rank, layer, vid FROM {source} WHERE it < (SELECT m FROM v_rounds) - {d}"


view("v_push", pushed())
view("nx_push", pushed("nx_capped"))
view("v_demand", "SELECT epoch, rank, it, layer, vid FROM lo_frontier WHERE kind = 'halo'")
view("nx_demand", "SELECT epoch, rank, it, layer, vid FROM nx_frontier WHERE kind = 'halo'")


def asof(push: str = "v_push", demand: str = "v_demand", ls: int = LS, d: int = D) -> str:
    """Every demand with the latest arrival no later than it."""
    return (
        f"SELECT q.epoch, q.rank, q.it, q.layer, q.vid, t.arrive_it AS written, coalesce(t.arrive_it IS NOT NULL AND q.it - t.arrive_it <= {ls} AND q.it >= {d}, FALSE) AS fresh"
        f" FROM {demand} q LEFT JOIN (SELECT q2.rank, q2.layer, q2.vid, q2.it, max(a.arrive_it) AS arrive_it FROM {demand} q2 JOIN {push} a ON a.to_rank = q2.rank AND a.layer = q2.layer AND a.vid = q2.vid AND a.arrive_it <= q2.it GROUP BY ALL) t"
        " ON t.rank = q.rank AND t.layer = q.layer AND t.vid = q.vid AND t.it = q.it"
    )


def held(push: str = "v_push", cs: int = CS, ls: int = LS) -> str:
    """Lines in each cache at each iteration, by a join of the arrivals of the last iterations."""
    return (
        f"SELECT to_rank AS rank, layer, now, vid FROM (SELECT a.to_rank, a.layer, k.now, a.vid, row_number() OVER (PARTITION BY a.to_rank, a.layer, k.now ORDER BY max(a.arrive_it) DESC, a.vid) AS n"
        f" FROM {push} a JOIN (SELECT unnest(range(0, (SELECT m FROM v_rounds))) AS now) k ON a.arrive_it BETWEEN k.now - {ls} AND k.now GROUP BY a.to_rank, a.layer, k.now, a.vid) WHERE n <= {cs}"
    )


def hits(push: str = "v_push", cs: int = CS, ls: int = LS, d: int = D, demand: str = "v_demand") -> str:
    return (
        f"SELECT a.epoch, a.rank, a.it, a.layer, a.vid, a.fresh AND h.vid IS NOT NULL AS hit, CASE WHEN a.fresh AND h.vid IS NOT NULL THEN CAST(a.written AS INTEGER) END AS version_it"
        f" FROM ({asof(push, demand, ls, d)}) a LEFT JOIN ({held(push, cs, ls)}) h ON h.rank = a.rank AND h.layer = a.layer AND h.now = a.it AND h.vid = a.vid"
    )


view("v_hits", hits())
view("v_exec", "SELECT b.* FROM lo_blocks b WHERE NOT EXISTS (SELECT 1 FROM v_hits h WHERE NOT h.hit AND h.epoch = b.epoch AND h.rank = b.rank AND h.it = b.it AND h.layer = b.layer AND h.vid = b.src)")
view("v_x", "SELECT vid, " + ", ".join(f"{feature('vid', k)} AS x{k}" for k in range(WIDTH)) + " FROM v_verts")
