"""DuckDB SQL for the engine's relations: graphs, measures, and iterations written out one after the other."""

from __future__ import annotations

from .functions.coin import FULL, coin_sql
from .functions.kernel import Kernel
from .plans.partition import level_plan

_WORDS = "unnest(list_distinct(string_split_regex(lower(text), '[^a-z0-9]+')))"
_BOUGHT = "lineitem JOIN orders ON l_orderkey = o_orderkey"
_LINKS = "SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages"

#: Ends of the edges of each graph; texts stand for their ids, since only counts are compared there.
RAW = {
    "order_part": "SELECT l_orderkey AS qid, l_partkey AS vid FROM lineitem",
    "cust_part": f"SELECT o_custkey AS qid, l_partkey AS vid FROM {_BOUGHT}",
    "part_cust": f"SELECT l_partkey AS qid, o_custkey AS vid FROM {_BOUGHT}",
    "supp_part": "SELECT l_suppkey AS qid, l_partkey AS vid FROM lineitem",
    "hour_user": "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) // 3600 AS qid, user_id AS vid FROM events",
    "brand_cart": f"SELECT o_custkey * 100 + CAST(regexp_extract(p_brand, '([0-9]+)', 1) AS BIGINT) AS qid, l_partkey AS vid FROM {_BOUGHT} JOIN part ON p_partkey = l_partkey",
    "token_doc": f"SELECT w AS qid, doc_id AS vid FROM (SELECT doc_id, {_WORDS} AS w FROM documents) WHERE w <> ''",
    "doc_token": f"SELECT doc_id AS qid, w AS vid FROM (SELECT doc_id, {_WORDS} AS w FROM documents) WHERE w <> ''",
    "conv_token": f"SELECT conv_id AS qid, w AS vid FROM (SELECT conv_id, {_WORDS} AS w FROM conversations) WHERE w <> ''",
    "page_link": f"SELECT page_id AS qid, href AS vid FROM ({_LINKS})",
    "link_page": f"SELECT href AS qid, page_id AS vid FROM ({_LINKS})",
    "vec_knn": """SELECT qid, vid FROM (
      SELECT a.vec_id AS qid, b.vec_id AS vid, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(
        list_sum(list_transform(range(1, len(a.x) + 1), lambda i: a.x[i] * b.x[i])) / (a.n * b.n), 6) DESC, b.vec_id) AS r
      FROM v a JOIN v b ON a.vec_id <> b.vec_id) WHERE r <= 10""",
}
_VECTORS = "v AS (SELECT vec_id, x, sqrt(list_sum(list_transform(x, lambda y: y * y))) AS n FROM (SELECT vec_id, list_transform(embedding, lambda y: CAST(y AS DOUBLE)) AS x FROM embeddings)), "


def edge(key: str) -> str:
    """CTEs down to edge(qid, vid) without queries of one member."""
    return (
        (_VECTORS if key == "vec_knn" else "")
        + f"raw AS (SELECT DISTINCT qid, vid FROM ({RAW[key]}) WHERE qid IS NOT NULL AND vid IS NOT NULL), "
        + "edge AS MATERIALIZED (SELECT qid, vid FROM raw WHERE qid IN (SELECT qid FROM raw GROUP BY qid HAVING count(*) > 1))"
    )


def assign(k: int, seed: int = 42, name: str = "assign") -> str:
    return f"{name} AS MATERIALIZED (SELECT vid, CAST({coin_sql('vid', str(seed))} % {k} AS INTEGER) AS bucket FROM (SELECT DISTINCT vid FROM edge))"


SHARE = "share AS MATERIALIZED (SELECT qid, bucket, count(*) AS cnt FROM edge JOIN assign USING (vid) GROUP BY qid, bucket)"
FAN = "fan AS (SELECT qid, count(*) AS fanout, sum(cnt) AS d FROM share GROUP BY qid)"


def over(key: str, k: int, body: str, *more: str, seed: int = 42) -> str:
    """body over edge, assign, share and fan of a graph placed at random."""
    return "WITH " + ", ".join([edge(key), assign(k, seed), SHARE, FAN, *more]) + " " + body


def _by_size(t: int | dict[int, int], f) -> str:
    """f(t), or a case over buckets whose numbers of final buckets differ."""
    if isinstance(t, int):
        return f(t)
    sizes = sorted(set(t.values()))
    if len(sizes) == 1:
        return f(sizes[0])
    return "CASE " + " ".join(f"WHEN h.bucket IN ({', '.join(str(b) for b, x in t.items() if x == size)}) THEN {f(size)}" for size in sizes) + " END"


def gains(kernel: Kernel, i: str, t: int | dict[int, int] = 1, children: list[tuple[int, int]] | None = None) -> str:
    """CTEs share_i, part_i and gain_i over state s_i(vid, parent, bucket). children: (parent, bucket) of all candidates, if unused ones count too."""
    idle = kernel.idle
    leave, arrive = _by_size(t, lambda x: kernel.leave_sql("h.cnt", x)), _by_size(t, lambda x: kernel.arrive_sql("h.cnt", x))
    if children:
        values = ", ".join(map(str, children))
        gain = f"SELECT o.vid, o.parent, o.src, c.b AS dst, o.part + coalesce(p.part, 0) AS gain_fx FROM part_{i} o JOIN (VALUES {values}) c(parent, b) ON c.parent = o.parent AND c.b <> o.src LEFT JOIN part_{i} p ON p.vid = o.vid AND p.b = c.b WHERE o.b = o.src"
    else:
        gain = f"SELECT p.vid, p.parent, p.src, p.b AS dst, p.part + o.part AS gain_fx FROM part_{i} p JOIN part_{i} o ON o.vid = p.vid AND o.b = o.src WHERE p.b <> p.src"
    return (
        f"share_{i} AS MATERIALIZED (SELECT qid, parent, bucket, count(*) AS cnt FROM edge JOIN s_{i} USING (vid) GROUP BY qid, parent, bucket), "
        f"part_{i} AS MATERIALIZED (SELECT e.vid, s.parent, s.bucket AS src, h.bucket AS b, CAST(sum(CASE WHEN h.bucket = s.bucket THEN {leave} - {idle} ELSE {idle} - ({arrive}) END) AS BIGINT) AS part "
        f"FROM edge e JOIN s_{i} s USING (vid) JOIN share_{i} h ON h.qid = e.qid AND h.parent = s.parent GROUP BY e.vid, s.parent, s.bucket, h.bucket), "
        f"gain_{i} AS MATERIALIZED ({gain})"
    )


def proposals(i: str, penalty: int = 0, nonpositive: bool = False) -> str:
    source = f"gain_{i}"
    extra = ""
    if penalty:
        extra = f"pen_{i} AS (SELECT g.vid, g.parent, g.src, g.dst, g.gain_fx + CASE WHEN g.src = h.bucket THEN -{penalty} WHEN g.dst = h.bucket THEN {penalty} ELSE 0 END AS gain_fx FROM gain_{i} g LEFT JOIN home h USING (vid)), "
        source = f"pen_{i}"
    return extra + (
        f"prop_{i} AS MATERIALIZED (SELECT vid, parent, src, dst, gain_fx, CASE WHEN gain_fx > 0 THEN length(bin(gain_fx)) WHEN gain_fx < 0 THEN -length(bin(-gain_fx)) ELSE 0 END AS gbin FROM "
        f"(SELECT *, row_number() OVER (PARTITION BY vid ORDER BY gain_fx DESC, dst) AS r FROM {source}) WHERE r = 1{'' if nonpositive else ' AND gain_fx > 0'})"
    )


def plain(i: str, weight: str | None = None) -> str:
    crowd = f"SELECT src, dst, CAST(sum(w) AS BIGINT) AS c FROM prop_{i} JOIN ({weight}) USING (vid) WHERE w > 0 GROUP BY src, dst" if weight else f"SELECT src, dst, count(*) AS c FROM prop_{i} GROUP BY src, dst"
    return (
        f"ex_{i} AS ({crowd}), "
        f"th_{i} AS MATERIALIZED (SELECT x.src, x.dst, x.c AS candidates, least(x.c, coalesce(y.c, 0)) AS admitted, CAST((least(x.c, coalesce(y.c, 0))::HUGEINT * {FULL}) // x.c AS BIGINT) AS threshold FROM ex_{i} x LEFT JOIN ex_{i} y ON y.src = x.dst AND y.dst = x.src)"
    )


def histogram(i: str, nonpositive: bool = False) -> str:
    """Bins of opposite directions paired from the top; with nonpositive gains only pairs whose mean gains add up to more than zero."""
    both = " AND a.g * b.c + b.g * a.c > 0" if nonpositive else ""
    return (
        f"ex_{i} AS (SELECT src, dst, gbin, count(*) AS c, sum(gain_fx)::HUGEINT AS g FROM prop_{i} GROUP BY src, dst, gbin), "
        f"iv_{i} AS (SELECT *, sum(c) OVER (PARTITION BY src, dst ORDER BY gbin DESC) AS hi FROM ex_{i}), "
        f"ov_{i} AS (SELECT a.src, a.dst, a.gbin, sum(least(a.hi, b.hi) - greatest(a.hi - a.c, b.hi - b.c)) AS adm FROM iv_{i} a JOIN iv_{i} b ON b.src = a.dst AND b.dst = a.src AND a.hi - a.c < b.hi AND b.hi - b.c < a.hi{both} GROUP BY a.src, a.dst, a.gbin), "
        f"th_{i} AS MATERIALIZED (SELECT e.src, e.dst, e.gbin, e.c AS candidates, e.g AS gain_sum, coalesce(o.adm, 0) AS admitted, CAST((coalesce(o.adm, 0)::HUGEINT * {FULL}) // e.c AS BIGINT) AS threshold FROM ex_{i} e LEFT JOIN ov_{i} o USING (src, dst, gbin))"
    )


def slack(i: str, caps: list[tuple[int, int, int, int]], k: int, eps: float, eps_level: float) -> str:
    """th_i with unpaired candidates that fill the room of their targets; caps: (parent, bucket, final buckets of the bucket, of the parent)."""
    n = "(SELECT count(*) FROM p_1)"
    last = f"greatest(floor(CAST({1 + eps!r} AS DOUBLE) * {n} / {k} + 1e-9), ceil({n} / {k}))"
    cap = f"least(x * {last}, greatest(floor(CAST({1 + eps_level!r} AS DOUBLE) * {n} * x / {k} + 1e-9), ceil(coalesce(z.held, 0) * x / t)))"
    return (
        f"cap_{i} AS (SELECT c.b AS bucket, CAST({cap} AS BIGINT) AS cap FROM (VALUES {', '.join(map(str, caps))}) c(parent, b, x, t) LEFT JOIN (SELECT parent, count(*) AS held FROM s_{i} GROUP BY parent) z ON z.parent = c.parent), "
        f"sp_{i} AS (SELECT h.*, greatest(c.cap - coalesce(z.size, 0), 0) AS room, CASE WHEN gbin > 0 THEN candidates - admitted ELSE 0 END AS spare FROM th0_{i} h JOIN cap_{i} c ON c.bucket = h.dst LEFT JOIN (SELECT bucket, count(*) AS size FROM s_{i} GROUP BY bucket) z ON z.bucket = h.dst), "
        f"sq_{i} AS (SELECT *, coalesce(sum(spare) OVER (PARTITION BY dst ORDER BY gbin DESC, src ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM sp_{i}), "
        f"th_{i} AS MATERIALIZED (SELECT src, dst, gbin, candidates, CAST(((admitted + greatest(least(spare, room - before), 0))::HUGEINT * {FULL}) // candidates AS BIGINT) AS threshold FROM sq_{i})"
    )


def moved(i: str, j: str, seed: int, level: int, turn: int, kind: str, damp: float = 1.0) -> str:
    """State s_j after the moves of s_i's proposals."""
    if kind == "ranked":
        rank = f"rk_{i} AS (SELECT *, row_number() OVER (PARTITION BY src, dst ORDER BY gain_fx DESC, vid) AS rn FROM prop_{i}), "
        ok = f"SELECT a.vid, a.dst FROM rk_{i} a JOIN rk_{i} b ON b.src = a.dst AND b.dst = a.src AND b.rn = a.rn"
        return rank + f"s_{j} AS MATERIALIZED (SELECT s.vid, s.parent, coalesce(m.dst, s.bucket) AS bucket FROM s_{i} s LEFT JOIN ({ok}) m USING (vid))"
    keys = "src, dst" + (", gbin" if kind == "histogram" else "")
    limit = "threshold" if damp == 1 else f"CAST(floor(threshold * {damp}) AS BIGINT)"
    ok = f"SELECT p.vid, p.dst FROM prop_{i} p JOIN th_{i} USING ({keys}) WHERE {coin_sql('p.vid', str(seed), str(level), str(turn))} < {limit}"
    return f"s_{j} AS MATERIALIZED (SELECT s.vid, s.parent, coalesce(m.dst, s.bucket) AS bucket FROM s_{i} s LEFT JOIN ({ok}) m USING (vid))"


def unrolled(key: str, k: int, turns: int, objective: str = "pfanout", p: float = 0.5, arity: int | None = None, lookahead: bool = False, kind: str = "plain", seed: int = 42, damp: float = 1.0, penalty: int = 0, start: str | None = None, nonpositive: bool = False, room: float | None = None, weight: str | None = None, body: str = "SELECT vid, CAST(bucket AS INTEGER) AS bucket FROM assign") -> str:
    """body over edge and assign(vid, bucket), the state after so many iterations per level. room: the allowance that one-way moves may use."""
    kernel = Kernel(objective, p)
    parts, state = [edge(key), "p_1 AS (SELECT DISTINCT vid, 0 AS parent FROM edge)"], None
    if penalty or start:
        parts.append(assign(k, seed, "home"))
    plan = level_plan(k, arity)
    for level, split in enumerate(plan, start=1):
        cases = []
        for (first, t), children in split:
            at = 0
            for c, size in children:
                cases.append(f"WHEN parent = {first} AND (c * {t}) >> 32 < {at + size} THEN {c}")
                at += size
        name = f"{level}_0"
        if start:
            parts.append(f"s_{name} AS MATERIALIZED (SELECT vid, 0 AS parent, bucket FROM home)")
        else:
            parts.append(f"s_{name} AS MATERIALIZED (SELECT vid, parent, CAST(CASE {' '.join(cases)} END AS INTEGER) AS bucket FROM (SELECT *, {coin_sql('vid', str(seed), str(level))} AS c FROM p_{level}))")
        t = {c: size for _, children in split for c, size in children} if lookahead else 1
        every = [(first, c) for (first, _), children in split for c, _ in children] if nonpositive else None
        for turn in range(1, turns + 1):
            nxt = f"{level}_{turn}"
            parts += [gains(kernel, name, t, every), proposals(name, penalty, nonpositive)]
            if kind == "plain":
                parts.append(plain(name, weight))
            elif kind == "histogram" and room is None:
                parts.append(histogram(name, nonpositive))
            elif kind == "histogram":
                caps = [(first, c, size, total) for (first, total), children in split for c, size in children]
                parts += [histogram(name, nonpositive).replace(f"th_{name} AS", f"th0_{name} AS"), slack(name, caps, k, room, room * level / len(plan))]
            parts.append(moved(name, nxt, seed, level, turn, kind, damp))
            name = nxt
        parts.append(f"p_{level + 1} AS MATERIALIZED (SELECT vid, bucket AS parent FROM s_{name})")
        state = name
    parts.append(f"assign AS MATERIALIZED (SELECT vid, CAST(bucket AS INTEGER) AS bucket FROM s_{state})")
    return "WITH " + ", ".join(parts) + " " + body
