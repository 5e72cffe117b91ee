"""Pieces of DuckDB SQL that the catalogue's oracles are put together from."""

from __future__ import annotations

DIM = 64

OBJECTS = """SELECT vec_id AS id, embedding AS vec, label, least(a, b)::DOUBLE AS lo, greatest(a, b)::DOUBLE AS hi
  FROM (SELECT *, (vec_id * 7919 + 104729) % 10007 AS a, (vec_id * 6101 + 15013) % 10009 AS b FROM embeddings)"""
POINTS = "SELECT vec_id AS id, embedding AS vec, label, ((vec_id * 7919 + 104729) % 10007)::DOUBLE AS lo, ((vec_id * 7919 + 104729) % 10007)::DOUBLE AS hi FROM embeddings"
LIVES = """SELECT vec_id AS id, embedding AS vec, label, lo, hi FROM embeddings JOIN (
  SELECT o_custkey, min(date_diff('day', DATE '1995-01-01', o_orderdate::DATE))::DOUBLE AS lo, max(date_diff('day', DATE '1995-01-01', o_orderdate::DATE))::DOUBLE AS hi FROM orders GROUP BY 1) ON o_custkey = vec_id"""
PROVIDERS = {"uniform": OBJECTS, "point": POINTS, "life": LIVES}


def sq(a: str, b: str, dim: int = DIM) -> str:
    """Squared distance in DOUBLE."""
    return f"list_sum(list_transform(range(1, {dim + 1}), lambda i: ({a}[i]::DOUBLE - {b}[i]::DOUBLE) * ({a}[i]::DOUBLE - {b}[i]::DOUBLE)))"


def below(objects: str, n: int) -> str:
    return f"SELECT * FROM ({objects}) WHERE id < {n}"


def ranges(n: int, kind: str = "uniform", width: int | None = None, base: str | None = None) -> str:
    base = base or f"FROM range({n}) t(qid)"
    if kind == "stab":
        return f"SELECT qid, ((qid * 3571 + 911) % 10007)::DOUBLE AS ql, ((qid * 3571 + 911) % 10007)::DOUBLE AS qr {base}"
    if kind == "halves":
        wide = "(CASE WHEN qid % 2 = 0 THEN 1500 ELSE 6000 END)"
        return f"SELECT qid, ((qid * 3571 + 911) % (10007 - {wide}))::DOUBLE AS ql, ((qid * 3571 + 911) % (10007 - {wide}) + {wide})::DOUBLE AS qr {base}"
    if width is not None:
        return f"SELECT qid, ((qid * 3571 + 911) % {10007 - width})::DOUBLE AS ql, ((qid * 3571 + 911) % {10007 - width} + {width})::DOUBLE AS qr {base}"
    return f"SELECT qid, least((qid * 3571 + 911) % 10007, (qid * 2909 + 4001) % 10009)::DOUBLE AS ql, greatest((qid * 3571 + 911) % 10007, (qid * 2909 + 4001) % 10009)::DOUBLE AS qr {base}"


def queries(mode: str, n: int = 200, kind: str = "uniform", width: int | None = None) -> str:
    per = max(1, n // 25)
    asked = f"FROM (SELECT vec_id * {per} + r AS qid FROM embeddings, range({per}) x(r) WHERE vec_id % 20 = 0)"
    return f"""SELECT r.qid, list_transform(range(1, {DIM + 1}), lambda i: (u.embedding[i]::DOUBLE + v.embedding[i]::DOUBLE) / 2) AS qvec, ql, qr, '{mode}' AS mode
      FROM ({ranges(n, kind, width, asked)}) r, (SELECT count(*) AS total FROM embeddings)
      JOIN embeddings u ON u.vec_id = r.qid // {per} JOIN embeddings v ON v.vec_id = (r.qid * 37 + 11) % total"""


VALID = "(CASE mode WHEN 'within' THEN lo >= ql AND hi <= qr WHEN 'covers' THEN lo <= ql AND hi >= qr ELSE true END)"


def topk(objects: str, queries_: str, k: int = 10, valid: str = VALID) -> str:
    return f"""WITH o AS MATERIALIZED ({objects}), q AS MATERIALIZED ({queries_}),
      c AS (SELECT qid, id, {sq("vec", "qvec")} AS d2 FROM q JOIN o ON {valid}),
      r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, id) AS rk FROM c)
    SELECT qid, rk::INTEGER AS rank, id, round(sqrt(d2), 6) AS d FROM r WHERE rk <= {k}"""


def graph(objects: str, pool: str | None = None, witness: str = "interval", disjoint: str = "drop", budget: int | None = None, want: str = "edges") -> str:
    """Recursive query for one pass of pruning over all sources; pool: (src, dst), else everyone. Gives a WITH list
    that ends in ``edges`` (src, dst, bits) and ``repairs`` (src, dst)."""
    join = f"JOIN ({pool}) p ON p.src = a.id AND p.dst = b.id" if pool else ""
    near = "w.d < p.d2 AND p.dv[w.id + 1] < p.d2"
    if witness == "none":
        takes = {1: f"{near}", 2: f"{near}"}
    else:
        shared = "w.lo <= p.mlo AND w.hi >= p.mhi" + (" OR p.apart" if disjoint == "keep" else "")
        takes = {1: f"{near} AND w.bits & 1 > 0 AND w.lo >= p.hlo AND w.hi <= p.hhi", 2: f"{near} AND w.bits & 2 > 0 AND ({shared})"}
    start = "3" if witness == "none" or disjoint == "keep" else "CASE WHEN p.apart THEN 1 ELSE 3 END"
    hits = {b: f"list_filter(s.kept, lambda w: {t})" for b, t in takes.items()}
    cap = "x.bits"
    if budget is not None:
        cap = " & ".join(["x.bits", *(f"(CASE WHEN len(list_filter(x.kept, lambda w: w.bits & {b} > 0)) >= {budget} THEN {3 - b} ELSE 3 END)" for b in (1, 2))])
    return f"""WITH RECURSIVE o AS MATERIALIZED ({objects}), ends AS (SELECT max(id) AS top FROM o),
      dist AS MATERIALIZED (SELECT a.id AS a, b.id AS b, {sq("a.vec", "b.vec")} AS d2 FROM o a, o b),
      matrix AS MATERIALIZED (SELECT i.v AS v, list(d2 ORDER BY i.w) AS dv FROM (SELECT x.id AS v, y.w FROM o x, ends, range(0, ends.top + 1) y(w)) i LEFT JOIN dist ON a = i.v AND b = i.w GROUP BY i.v),
      p AS MATERIALIZED (SELECT a.id AS src, b.id AS dst, dist.d2, b.lo, b.hi, m.dv, greatest(a.lo, b.lo) AS mlo, least(a.hi, b.hi) AS mhi, least(a.lo, b.lo) AS hlo, greatest(a.hi, b.hi) AS hhi,
          greatest(a.lo, b.lo) > least(a.hi, b.hi) AS apart, row_number() OVER (PARTITION BY a.id ORDER BY dist.d2, b.id) AS rn
        FROM dist JOIN o a ON a.id = dist.a JOIN o b ON b.id = dist.b AND a.id != b.id {join} JOIN matrix m ON m.v = b.id),
      step(src, k, kept, lost) USING KEY (src) AS (
        SELECT id AS src, 0 AS k, []::STRUCT(id BIGINT, d DOUBLE, lo DOUBLE, hi DOUBLE, bits INTEGER)[] AS kept, []::STRUCT(w BIGINT, v BIGINT)[] AS lost FROM o
        UNION ALL
        SELECT src, k, CASE WHEN b > 0 THEN list_append(kept, {{'id': dst, 'd': d2, 'lo': lo, 'hi': hi, 'bits': b}}) ELSE kept END,
          list_concat(lost, list_concat(CASE WHEN start & 1 > 0 AND w1 IS NOT NULL THEN [{{'w': w1, 'v': dst}}] ELSE [] END, CASE WHEN start & 2 > 0 AND w2 IS NOT NULL THEN [{{'w': w2, 'v': dst}}] ELSE [] END))
        FROM (SELECT x.*, ({cap})::INTEGER AS b FROM (
          SELECT y.*, (start & (CASE WHEN w1 IS NULL THEN 3 ELSE 2 END) & (CASE WHEN w2 IS NULL THEN 3 ELSE 1 END)) AS bits FROM (
            SELECT s.src, s.k + 1 AS k, s.kept, s.lost, p.dst, p.d2, p.lo, p.hi, {start} AS start, {hits[1]}[1].id AS w1, {hits[2]}[1].id AS w2
            FROM step s JOIN p ON p.src = s.src AND p.rn = s.k + 1) y) x)),
      last AS (SELECT src, kept, lost FROM step),
      edges AS (SELECT src, e.id AS dst, e.bits AS bits FROM (SELECT src, unnest(kept) AS e FROM last)),
      repairs AS (SELECT DISTINCT r.w AS src, r.v AS dst FROM (SELECT unnest(lost) AS r FROM last))
    """


def attribute_pool(budget: int, keys: tuple[str, ...] = ("lo", "hi", "mid", "len"), objects: str = "SELECT * FROM o") -> str:
    h = budget // 8
    exprs = {"lo": "lo", "hi": "hi", "mid": "lo + hi", "len": "hi - lo"}
    one = [f"SELECT a.id AS src, b.id AS dst FROM (SELECT id, row_number() OVER (ORDER BY {exprs[k]}, id) AS r FROM ({objects})) a JOIN (SELECT id, row_number() OVER (ORDER BY {exprs[k]}, id) AS r FROM ({objects})) b ON abs(a.r - b.r) <= {h} AND a.r != b.r" for k in keys]
    return " UNION ".join(one)


def spatial_pool(k: int, objects: str = "SELECT * FROM o") -> str:
    return f"SELECT src, dst FROM (SELECT a.id AS src, b.id AS dst, row_number() OVER (PARTITION BY a.id ORDER BY {sq('a.vec', 'b.vec')}, b.id) AS r FROM ({objects}) a, ({objects}) b WHERE a.id != b.id) WHERE r <= {k}"
