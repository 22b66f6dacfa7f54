"""SQL of the definitions, for the checks: point sets, curves, seeds and assignments from the tables alone."""

from __future__ import annotations

P = {
    "lattice2d": "SELECT gx*1000+gy AS pid, gx, gy, gx::DOUBLE AS x, gy::DOUBLE AS y, count(*) AS w FROM (SELECT floor(l_quantity)::BIGINT AS gx, floor(l_extendedprice/2100)::BIGINT AS gy FROM lineitem) GROUP BY gx, gy",
    "lattice3d": "SELECT (gx*1000+gy)*1000+gz AS pid, gx, gy, gz, gx::DOUBLE AS x, gy::DOUBLE AS y, gz::DOUBLE AS z, count(*) AS w FROM (SELECT floor(l_quantity/5)::BIGINT AS gx, floor(l_extendedprice/10500)::BIGINT AS gy, floor(date_diff('day', DATE '1995-01-01', l_shipdate::DATE)/90.0)::BIGINT AS gz FROM lineitem) GROUP BY gx, gy, gz",
    "events2d": "SELECT event_id AS pid, (epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01'))/86400000000.0::DOUBLE AS x, value/10 AS y, 1::BIGINT AS w FROM events",
    "events3d": "SELECT event_id AS pid, (epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01'))/86400000000.0::DOUBLE AS x, hour(ts)::DOUBLE AS y, value/10 AS z, 1::BIGINT AS w FROM events",
    "orders2d": "SELECT o_orderkey AS pid, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::DOUBLE AS x, o_totalprice/1000 AS y, coalesce(n, 1)::BIGINT AS w FROM orders LEFT JOIN (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY l_orderkey) ON o_orderkey = l_orderkey",
    "parts2d": "SELECT p_partkey AS pid, p_size::DOUBLE AS x, p_retailprice AS y, 1::BIGINT AS w FROM part",
    "customers2d": "SELECT c_custkey AS pid, c_nationkey::DOUBLE AS x, c_acctbal/100 AS y, greatest(coalesce(n, 0), 1)::BIGINT AS w FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) ON c_custkey = o_custkey",
    "docs2d": "SELECT doc_id AS pid, ln(1+n_chars::DOUBLE) AS x, (length(text)-length(replace(text, chr(10), ''))+1)::DOUBLE AS y, greatest(n_chars, 1) AS w FROM documents",
    "turns2d": "SELECT conv_id*100+turn AS pid, conv_id::DOUBLE AS x, turn::DOUBLE AS y, length(text)::BIGINT AS w FROM conversations",
    "pages2d": "SELECT page_id AS pid, length(html)::DOUBLE/1000 AS x, (length(url)-length(replace(url, '/', '')))::DOUBLE AS y, length(html)::BIGINT AS w FROM pages",
    "tiny": "SELECT item_id AS pid, item_id::DOUBLE AS x, length(text)::DOUBLE AS y, 1::BIGINT AS w FROM benchmark",
}


def materialized(parts: list[tuple[str, str]], select: str) -> str:
    """CTEs that are each computed once, however often they are read."""
    return "WITH " + ", ".join(f"{n} AS MATERIALIZED ({q})" for n, q in parts) + f" {select}"


def quantized(src: str, dims: str, bits: int) -> str:
    side = 1 << bits
    box = ", ".join(f"min({d}) AS lo_{d}, max({d}) AS hi_{d}" for d in dims)
    cells = ", ".join(f"CASE WHEN hi_{d} > lo_{d} THEN least(floor(({d}-lo_{d})/(hi_{d}-lo_{d})*{side}.0::DOUBLE)::BIGINT, {side - 1}) ELSE 0 END::BIGINT AS g{d}" for d in dims)
    return f"SELECT p.*, {cells} FROM ({src}) p, (SELECT {box} FROM ({src})) b"


def hilbert2d(src: str, bits: int, x: str = "gx", y: str = "gy") -> str:
    top = (1 << bits) - 1
    s = f"SELECT *, {x} AS _x, {y} AS _y, 0::BIGINT AS hkey FROM ({src})"
    for b in range(bits - 1, -1, -1):
        rx, ry = f"((_x >> {b}) & 1)", f"((_y >> {b}) & 1)"
        s = f"SELECT * REPLACE (CASE WHEN {ry}=1 THEN _x WHEN {rx}=1 THEN {top}-_y ELSE _y END AS _x, CASE WHEN {ry}=1 THEN _y WHEN {rx}=1 THEN {top}-_x ELSE _x END AS _y, hkey*4 + xor(3*{rx}, {ry}) AS hkey) FROM ({s})"
    return f"SELECT * EXCLUDE (_x, _y) FROM ({s})"


def hilbert3d(src: str, bits: int) -> str:
    s = f"SELECT *, gx AS _x, gy AS _y, gz AS _z FROM ({src})"
    for b in range(bits - 1, 0, -1):
        q, low = 1 << b, (1 << b) - 1
        s = f"SELECT * REPLACE (CASE WHEN _x & {q} <> 0 THEN xor(_x, {low}) ELSE _x END AS _x) FROM ({s})"
        for a in ("_y", "_z"):
            s = f"SELECT * REPLACE (CASE WHEN {a} & {q} <> 0 THEN xor(_x, {low}) ELSE xor(_x, xor(_x, {a}) & {low}) END AS _x, CASE WHEN {a} & {q} <> 0 THEN {a} ELSE xor({a}, xor(_x, {a}) & {low}) END AS {a}) FROM ({s})"
    s = f"SELECT * REPLACE (xor(_y, _x) AS _y) FROM ({s})"
    s = f"SELECT * REPLACE (xor(_z, _y) AS _z) FROM ({s})"
    flip = "0::BIGINT"
    for b in range(bits - 1, 0, -1):
        flip = f"xor({flip}, CASE WHEN (_z >> {b}) & 1 = 1 THEN {(1 << b) - 1} ELSE 0 END)"
    s = f"SELECT *, {flip} AS _t FROM ({s})"
    s = f"SELECT * REPLACE (xor(_x, _t) AS _x, xor(_y, _t) AS _y, xor(_z, _t) AS _z) FROM ({s})"
    key = " + ".join(f"((_x >> {b}) & 1)*{4 << 3 * b} + ((_y >> {b}) & 1)*{2 << 3 * b} + ((_z >> {b}) & 1)*{1 << 3 * b}" for b in range(bits))
    return f"SELECT * EXCLUDE (_x, _y, _z, _t), ({key})::BIGINT AS hkey FROM ({s})"


def morton2d(src: str, bits: int) -> str:
    key = " + ".join(f"((gx >> {b}) & 1)*{2 << 2 * b} + ((gy >> {b}) & 1)*{1 << 2 * b}" for b in range(bits))
    return f"SELECT *, ({key})::BIGINT AS hkey FROM ({src})"


def chunks(src: str, k: int) -> str:
    """pid, block of k equal-weight runs along hkey."""
    return f"SELECT pid, least({k - 1}, floor((cum - w/2)*{k}/total))::INTEGER AS block FROM (SELECT pid, w, sum(w) OVER (ORDER BY hkey, pid ROWS UNBOUNDED PRECEDING)::DOUBLE AS cum, sum(w) OVER ()::DOUBLE AS total FROM ({src}))"


def seeds(src: str, k: int, dims: str = "xy") -> str:
    c = ", ".join(dims)
    return f"SELECT s.block::INTEGER AS block, {c} FROM (SELECT *, row_number() OVER (ORDER BY hkey, pid)-1 AS rank, count(*) OVER () AS n FROM ({src})) r JOIN (SELECT unnest(range({k})) AS block) s ON r.rank = (2*s.block+1)*r.n//{2 * k}"


#: Closed formula of the block id that stands in for an influence in the checks.
INFLUENCE = "(1 + (block % 3)*0.125::DOUBLE)"

H2 = hilbert2d(P["lattice2d"], 6)
H3 = hilbert3d(P["lattice3d"], 5)
HE = hilbert2d(quantized(P["events2d"], "xy", 16), 16)


def nearest(points: str, centres: str, dims: str = "xy", influence: str = INFLUENCE) -> str:
    """pid, dims, w, block, eff, eff2: least and second-least effective distance, ties to the lowest block."""
    d2 = " + ".join(f"(p.{d}-c.{d})*(p.{d}-c.{d})" for d in dims)
    cols = ", ".join(f"p.{d}" for d in dims)
    names = ", ".join(dims)
    return f"SELECT pid, {names}, w, block, eff, eff2 FROM (SELECT *, row_number() OVER (PARTITION BY pid ORDER BY eff, block) AS rn, lead(eff) OVER (PARTITION BY pid ORDER BY eff, block) AS eff2 FROM (SELECT p.pid, {cols}, p.w, c.block, sqrt({d2})/{influence} AS eff FROM ({points}) p, ({centres}) c)) WHERE rn = 1"


G1 = "SELECT a.pid AS src, b.pid AS dst, 1.0::DOUBLE AS ew FROM ({p}) a JOIN ({p}) b ON (b.gx=a.gx+1 AND b.gy=a.gy) OR (b.gx=a.gx AND b.gy=a.gy+1) OR (b.gx=a.gx+1 AND b.gy=a.gy+1)".format(p=P["lattice2d"])
A8 = chunks(H2, 8)
E8 = f"SELECT e.src, e.dst, e.ew, a.block AS b1, b.block AS b2 FROM ({G1}) e JOIN ({A8}) a ON e.src=a.pid JOIN ({A8}) b ON e.dst=b.pid"
BORDER8 = f"SELECT DISTINCT * FROM (SELECT b1 AS block, src AS pid, b2 AS other FROM ({E8}) WHERE b1<>b2 UNION ALL SELECT b2, dst, b1 FROM ({E8}) WHERE b1<>b2)"
