"""The same results in plain SQL, for an engine that shares no code with this one: fragments and their assembly."""

from __future__ import annotations

import re

from ..functions.clip import WEDGE_STEPS
from ..sources.fixtures import DIRECTIONS, WORKLOADS

_DX = ", ".join(str(d[0]) for d in DIRECTIONS)
_DY = ", ".join(str(d[1]) for d in DIRECTIONS)
_WEDGE = ", ".join(f"{sql} AS {name}" for name, sql in WEDGE_STEPS)
_SOURCE_KEYS = {"orders": ("o_orderkey", "o_custkey"), "customer": ("c_custkey", "c_nationkey"), "part": ("p_partkey", "p_size")}


def _ring(rows: str, key: str) -> str:
    """Vertices in order from rows of key, cx, cy, h, n."""
    return f"""SELECT {key}, j, (cx + r * [{_DX}][1 + (12 * j) // n]) / 128.0::DOUBLE AS x, (cy + r * [{_DY}][1 + (12 * j) // n]) / 128.0::DOUBLE AS y
      FROM (SELECT *, 1 + (h * (5 + ({key} * (j + 1)) % 6)) // 50 AS r FROM (SELECT *, unnest(range(n)) AS j FROM {rows}))"""


def fragments(work_name: str = "d1") -> dict[str, str]:
    """Named common table expressions; each may use the others."""
    work = WORKLOADS[work_name]
    first, second = _SOURCE_KEYS[work.sources]
    f = {
        "dom": f"SELECT w, w * {work.permille} // 1000 AS m FROM (SELECT floor({work.base} * sqrt(count(*) / 1500000.0::DOUBLE) + 1e-6)::BIGINT AS w FROM orders)",
        "src": f"""SELECT sid, cx, cy, 30 + (sid * 11) % (5 + 6 * b) AS h, 4 + (sid * 7) % (1 + b) AS n FROM (SELECT *, 8 * cx // m AS b FROM (
            SELECT {first}::BIGINT AS sid, ({first}::BIGINT * 7919 + {second}::BIGINT * 104729) % m AS cx, ({first}::BIGINT * 6151 + {second}::BIGINT * 3571) % w AS cy, m FROM {work.sources}, dom))""",
        "sv": _ring("src", "sid"),
        "tv": _ring("trg", "tid"),
    }
    if work.targets == "orders":
        f["trg"] = """SELECT o_orderkey AS tid, (o_orderkey * 7919 + o_custkey * 104729) % w AS cx, (o_orderkey * 6151 + o_custkey * 3571) % w AS cy,
            5 + floor(o_totalprice)::BIGINT % 60 AS h, 3 + o_orderkey % 10 AS n, o_orderkey % 2 = 0 AS line FROM orders, dom"""
    else:
        f["trg"] = """SELECT ok * 8 + ln + 1000000000 * (pk * 1001 + sk) AS tid, (ok * 7919 + pk * 104729 + ln * 613) % w AS cx, (ok * 6151 + sk * 3571 + ln * 977) % w AS cy,
            2 * floor(q)::BIGINT AS h, 3 + (ok * 8 + ln + 1000000000 * (pk * 1001 + sk)) % 10 AS n, st = 'O' AS line
          FROM (SELECT l_orderkey::BIGINT AS ok, l_linenumber::BIGINT AS ln, l_partkey::BIGINT AS pk, l_suppkey::BIGINT AS sk, max(l_quantity) AS q, max(l_linestatus) AS st FROM lineitem GROUP BY 1, 2, 3, 4), dom"""
    f |= {
        "sbox": "SELECT sid, min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM sv GROUP BY sid",
        "tbox": "SELECT tid, min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM tv GROUP BY tid",
        "sedge": "SELECT sid, j, x AS x1, y AS y1, coalesce(lead(x) OVER o, first_value(x) OVER o) AS x2, coalesce(lead(y) OVER o, first_value(y) OVER o) AS y2 FROM sv WINDOW o AS (PARTITION BY sid ORDER BY j)",
        "tedge": "SELECT tid, j, n, line, x AS x1, y AS y1, coalesce(lead(x) OVER o, first_value(x) OVER o) AS x2, coalesce(lead(y) OVER o, first_value(y) OVER o) AS y2 FROM tv JOIN (SELECT tid, n, line FROM trg) USING (tid) WINDOW o AS (PARTITION BY tid ORDER BY j)",
        "smeas": "SELECT sid, count(*) AS n, sum(x1 * y2 - x2 * y1) / 2 AS area, sum(sqrt((x2 - x1) * (x2 - x1) + (y2 - y1) * (y2 - y1))) AS perimeter, sum((x1 + x2) * (x1 * y2 - x2 * y1)) / 6 / (sum(x1 * y2 - x2 * y1) / 2) AS cx, sum((y1 + y2) * (x1 * y2 - x2 * y1)) / 6 / (sum(x1 * y2 - x2 * y1) / 2) AS cy FROM sedge GROUP BY sid",
        "tmeas": "SELECT tid, any_value(n) AS points, sum(CASE WHEN line AND j = n - 1 THEN 0 ELSE sqrt((x2 - x1) * (x2 - x1) + (y2 - y1) * (y2 - y1)) END) AS length FROM tedge GROUP BY tid",
        "cedge": "SELECT sid, j, x1 - cx AS x1, y1 - cy AS y1, x2 - cx AS x2, y2 - cy AS y2 FROM sedge JOIN smeas USING (sid)",
        "cbox": "SELECT sid, min(x1) AS x1, min(y1) AS y1, max(x1) AS x2, max(y1) AS y2 FROM cedge GROUP BY sid",
        "scalars": "SELECT sid, n, area, perimeter, (b.x2 - b.x1 + 1e-9) / (b.y2 - b.y1 + 1e-9) AS aspect, CASE WHEN perimeter > 0 THEN 4 * pi() * area / (perimeter * perimeter) ELSE 0 END AS phi, (b.x1 + b.x2) / 2 AS bx, (b.y1 + b.y2) / 2 AS by_ FROM smeas JOIN cbox b USING (sid)",
        "walk": "SELECT sid, x1, y1, x2, y2, len, coalesce(sum(len) OVER (PARTITION BY sid ORDER BY j ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS at0, sum(len) OVER (PARTITION BY sid) AS total FROM (SELECT *, sqrt((x2 - x1) * (x2 - x1) + (y2 - y1) * (y2 - y1)) AS len FROM sedge)",
        "spots": "SELECT sid, i, x1 + (x2 - x1) * (i * total / 64 - at0) / len AS x, y1 + (y2 - y1) * (i * total / 64 - at0) / len AS y FROM (SELECT *, unnest(range(64)) AS i FROM walk) WHERE i * total / 64 >= at0 AND i * total / 64 < at0 + len",
        "waves": "SELECT sid, k, sqrt(sum(x * cos(2 * pi() * k * i / 64) + y * sin(2 * pi() * k * i / 64)) ** 2 + sum(y * cos(2 * pi() * k * i / 64) - x * sin(2 * pi() * k * i / 64)) ** 2) / 64 AS m FROM (SELECT *, unnest(range(1, 10)) AS k FROM spots) GROUP BY sid, k",
        "fds": "SELECT sid, list(m / m1 ORDER BY k) FILTER (k > 1) AS fd FROM waves JOIN (SELECT sid, m AS m1 FROM waves WHERE k = 1) USING (sid) GROUP BY sid",
        "grid": "SELECT 1 / avg(x2 - x1) AS dx, 1 / avg(y2 - y1) AS dy FROM sbox",
        "stile": "SELECT sid, x1, y1, x2, y2, floor(x1 * dx)::BIGINT AS i1, floor(y1 * dy)::BIGINT AS j1, floor(x2 * dx)::BIGINT AS i2, floor(y2 * dy)::BIGINT AS j2 FROM sbox, grid",
        "ttile": "SELECT tid, x1, y1, x2, y2, floor(x1 * dx)::BIGINT AS i1, floor(y1 * dy)::BIGINT AS j1, floor(x2 * dx)::BIGINT AS i2, floor(y2 * dy)::BIGINT AS j2 FROM tbox, grid",
        "sx": "SELECT *, unnest(range(j1, j2 + 1)) AS j FROM (SELECT *, unnest(range(i1, i2 + 1)) AS i FROM stile)",
        "tx": "SELECT *, unnest(range(j1, j2 + 1)) AS j FROM (SELECT *, unnest(range(i1, i2 + 1)) AS i FROM ttile)",
        "pairs": """SELECT tid, sid, count(*) AS common_tiles, any_value(s.x1 <= t.x2 AND t.x1 <= s.x2 AND s.y1 <= t.y2 AND t.y1 <= s.y2) AS mbr_hit,
            any_value(greatest(0, least(s.x2, t.x2) - greatest(s.x1, t.x1)) * greatest(0, least(s.y2, t.y2) - greatest(s.y1, t.y1))) AS shared FROM tx t JOIN sx s USING (i, j) GROUP BY tid, sid""",
        "hits": "SELECT tid, sid FROM tbox t JOIN sbox s ON s.x1 <= t.x2 AND t.x1 <= s.x2 AND s.y1 <= t.y2 AND t.y1 <= s.y2",
        "members": "SELECT tid AS cid, sid, size FROM (SELECT *, count(*) OVER (PARTITION BY tid) AS size FROM pairs WHERE mbr_hit) WHERE size >= 2",
        "mpairs": "SELECT cid, x.sid AS a, y.sid AS b FROM members x JOIN members y USING (cid) WHERE x.sid < y.sid",
        "dpairs": "SELECT DISTINCT a, b FROM mpairs",
        "wedges": f"SELECT a, b, {_WEDGE} FROM (SELECT a, b, p.x1 AS px, p.y1 AS py, p.x2 AS qx, p.y2 AS qy, s.x1 AS sx, s.y1 AS sy, s.x2 AS tx, s.y2 AS ty FROM dpairs JOIN cedge p ON p.sid = a JOIN cedge s ON s.sid = b)",
        "inters": "SELECT a, b, greatest(0, sum(wedge)) AS inter FROM wedges GROUP BY a, b",
        "sims": """SELECT a, b, inter / (x.area + y.area - inter) AS jaccard, 2 * inter / (x.area + y.area) AS area, exp(-abs(x.n - y.n) / greatest(x.n, y.n)::DOUBLE) AS curvature,
            1 / (1 + sqrt(list_sum(list_transform(list_zip(f.fd, g.fd), lambda z: (z[1] - z[2]) ** 2)))) AS fourier, 1 / (1 + abs(x.aspect - y.aspect)) AS aspect, 1 / (1 + abs(x.perimeter - y.perimeter)) AS perimeter,
            1 / (1 + sqrt((x.bx - y.bx) ** 2 + (x.by_ - y.by_) ** 2)) AS bbox, 1 / (1 + abs(x.phi - y.phi)) AS circularity
          FROM inters JOIN scalars x ON x.sid = a JOIN scalars y ON y.sid = b JOIN fds f ON f.sid = a JOIN fds g ON g.sid = b""",
        "scored_pairs": "SELECT *, (jaccard + area + curvature + fourier + aspect + perimeter + bbox + circularity) / 8 AS s FROM sims",
        "si": "SELECT cid, count(*) AS n_pairs, avg(s) AS si FROM mpairs JOIN scored_pairs USING (a, b) GROUP BY cid",
        "sstats": "SELECT sid, sum(common_tiles)::BIGINT AS total, count(*) AS \"distinct\", count(*) FILTER (mbr_hit) AS \"real\" FROM pairs GROUP BY sid",
        "tstats": "SELECT tid, sum(common_tiles)::BIGINT AS total, count(*) AS \"distinct\", count(*) FILTER (mbr_hit) AS \"real\" FROM pairs GROUP BY tid",
        "raw": """SELECT m.cid, m.sid, (st.x2 - st.x1) * (st.y2 - st.y1) AS f1, (tt.x2 - tt.x1) * (tt.y2 - tt.y1) AS f2, ((st.i2 - st.i1 + 1) * (st.j2 - st.j1 + 1))::DOUBLE AS f3, ((tt.i2 - tt.i1 + 1) * (tt.j2 - tt.j1 + 1))::DOUBLE AS f4,
            p.common_tiles::DOUBLE AS f5, sm.n::DOUBLE AS f6, tm.points::DOUBLE AS f7, sm.perimeter AS f8, tm.length AS f9, ss.total::DOUBLE AS f10, ss."distinct"::DOUBLE AS f11, ss."real"::DOUBLE AS f12, ts.total::DOUBLE AS f13, ts."distinct"::DOUBLE AS f14, m.size::DOUBLE AS f15, p.shared AS f16
          FROM members m JOIN pairs p ON p.tid = m.cid AND p.sid = m.sid JOIN stile st ON st.sid = m.sid JOIN ttile tt ON tt.tid = m.cid JOIN smeas sm ON sm.sid = m.sid JOIN tmeas tm ON tm.tid = m.cid JOIN sstats ss ON ss.sid = m.sid JOIN tstats ts ON ts.tid = m.cid""",
        "praw": "SELECT cid, sid, " + ", ".join(f"coalesce((f{i} - min(f{i}) OVER ()) / nullif(max(f{i}) OVER (), 0) * 10000, 0) AS f{i}" for i in range(1, 17)) + " FROM raw",
        "pmeans": "SELECT cid, " + ", ".join(f"avg(f{i}) AS f{i}" for i in range(1, 17)) + " FROM praw GROUP BY cid",
        "cfeat": "SELECT cid, " + ", ".join(f"coalesce((f{i} - min(f{i}) OVER ()) / nullif(max(f{i}) OVER (), 0) * 10000, 0) AS f{i}" for i in range(1, 17)) + " FROM pmeans",
        "draw": "SELECT cid, row_number() OVER (ORDER BY ((cid % 2147483647) * 48271 + 1) % 2147483647, cid) - 1 AS place FROM (SELECT DISTINCT cid FROM members)",
        "sample": "SELECT cid, place FROM draw WHERE place < 300",
        "tau": "SELECT quantile_cont(si, 0.9) AS tau FROM si",
        "sizes": "SELECT cid, count(*) AS size FROM members GROUP BY cid",
        "ranked": "SELECT cid, si, size AS w, CASE WHEN si >= tau THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS label, row_number() OVER (ORDER BY size, cid) AS place FROM sizes JOIN si USING (cid), tau",
    }
    return f


def assemble(select: str, work_name: str = "d1", **more: str) -> str:
    """The select with exactly the fragments it needs, in order of use."""
    known = fragments(work_name) | more
    order: list[str] = []

    def visit(sql: str) -> None:
        for name in re.findall(r"(?:FROM|JOIN|,)\s+(\w+)", sql):
            if name in known and name not in order:
                visit(known[name])
                if name not in order:
                    order.append(name)

    visit(select)
    return ("WITH " + ",\n".join(f"{n} AS MATERIALIZED ({known[n]})" for n in order) + "\n" if order else "") + select
