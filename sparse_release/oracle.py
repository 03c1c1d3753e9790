"""The queries' meaning over again, in SQL for another engine: hashed draws make the randomised methods comparable row by row."""

from __future__ import annotations

import math

from .functions.laws import KeepLaw
from .functions.prf import BITS
from .operators.contingency import blocks_of
from .operators.zero_cells import walk_length
from .sources import views as V


def d(x: float) -> str:
    return f"CAST({float(x)!r} AS DOUBLE)"


def draw(key: str, tag: str, *keys: str) -> str:
    text = f"concat_ws(':', '{key}', '{tag}', {', '.join(f'CAST({k} AS VARCHAR)' for k in keys)})"
    return f"CAST('0x' || substr(md5({text}), 1, {BITS // 4}) AS BIGINT)"


def uniform(key: str, tag: str, *keys: str) -> str:
    return f"((CAST({draw(key, tag, *keys)} AS DOUBLE) + {d(0.5)}) / {d(1 << BITS)})"


def tail(alpha: float, u: str) -> str:
    return f"CAST(floor(ln({u}) / {d(math.log(alpha))}) AS BIGINT)"


def geometric(alpha: float, key: str, *keys: str, tag: str = "noise") -> str:
    return f"({tail(alpha, uniform(key, f'{tag}+', *keys))} - {tail(alpha, uniform(key, f'{tag}-', *keys))})"


def laplace(scale: float, key: str, *keys: str, tag: str = "noise") -> str:
    half = f"({uniform(key, tag, *keys)} - {d(0.5)})"
    return f"(-{d(scale)} * sign({half}) * ln({d(1)} - {d(2)} * abs({half})))"


def at(values: list[str], column: str) -> str:
    return f"(list_position([{', '.join(repr(v) for v in values)}], {column}) - 1)"


_LINES = "lineitem JOIN orders ON l_orderkey = o_orderkey"
_SRC = "CAST(substr(source, 4) AS BIGINT)"
_HOST = r"regexp_extract(url, '://([^/?#]*)', 1)"

#: View -> (rows, cell expression, domain size expression).
CELLS: dict[str, tuple[str, str, str]] = {
    "v1": (_LINES, "o_custkey * (SELECT count(*) FROM supplier) + l_suppkey", "(SELECT count(*) FROM customer) * (SELECT count(*) FROM supplier)"),
    "v1b": (_LINES, f"(((o_custkey * (SELECT count(*) FROM supplier) + l_suppkey) * 3 + {at(V.FLAGS, 'l_returnflag')}) * 2 + {at(V.STATUSES, 'l_linestatus')}) * 5 + {at(V.PRIORITIES, 'o_orderpriority')}", "(SELECT count(*) FROM customer) * (SELECT count(*) FROM supplier) * 30"),
    "v2": (f"{_LINES} JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey", f"((((({at(V.FLAGS, 'l_returnflag')} * 2 + {at(V.STATUSES, 'l_linestatus')}) * 5 + {at(V.PRIORITIES, 'o_orderpriority')}) * 3 + {at(V.ORDER_STATUSES, 'o_orderstatus')}) * 5 + {at(V.SEGMENTS, 'c_mktsegment')}) * 25 + c_nationkey) * 25 + CAST(substr(p_brand, 7) AS BIGINT) - 1", "281250"),
    "v3a": ("lineitem", "least(greatest(CAST(floor(l_extendedprice / 10) AS BIGINT), 0), 16383)", "16384"),
    "v3b": ("orders", "least(greatest(CAST(floor(o_totalprice) AS BIGINT), 0), 524287)", "524288"),
    "v3c": ("lineitem", "date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE))", "4096"),
    "v4": ("events", "(user_id * 720 + CAST(floor((epoch(ts) - 1704067200) / 3600) AS BIGINT)) * 10 + least(greatest(CAST(floor(value / 10) AS BIGINT), 0), 9)", f"{V.USERS * 7200}"),
    "v5": ("customer", f"(c_nationkey * 5 + {at(V.SEGMENTS, 'c_mktsegment')}) * 11 + least(greatest(CAST(floor((c_acctbal + 1000) / 1000) AS BIGINT), 0), 10)", "1375"),
    "v5b": ("customer", f"(c_nationkey * 5 + {at(V.SEGMENTS, 'c_mktsegment')}) * 110 + least(greatest(CAST(floor((c_acctbal + 1000) / 100) AS BIGINT), 0), 109)", "13750"),
    "v6": ("documents", f"({at(V.LANGS, 'lang')} * 20 + {_SRC}) * 100 + least(n_chars // 500, 99)", "8000"),
    "v7a": ("labels JOIN documents USING (doc_id)", f"(({at(V.LANGS, 'lang')} * 20 + {_SRC}) * 2 + quality) * 2 + toxic", "320"),
    "v7b": ("conversations", f"({at(V.ROLES, 'role')} * 8 + turn) * 100 + least(length(text) // 20, 99)", "2400"),
    "v7c": ("embeddings", f"label * 256 + {' + '.join(f'{1 << (8 - k)} * CAST(embedding[{k}] >= 0 AS INT)' for k in range(1, 9))}", "2560"),
    "v7d": ("pages", f"((CAST('0x' || substr(md5({_HOST}), 1, 4) AS BIGINT) % {V.HOST_BUCKETS}) * 4 + {at(V.LANGS, chr(39).join(['regexp_extract(url, ', '://[^/]*/([a-z]+)', ', 1)']))}) * 64 + least(length(html) // 1000, 63)", f"{V.HOST_BUCKETS * 256}"),
    "v8": ("lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey", "c_nationkey * 25 + s_nationkey", "625"),
}


def cells(view: str) -> str:
    rows, cell, _ = CELLS[view]
    return f"SELECT CAST({cell} AS BIGINT) AS cell_id, count(*) AS v FROM {rows} GROUP BY 1"


def density(view: str) -> str:
    return f"""WITH c AS ({cells(view)}) SELECT CAST({CELLS[view][2]} AS BIGINT) AS m, count(*) AS n, round(count(*) / CAST({CELLS[view][2]} AS DOUBLE), 9) AS rho,
        round(CAST({CELLS[view][2]} AS DOUBLE) / count(*), 6) AS blow_up, CAST(sum(v) AS BIGINT) AS total, round(avg(v), 6) AS mean, round(stddev_samp(v), 6) AS sd,
        round(avg(CAST(v <= 2 AS DOUBLE)), 6) AS share_to_2 FROM c"""


def everything(m: int, alpha: float, key: str, given: str = "c") -> str:
    """All noisy cells."""
    return f"SELECT i AS cell_id, coalesce(v, 0) + {geometric(alpha, key, 'i')} AS value FROM range({m}) r(i) LEFT JOIN {given} ON cell_id = i"


def magnitude(law: KeepLaw, key: str) -> str:
    cuts, far = law.cuts(), tail(law.alpha, uniform(key, "tail", "cell_id"))
    if not cuts:
        return f"{law.lo} + {far}"
    h = draw(key, "size", "cell_id")
    listed = ", ".join(f"CAST({c} AS BIGINT)" for c in cuts)
    return f"CASE WHEN {h} < {cuts[-1]} THEN {law.lo + len(cuts)} + {far} ELSE {law.lo} + (SELECT count(*) FROM (SELECT unnest([{listed}]) AS cut) WHERE {h} < cut) END"


def walks(m: int, p: float, key: str, blocks: int, given: str = "c") -> str:
    """CTEs that end in `places` (cell_id): the empty cells that are kept."""
    width = blocks_of(m, blocks)
    steps = walk_length(min(width, m), p)
    gap = f"CAST(floor(ln({uniform(key, 'gap', 'block', 'i')}) / {d(math.log1p(-p))}) AS BIGINT) + 1"
    return f"""w_occ AS (SELECT cell_id // {width} AS block, cell_id % {width} AS spot FROM {given}),
        w_key AS (SELECT block, spot - (row_number() OVER (PARTITION BY block ORDER BY spot) - 1) AS key FROM w_occ),
        w_size AS (SELECT b AS block, least({width}, {m} - b * {width}) - coalesce(n, 0) AS empty FROM range({math.ceil(m / width)}) r(b) LEFT JOIN (SELECT block, count(*) AS n FROM w_occ GROUP BY 1) o ON o.block = b),
        w_gap AS (SELECT block, empty, i, {gap} AS gap FROM w_size, range({steps + 1}) s(i)),
        w_rank AS (SELECT block, key FROM (SELECT block, empty, sum(gap) OVER (PARTITION BY block ORDER BY i) - 1 AS key FROM w_gap) WHERE key < empty),
        places AS (SELECT CAST(r.block * {width} + r.key + (SELECT count(*) FROM w_key k WHERE k.block = r.block AND k.key <= r.key) AS BIGINT) AS cell_id FROM w_rank r)"""


def direct(view: str, m: int, law: KeepLaw, key: str, blocks: int) -> str:
    return direct_of(cells(view), m, law, key, blocks)


def direct_of(given: str, m: int, law: KeepLaw, key: str, blocks: int) -> str:
    """A query for (cell_id, value): the direct route with walks, over any cells (cell_id, v)."""
    fits = f"value >= {law.lo}" if law.sides == 1 else f"abs(value) >= {law.lo}"
    keep = "" if law.tau <= 1 else f" AND {uniform(key, 'keep', 'cell_id')} < least(abs(value) / {d(law.tau)}, {d(1)})"
    sign = "1" if law.sides == 1 else f"CASE WHEN {uniform(key, 'sign', 'cell_id')} < {d(0.5)} THEN -1 ELSE 1 END"
    return f"""WITH c AS ({given}), {walks(m, law.keep(), key, blocks)},
        own AS (SELECT cell_id, value FROM (SELECT cell_id, v + {geometric(law.alpha, key, 'cell_id')} AS value FROM c) WHERE {fits}{keep})
        SELECT cell_id, CAST(value AS BIGINT) AS value FROM own UNION ALL SELECT cell_id, CAST({sign} * ({magnitude(law, key)}) AS BIGINT) AS value FROM places"""


def materialised(view: str, m: int, law: KeepLaw, key: str) -> str:
    fits = f"value >= {law.lo}" if law.sides == 1 else f"abs(value) >= {law.lo}"
    keep = "" if law.tau <= 1 else f" AND {uniform(key, 'keep', 'cell_id')} < least(abs(value) / {d(law.tau)}, {d(1)})"
    return f"WITH c AS ({cells(view)}), f AS ({everything(m, law.alpha, key)}) SELECT cell_id, CAST(value AS BIGINT) AS value FROM f WHERE {fits}{keep}"


def weighted(inner: str, tau: float) -> str:
    return f"SELECT cell_id, value, sign(value) * greatest(CAST(abs(value) AS DOUBLE), {d(tau)}) AS weight FROM ({inner})"


def node_counts(view: str, h: int) -> str:
    return f"SELECT CAST(l AS INT) AS level, cell_id >> CAST(l AS INT) AS pos, CAST(sum(v) AS BIGINT) AS v FROM ({cells(view)}), range({h + 1}) r(l) GROUP BY 1, 2"


def coefficients(view: str, h: int) -> str:
    return f"""SELECT level, pos, v FROM (SELECT CAST(l AS INT) AS level, CASE WHEN l = {h + 1} THEN 0 ELSE cell_id >> CAST(l AS INT) END AS pos,
        CAST(sum(CASE WHEN l <= {h} AND (cell_id >> CAST(l - 1 AS INT)) % 2 = 1 THEN -v ELSE v END) AS BIGINT) AS v FROM ({cells(view)}), range(1, {h + 2}) r(l) GROUP BY 1, 2) WHERE v != 0"""


def node_id(h: int, level: str, pos: str) -> str:
    return f"({1 << (h + 1)} - (CAST(1 AS BIGINT) << CAST({h + 1} - {level} AS INT)) + {pos})"


def node_of(h: int, name: str = "cell_id") -> tuple[str, str]:
    """Level and position of a node's number, found among all levels."""
    level = f"(SELECT max(l) FROM range({h + 1}) z(l) WHERE {1 << (h + 1)} - (CAST(1 AS BIGINT) << CAST({h + 1} - l AS INT)) <= {name})"
    return f"CAST({level} AS INT)", f"CAST({name} - {1 << (h + 1)} + (CAST(1 AS BIGINT) << CAST({h + 1} - {level} AS INT)) AS BIGINT)"


def subsets(m: int, sizes: list[int], per_size: int, seed: str = "1") -> str:
    primes = [p for p in (1_000_003, 1_299_709, 7_368_787, 15_485_863, 32_452_843) if m % p]
    step = f"[{', '.join(map(str, primes))}][CAST({draw(seed, 'step', 'size', 'id')} % {len(primes)} AS INT) + 1]"
    return f"""SELECT size * 1000000 + id AS qid, size, ({draw(seed, 'subset', 'size', 'id')} % {m} + (k * {step}) % {m}) % {m} AS cell_id
        FROM (SELECT i AS id, unnest([{', '.join(map(str, sizes))}])::BIGINT AS size FROM range({per_size}) r(i)), range({max(sizes)}) s(k) WHERE k < size"""


def ranges(m: int, sizes: list[int], per_size: int, seed: str = "1") -> str:
    lo = f"CAST(floor({uniform(seed, 'range', 'size', 'id')} * CAST({m} - size + 1 AS DOUBLE)) AS BIGINT)"
    return f"SELECT size * 1000000 + id AS qid, size, {lo} AS lo, {lo} + size AS hi FROM (SELECT i AS id, unnest([{', '.join(map(str, sizes))}])::BIGINT AS size FROM range({per_size}) r(i))"


def cover(queries: str, h: int) -> str:
    """(qid, level, pos), by walking up level by level."""
    return f"""WITH RECURSIVE up AS (SELECT qid, lo, hi, 0 AS level FROM ({queries}) q UNION ALL
            SELECT qid, (lo + 1) // 2, hi // 2, level + 1 FROM up WHERE level < {h} AND (lo + 1) // 2 <= hi // 2),
        ends AS (SELECT qid, level, lo AS pos FROM up WHERE lo < hi AND lo % 2 = 1 UNION ALL SELECT qid, level, hi - 1 FROM up WHERE lo < hi AND hi % 2 = 1)
        SELECT qid, CAST(level AS INT) AS level, CAST(pos AS BIGINT) AS pos FROM ends"""
