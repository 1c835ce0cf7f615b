"""SQL of the shared derivations, for the oracle: common table expressions by name, put together on demand."""

from __future__ import annotations

from adaptivejoin.functions.costs import CostProfile

LANES = 8
HOMES = 8
BATCH = 32

HASH = "CAST('0x' || substr(md5({0}), 1, 15) AS BIGINT)"


def h(x: str) -> str:
    return HASH.format(x)


ROW_ID = "concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey)"
POWER = {0.0: "1.0", 0.5: "sqrt(CAST(k AS DOUBLE))", 1.0: "CAST(k AS DOUBLE)", 1.5: "(k * sqrt(CAST(k AS DOUBLE)))"}


def probe(z: float, lanes: int = LANES, moving: bool = False) -> str:
    """probe(row_id, lane, l_orderkey, l_linenumber, l_partkey, l_suppkey, qty, key[, phase])."""
    rank = "k - 1"
    phase = ", 10 * l_orderkey // (SELECT max(l_orderkey) + 1 FROM lineitem) AS phase"
    key = f"({rank} + phase * 97) % (SELECT n FROM universe)" if moving else rank
    return f"""
universe AS (SELECT count(*) AS n FROM part),
weights AS (SELECT k, CAST(floor(1000000000 / {POWER[z]}) AS BIGINT) AS w FROM (SELECT unnest(generate_series(1, (SELECT CAST(n AS BIGINT) FROM universe))) AS k)),
bounds AS (SELECT k, CAST(sum(w) OVER (ORDER BY k) AS BIGINT) - w AS lo, CAST(sum(w) OVER (ORDER BY k) AS BIGINT) AS hi FROM weights),
drawn AS (SELECT *, {h("row_id")} % (SELECT max(hi) FROM bounds) AS u, {h("row_id || '#'")} % {lanes} AS lane
  FROM (SELECT {ROW_ID} AS row_id, l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(l_quantity AS BIGINT) AS qty FROM lineitem)),
probe AS (SELECT row_id, CAST(lane AS INTEGER) AS lane, l_orderkey, l_linenumber, l_partkey, l_suppkey, qty, CAST({key} AS BIGINT) AS key{", phase" if moving else ""}
  FROM (SELECT *{phase if moving else ""} FROM drawn) d JOIN bounds ON u >= lo AND u < hi)"""


SEQ = "l_orderkey, l_linenumber, l_partkey, l_suppkey"


def transfer(size: str, p: CostProfile) -> str:
    return f"(({size}) + {p.bandwidth - 1}) // {p.bandwidth}"


def costs(p: CostProfile, value_bytes: str = "value_bytes") -> dict[str, str]:
    join = (lambda *x: f"greatest({', '.join(x)})") if p.overlap else (lambda *x: "(" + " + ".join(x) + ")")
    return {
        "rent": f"CAST({join(str(p.home_disk_us), transfer(str(p.key_bytes + p.param_bytes + p.result_bytes), p), str(p.home_cpu_us))} AS BIGINT)",
        "buy": f"CAST({join(str(p.home_disk_us), transfer(f'{value_bytes} + {p.key_bytes}', p))} AS BIGINT)",
        "mem": f"CAST({p.lane_cpu_us} AS BIGINT)",
        "disk": f"CAST({join(str(p.lane_cpu_us), str(p.lane_disk_us))} AS BIGINT)",
    }


def threshold(r: str, b: str, m: str, first_ships: bool = True) -> str:
    by = f"CASE WHEN {r} <= {m} THEN {(1 << 62) - 1} ELSE {b} // ({r} - {m}) END"
    return f"CASE WHEN {r} > {m} AND {b} <= {r} THEN 1 ELSE greatest({by}, 1) END" if first_ships else by


STORE_BYTES = "CAST(2 * octet_length(encode(p_name)) * (1 + p_size) AS BIGINT)"


def routed(p: CostProfile, z: float, first_ships: bool = True, use: str | None = None, moving: bool = False, rent: str | None = None) -> str:
    """probe, store and trace(row_id, lane, key, c, route, rent, buy, use, m)."""
    c = costs(p)
    use, rent = use or c["mem"], rent or c["rent"]
    return f"""{probe(z, moving=moving)},
store AS (SELECT p_partkey AS skey, p_size, p_retailprice, {STORE_BYTES} AS value_bytes FROM part),
priced AS (SELECT p.*, s.value_bytes, {rent} AS rent, {c['buy']} AS buy, {use} AS use FROM probe p JOIN store s ON p.key = s.skey),
counted AS (SELECT *, row_number() OVER (PARTITION BY lane, key ORDER BY {SEQ}) AS c, {threshold('rent', 'buy', 'use', first_ships)} AS m FROM priced),
trace AS (SELECT *, CASE WHEN c <= m THEN 'ship' WHEN c = m + 1 THEN 'fetch' ELSE 'local' END AS route FROM counted)"""


CALL = "(key * 31 + qty * 7 + p_size * CAST(floor(p_retailprice) AS BIGINT)) % 1000003"
