"""SQL twins: offsets by neighbours, and the derived inputs, as text for the other engine."""

from __future__ import annotations

HALF = 1 << 54
STEP = 1 << 56

K4 = ["l_returnflag", "l_linestatus", "l_tax", "l_discount"]
K6 = ["l_returnflag", "l_linestatus", "l_linenumber", "l_tax", "l_discount", "l_quantity"]
K8 = [*K6, "l_suppkey", "l_partkey"]
KL = ["l_orderkey", "l_linenumber"]
KO = ["o_orderstatus", "o_orderpriority", "o_orderdate", "o_custkey"]
KE = ["event_type", "user_id", "ts"]
KV = ["conv_id", "turn"]
KC = ["c_mktsegment", "c_nationkey", "c_custkey"]


def order(keys: list[str]) -> str:
    return ", ".join(f"{k[1:]} DESC NULLS LAST" if k[0] == "-" else f"{k} NULLS FIRST" for k in keys)


def offsets(source: str, keys: list[str], more: list[str] | None = None, columns: str = "*", tie: str = "") -> str:
    """Rows of a table or sub-query with off; a sub-query to select from."""
    names = [k.lstrip("-") for k in keys]
    lags = ", ".join(f"lag({n}) OVER w AS p_{n}" for n in names)
    cases = " ".join(f"WHEN {n} IS DISTINCT FROM p_{n} THEN {j}" for j, n in enumerate(names))
    by = order(keys) + (f", {tie}" if tie else "")
    return (
        f"(SELECT *, CASE WHEN rn_ = 1 THEN 0 {cases} ELSE {len(names)} END AS off FROM "
        f"(SELECT {columns}, {lags}, row_number() OVER w AS rn_ FROM {source} WINDOW w AS (ORDER BY {by})))"
    )


def ndv(source: str, keys: list[str]) -> list[str]:
    """Sub-queries that count distinct prefixes."""
    return [f"(SELECT count(*) FROM (SELECT DISTINCT {', '.join(keys[: j + 1])} FROM {source}))" for j in range(len(keys))]


def digits(constant: int, total: int = 10) -> tuple[list[str], str]:
    """Key columns: some constant, the others digits in base 9 of a scrambled number. (names, select list)"""
    x = "((l_orderkey * 1000003 + l_partkey * 7919 + l_linenumber * 104729) % 43046721)"
    names = [f"d{i}" for i in range(total)]
    cols = [f"1 AS d{i}" for i in range(constant)]
    cols += [f"CAST((floor({x} / {9 ** ((i - constant) % 8)}) % 9) + 1 AS INT) AS d{i}" for i in range(constant, total)]
    return names, ", ".join(cols)


def copies(each: int, base: int = 7, columns: int = 8) -> tuple[list[str], str]:
    """Keys repeated ``each`` times: digits of rid / each. (names, select list over rid)"""
    names = [f"d{i}" for i in range(columns)]
    return names, ", ".join(f"CAST(floor(floor(rid / {each}) / {base ** (columns - 1 - i)}) % {base} AS INT) AS d{i}" for i in range(columns))


RID = (
    "(SELECT *, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) - 1 AS rid FROM lineitem)"
)
