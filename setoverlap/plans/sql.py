"""SQL texts, for another engine, of the md5-family plans: registers, six sums, estimators and unrolled Newton steps."""

from __future__ import annotations

HASH = "CAST('0x' || substr(md5(k || ':' || e), 1, 15) AS BIGINT)"
UNIT = "(({v}::DOUBLE + 0.5) / 1152921504606846976.0)"


def energy(v: str) -> str:
    return f"(-ln(1.0 - {UNIT.format(v=v)}))"


def pair_registers(src: str, m: int, by: str = "") -> str:
    """src: a query giving by..., e, in_a, in_b."""
    g = f"{by}, " if by else ""
    return f"SELECT {g}k, min({HASH}) FILTER (in_a) AS va, min({HASH}) FILTER (in_b) AS vb FROM ({src}) s, range({m}) r(k) WHERE e IS NOT NULL AND (in_a OR in_b) GROUP BY {g}k"


def stats(registers: str, m: int, by: str = "") -> str:
    g = f"{by}, " if by else ""
    won_b, won_a = "vb IS NOT NULL AND (va IS NULL OR vb < va)", "va IS NOT NULL AND (vb IS NULL OR va < vb)"
    return f"""SELECT {g}{m}::BIGINT AS m, count(*) FILTER (va = vb) AS k_tie, count(*) FILTER ({won_b}) AS k_b, count(*) FILTER ({won_a}) AS k_a,
    count(*) FILTER ({won_b} AND va IS NOT NULL) AS k_b_seen, count(*) FILTER ({won_a} AND vb IS NOT NULL) AS k_a_seen,
    coalesce(sum({energy('va')}), 0) AS sum_a, coalesce(sum({energy('vb')}), 0) AS sum_b, coalesce(sum({energy('least(va, vb)')}), 0) AS sum_any
    FROM ({registers}) q {'GROUP BY ' + by if by else ''}"""


def newton(stats_sql: str, by: str = "", steps: int = 12, start: str = "interior") -> str:
    """by..., card_a, card_b, card_both after damped steps, with the closed forms at a boundary."""
    g = f"{by}, " if by else ""
    keep = f"{g}m, k_tie, k_b, k_a, sum_a, sum_b, sum_any"
    seen = "(k_tie + k_a + k_b)"
    first = f"1.0 * (k_tie + k_a) / sum_any AS a, 1.0 * (k_tie + k_b) / sum_any AS b, 1.0 * k_tie / sum_any AS n"
    if start == "scheme2":
        first = f"m / sum_a AS a, m / sum_b AS b, least(1.0 * k_tie / {seen} * {seen} / sum_any, 0.999 * m / sum_a, 0.999 * m / sum_b) AS n"
    parts = [f"s AS ({stats_sql})", f"x0 AS (SELECT {keep}, {first} FROM s WHERE k_tie > 0 AND k_b > 0 AND k_a > 0)"]
    for i in range(steps):
        parts += [
            f"g{i} AS (SELECT *, k_b / a + k_a / (a - n) - sum_a AS ga, k_a / b + k_b / (b - n) - sum_b AS gb, k_tie / n - k_b / (b - n) - k_a / (a - n) + sum_any AS gn, k_a / (a - n) / (a - n) AS wa, k_b / (b - n) / (b - n) AS wb FROM x{i})",
            f"d{i} AS (SELECT *, (gn + wa * ga / (k_b / a / a + wa) + wb * gb / (k_a / b / b + wb)) / (k_tie / n / n + wa + wb - wa * wa / (k_b / a / a + wa) - wb * wb / (k_a / b / b + wb)) AS dn FROM g{i})",
            f"f{i} AS (SELECT *, (ga + wa * dn) / (k_b / a / a + wa) AS da, (gb + wb * dn) / (k_a / b / b + wb) AS db FROM d{i})",
            f"t{i} AS (SELECT *, least(CASE WHEN a - n + da - dn > 0 THEN 1.0 ELSE 0.9 * (a - n) / (dn - da) END, CASE WHEN b - n + db - dn > 0 THEN 1.0 ELSE 0.9 * (b - n) / (dn - db) END, CASE WHEN n + dn > 0 THEN 1.0 ELSE -0.9 * n / dn END) AS t FROM f{i})",
            f"x{i + 1} AS (SELECT {keep}, a + t * da AS a, b + t * db AS b, n + t * dn AS n FROM t{i})",
        ]
    sa, sb = "(k_tie + k_a + k_b_seen)", "(k_tie + k_b + k_a_seen)"
    none = "(k_tie = 0 OR k_tie + k_a = 0 OR k_tie + k_b = 0)"
    closed = f"""SELECT {g}CASE WHEN {none} THEN coalesce({sa} / nullif(sum_a, 0), 0) WHEN k_a = 0 AND k_b = 0 THEN {seen} / sum_any WHEN k_a = 0 THEN {sa} / sum_a ELSE {sb} / sum_b + k_a / sum_a END AS card_a,
      CASE WHEN {none} THEN coalesce({sb} / nullif(sum_b, 0), 0) WHEN k_a = 0 AND k_b = 0 THEN {seen} / sum_any WHEN k_a = 0 THEN {sa} / sum_a + k_b / sum_b ELSE {sb} / sum_b END AS card_b,
      CASE WHEN {none} THEN 0 WHEN k_a = 0 AND k_b = 0 THEN {seen} / sum_any WHEN k_a = 0 THEN {sa} / sum_a ELSE {sb} / sum_b END AS card_both FROM s WHERE NOT (k_tie > 0 AND k_b > 0 AND k_a > 0)"""
    return f"WITH {', '.join(parts)} SELECT {g}a AS card_a, b AS card_b, n AS card_both FROM x{steps} UNION ALL {closed}"


def rounded(sql: str, cols: list[str], keys: list[str] | tuple = (), digits: int = 3) -> str:
    return f"SELECT {', '.join([*keys, *[f'round({c}, {digits}) AS {c}' for c in cols]])} FROM ({sql}) z"


def exact_flags(src: str, by: str = "") -> str:
    """by..., the six exact sizes of a query giving by..., e, in_a, in_b."""
    g, t = (f"{by}, ", f"GROUP BY {by}") if by else ("", "")
    return f"SELECT {g}count(*) FILTER (a) AS card_a, count(*) FILTER (b) AS card_b, count(*) FILTER (a AND b) AS card_both, count(*) AS card_any, count(*) FILTER (a AND NOT b) AS only_a, count(*) FILTER (b AND NOT a) AS only_b FROM (SELECT {g}e, bool_or(in_a) AS a, bool_or(in_b) AS b FROM ({src}) q WHERE in_a OR in_b GROUP BY {g}e) z {t}"
