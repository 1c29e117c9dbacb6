"""Builders of the SQL twins: level chains of pivots and segments, as common table expressions."""

from __future__ import annotations


def by_position(table: str, columns: str, order: str, pos: str = "pos") -> str:
    """Rows with their zero-based position in an order."""
    return f"SELECT {columns}, row_number() OVER (ORDER BY {order}) - 1 AS {pos} FROM {table}"


def chain(base: str, p: int, rule: str = "midpoint", *, whole: bool = False, cast: str = "DOUBLE") -> str:
    """A WITH clause: base(k, r, ...), then for each level v<i>(s, piv), pv<i>, and the rows s<i> with their segment s.

    rule: midpoint, middle (median of the ranks' middles), mean (of these), designated (that of the first
    rank), exact, and the ends of a sample of 20 rows a rank by t: ``sampled`` with all ranks taking part in
    all levels, ``sampled_exchange`` with ranks as they are after the exchanges so far, ``sampled_combined``
    with the exchanges of the combined variant.
    whole: keys are whole numbers, whose midpoint is rounded down.
    """
    levels, parts = p.bit_length() - 1, [f"base AS ({base})", "s0 AS (SELECT *, 0 AS s FROM base)"]
    if rule == "sampled_combined":
        parts[1] = "s0 AS (SELECT base.*, 0 AS s, switch.l FROM base, switch)"
        parts.insert(1, f"switch AS (SELECT CAST(min(g.range) AS INTEGER) AS l FROM range({levels + 1}) g, (SELECT count(*) AS n FROM base) b WHERE g.range = {levels} OR b.n::DOUBLE / {p} > 1500 * ({p} >> g.range::INTEGER) / log2(b.n))")
    for i in range(levels):
        if rule == "midpoint":
            half = "CAST(floor((min(k) + max(k)) / 2) AS BIGINT)" if whole else "(min(k) + max(k)) / 2"
            parts.append(f"v{i} AS (SELECT s, {half} AS piv FROM s{i} GROUP BY s)")
        elif rule.startswith("sampled"):
            half = "CAST(floor((min(k) + max(k)) / 2) AS BIGINT)" if whole else "(min(k) + max(k)) / 2"
            rest = p >> i
            at = "r"
            if rule == "sampled_exchange":
                at = f"s * {rest} + r % {rest}"
            elif rule == "sampled_combined":  # ranks stay as they are from the switch on
                at = f"(s >> greatest(0, {i} - l)) * ({p} >> least({i}, l)) + r % ({p} >> least({i}, l))"
            parts.append(f"v{i} AS (SELECT s, {half} AS piv FROM (SELECT s, k, row_number() OVER (PARTITION BY s, {at} ORDER BY t, k) AS rn FROM s{i}) WHERE rn <= 20 GROUP BY s)")
        elif rule == "exact":
            parts.append(f"v{i} AS (SELECT s, k AS piv FROM (SELECT s, k, row_number() OVER (PARTITION BY s ORDER BY k) AS rn, count(*) OVER (PARTITION BY s) AS n FROM s{i}) WHERE rn = (n + 1) // 2)")
        else:
            parts.append(f"c{i} AS (SELECT s, r, k AS mid FROM (SELECT s, r, k, row_number() OVER (PARTITION BY s, r ORDER BY k) AS rn, count(*) OVER (PARTITION BY s, r) AS n FROM s{i}) WHERE rn = n // 2 + 1)")
            if rule == "mean":
                parts.append(f"v{i} AS (SELECT s, avg(mid) AS piv FROM c{i} GROUP BY s)")
            elif rule == "middle":
                parts.append(f"v{i} AS (SELECT s, mid AS piv FROM (SELECT s, mid, row_number() OVER (PARTITION BY s ORDER BY mid) AS rn, count(*) OVER (PARTITION BY s) AS n FROM c{i}) WHERE rn = (n + 1) // 2)")
            else:
                parts.append(f"v{i} AS (SELECT s, arg_min(mid, r) AS piv FROM c{i} GROUP BY s)")
        above = f"LEFT JOIN pv{i - 1} u ON u.s = g.s // 2" if i else ""
        inherited = "coalesce(v.piv, u.piv)" if i else "v.piv"
        parts.append(f"pv{i} AS (SELECT g.s, {inherited} AS piv FROM (SELECT range AS s FROM range({1 << i})) g LEFT JOIN v{i} v ON v.s = g.s {above})")
        parts.append(f"s{i + 1} AS (SELECT a.* EXCLUDE (s), 2 * a.s + CASE WHEN a.k > b.piv THEN 1 ELSE 0 END AS s FROM s{i} a JOIN v{i} b ON a.s = b.s)")
    return "WITH " + ",\n".join(parts)


def pivots(base: str, p: int, rule: str, **options) -> str:
    """(level, segment, inorder_slot, pivot) of all levels."""
    rows = [f"SELECT {i} AS level, CAST(s AS INTEGER) AS segment, CAST((2 * s + 1) * {p >> (i + 1)} AS INTEGER) AS inorder_slot, piv AS pivot FROM pv{i}" for i in range(p.bit_length() - 1)]
    return chain(base, p, rule, **options) + "\n" + " UNION ALL ".join(rows)


def last(p: int) -> str:
    """The name of the rows after all levels."""
    return f"s{p.bit_length() - 1}"


def moved(p: int, exchange_levels: int, r: str = "r", s: str = "s") -> str:
    """How often a row moves from rank r to segment s."""
    rest = (p.bit_length() - 1) - exchange_levels
    wrong = f"xor(CAST({r} AS BIGINT), CAST({s} AS BIGINT))"
    return f"bit_count({wrong} >> {rest}) + CASE WHEN ({wrong} & {(1 << rest) - 1}) <> 0 THEN 1 ELSE 0 END"
