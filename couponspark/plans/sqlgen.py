"""DuckDB SQL for the sketch operators under the portable profile, built from parts: the twins of ``operators``."""

from __future__ import annotations

from collections.abc import Sequence

from couponspark.functions import solvers as S
from couponspark.functions.hashing import PORTABLE_COLUMNS as J

By = Sequence[str]


def names(*groups: By) -> str:
    """Column names followed by a comma, or nothing."""
    flat = [c for g in groups for c in g]
    return ", ".join(flat) + (", " if flat else "")


def group(by: By) -> str:
    return f" GROUP BY {', '.join(by)}" if by else ""


def doubles(values: Sequence[float]) -> str:
    return "[" + ", ".join(f"{v!r}::DOUBLE" for v in values) + "]"


def rendered(*cols: str) -> str:
    """The text that is hashed for an id of several columns."""
    return f"concat_ws('|', {', '.join(cols)})" if len(cols) > 1 else f"{cols[0]}::VARCHAR"


def source(table: str, ids: Sequence[str], by: By = (), extra: By = (), where: str = "TRUE") -> str:
    present = " AND ".join(f"{c} IS NOT NULL" for c in ids)
    return f"SELECT {names(by, extra)}{rendered(*ids)} AS id FROM {table} WHERE {where} AND {present}"


def coupon_rows(src: str, by: By = (), k: int = 1024, extra: By = ()) -> str:
    return f"SELECT {names(by, extra)}(lo & {k - 1})::INTEGER AS row_id, (CASE WHEN hi = 0 THEN {J} ELSE {J} - length(bin(hi)) END)::INTEGER AS col_id FROM (SELECT {names(by, extra)}('0x' || substr(md5(id), 1, 15))::BIGINT AS hi, ('0x' || substr(md5(id), 18, 15))::BIGINT AS lo FROM ({src}))"


def coupons(src: str, by: By = (), k: int = 1024) -> str:
    return f"SELECT DISTINCT * FROM ({coupon_rows(src, by, k)})"


def words(src: str, by: By = (), k: int = 1024) -> str:
    return f"SELECT {names(by)}row_id, bit_or(1::BIGINT << (col_id - 1)) AS word FROM ({coupon_rows(src, by, k)}) GROUP BY {names(by)}row_id"


def collected(words_sql: str, by: By = ()) -> str:
    return f"SELECT {names(by)}coalesce(sum(bit_count(word)), 0)::BIGINT AS coupons FROM ({words_sql}){group(by)}"


def occupancy(words_sql: str, by: By = ()) -> str:
    sums = ", ".join(f"coalesce(sum((word >> {j}) & 1), 0)::BIGINT" for j in range(J))
    return f"SELECT {names(by)}coalesce(sum(bit_count(word)), 0)::BIGINT AS coupons, [{sums}] AS occ FROM ({words_sql}){group(by)}"


def bisect(src: str, carry: By, less: str, k: int) -> str:
    """``carry`` columns of ``src`` and m: 60 halvings of [0, log2 k + 62]; ``less`` says that pow(2, mid) is too small."""
    c = names(carry)
    return f"""WITH RECURSIVE start AS ({src}), b AS (
  SELECT {c}0::DOUBLE AS lo, {S.top_of(k)}::DOUBLE AS hi, 0 AS i FROM start
  UNION ALL
  SELECT {c}CASE WHEN less THEN mid ELSE lo END, CASE WHEN less THEN hi ELSE mid END, i + 1 FROM (SELECT *, {less} AS less FROM (SELECT *, pow(2, mid) AS m FROM (SELECT *, (lo + hi) / 2 AS mid FROM b WHERE i < {S.STEPS}))))
SELECT {c}pow(2, (lo + hi) / 2) AS m FROM b WHERE i = {S.STEPS}"""


def expected(m: str, k: int, poisson: bool = False) -> str:
    rates = [-p for p in S.masses(k, J)] if poisson else S.log_rest(k, J)
    return f"({k} * list_sum(list_transform({doubles(rates)}, lambda l: 1 - exp({m} * l))))"


def count_inverse(counts: str, by: By = (), k: int = 1024, poisson: bool = False, digits: int = 2) -> str:
    found = bisect(counts, [*by, "coupons"], f"{expected('m', k, poisson)} < coupons", k)
    return f"SELECT {names(by)}coupons, round(CASE WHEN coupons = 0 THEN 0 ELSE m END, {digits}) AS estimate FROM ({found})"


def code_length(occ: str, by: By = (), k: int = 1024, digits: int = 2) -> str:
    ls = doubles(S.log_rest(k, J))
    slope = f"list_sum(list_transform(range(1, {J + 1}), lambda j: ({ls})[j] * (({k} - occ[j]) - CASE WHEN occ[j] = 0 THEN 0 ELSE occ[j] / (exp(-m * ({ls})[j]) - 1) END))) > 0"
    return f"SELECT {names(by)}coupons, round(CASE WHEN coupons = 0 THEN 0 ELSE m END, {digits}) AS estimate FROM ({bisect(occ, [*by, 'coupons', 'occ'], slope, k)})"


def registers(words_sql: str, by: By = ()) -> str:
    return f"SELECT {names(by)}row_id, length(bin(word))::INTEGER AS reg FROM ({words_sql})"


def register(regs: str, by: By = (), k: int = 1024, digits: int = 4) -> str:
    raw = f"({S.register_alpha(k)!r}::DOUBLE * {k * k} / s)"
    return f"SELECT {names(by)}round(CASE WHEN empty = {k} THEN 0 WHEN {raw} <= {2.5 * k} AND empty > 0 THEN {k} * ln({float(k)} / greatest(empty, 1)) ELSE {raw} END, {digits}) AS estimate FROM (SELECT {names(by)}coalesce(sum(pow(2, -reg)), 0) + {k} - count(*) AS s, {k} - count(*) AS empty FROM ({regs}){group(by)})"


def register_code_length(regs: str, by: By = (), k: int = 1024, digits: int = 2) -> str:
    ls = S.log_rest(k, J)
    later, own = doubles([sum(ls[j:]) for j in range(J + 1)]), doubles([0.0, *ls])
    hist = ", ".join([f"({k} - count(*))::BIGINT", *(f"count(*) FILTER (WHERE reg = {v})" for v in range(1, J + 1))])
    slope = f"list_sum(list_transform(range(1, {J + 2}), lambda v: CASE WHEN hist[v] = 0 THEN 0 ELSE hist[v] * (({later})[v] - CASE WHEN v = 1 THEN 0 ELSE ({own})[v] / (exp(-m * ({own})[v]) - 1) END) END)) > 0"
    src = f"SELECT {names(by)}[{hist}] AS hist FROM ({regs}){group(by)}"
    return f"SELECT {names(by)}round(CASE WHEN hist[1] = {k} THEN 0 ELSE m END, {digits}) AS estimate FROM ({bisect(src, [*by, 'hist'], slope, k)})"


def arrivals(src: str, pos: str, by: By = (), k: int = 1024) -> str:
    """``src`` gives the column ``pos``."""
    return f"SELECT {names(by)}row_id, col_id, min({pos}) AS first_pos FROM ({coupon_rows(src, by, k, [pos])}) GROUP BY {names(by)}row_id, col_id"


def partition(by: By, *more: str) -> str:
    cols = [*by, *more]
    return f"PARTITION BY {', '.join(cols)} " if cols else ""


def history_steps(arr: str, by: By = (), k: int = 1024) -> str:
    total = k << (J - 1)
    return f"SELECT *, {float(total)!r} / ({total}::HUGEINT - coalesce(sum(1::HUGEINT << ({J - 1} - least(col_id, {J - 1}))) OVER ({partition(by)}ORDER BY first_pos, row_id, col_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::DOUBLE AS step FROM ({arr})"


def history(arr: str, by: By = (), k: int = 1024, digits: int = 4) -> str:
    return f"SELECT {names(by)}count(*) AS coupons, round(sum(step), {digits}) AS estimate FROM ({history_steps(arr, by, k)}){group(by)}"


def register_history_steps(arr: str, by: By = (), k: int = 1024) -> str:
    total = k << J
    raised = f"SELECT * FROM (SELECT *, coalesce(max(col_id) OVER ({partition(by, 'row_id')}ORDER BY first_pos, col_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS old FROM ({arr})) WHERE col_id > old"
    loss = f"((1::HUGEINT << ({J} - old)) - (1::HUGEINT << ({J} - col_id)))"
    return f"SELECT *, {float(total)!r} / ({total}::HUGEINT - coalesce(sum({loss}) OVER ({partition(by)}ORDER BY first_pos, row_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::DOUBLE AS step FROM ({raised})"


def register_history(arr: str, by: By = (), k: int = 1024, digits: int = 4) -> str:
    return f"SELECT {names(by)}round(sum(step), {digits}) AS estimate FROM ({register_history_steps(arr, by, k)}){group(by)}"


def hybrid_history(arr: str, by: By = (), k: int = 1024, switch: float = 0.1, digits: int = 4) -> str:
    early = f"SELECT *, sum(step) OVER ({partition(by)}ORDER BY first_pos, row_id, col_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - step < {switch * k!r} AS early FROM ({history_steps(arr, by, k)})"
    key = ", ".join([*by, "row_id", "col_id"])
    return f"SELECT {names(by)}round(sum(CASE WHEN early THEN a.step ELSE coalesce(b.rstep, 0) END), {digits}) AS estimate, sum(early::INTEGER)::BIGINT AS matrix_coupons FROM ({early}) a LEFT JOIN (SELECT {key}, step AS rstep FROM ({register_history_steps(arr, by, k)})) b USING ({key}){group(by)}"


def leftmost_gap(words_sql: str, by: By = (), k: int = 1024, digits: int = 4) -> str:
    return f"SELECT {names(by)}round({k / S.GAP_CONSTANT!r} * pow(2, sum(bit_count(word & ~(word + 1))) / {float(k)}), {digits}) AS estimate FROM ({words_sql}){group(by)}"


def harmonic(coupons_: str, cells: int) -> str:
    """cells * (H(cells) - H(cells - c))."""
    return f"CASE WHEN {coupons_} = 0 THEN 0 WHEN {coupons_} < {cells} THEN {cells} * list_sum(list_transform(range(1, {coupons_}::BIGINT + 1), lambda i: 1.0::DOUBLE / ({cells + 1} - i))) END"
