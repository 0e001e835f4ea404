"""DuckDB SQL that rebuilds hashes, sketches and estimates, to hold the engine's results against."""

from __future__ import annotations

MASK = (1 << 32) - 1
#: Multipliers and rotations of the 32-bit Murmur3 hash, which Spark's hash() uses with seed 42.
C1, C2, ADD, F1, F2 = 0xCC9E2D51, 0x1B873593, 0xE6546B64, 0x85EBCA6B, 0xC2B2AE35
SEED = 42


def _rotl(x: int, r: int) -> int:
    return (x << r | x >> 32 - r) & MASK


def murmur_int(i: int, seed: int = SEED) -> int:
    """Spark's hash of a 4-byte integer, unsigned."""
    k = _rotl((i & MASK) * C1 & MASK, 15) * C2 & MASK
    h = _rotl(seed ^ k, 13) * 5 + ADD & MASK
    h ^= 4
    h = (h ^ h >> 16) * F1 & MASK
    h = (h ^ h >> 13) * F2 & MASK
    return h ^ h >> 16


def murmur_ctes(keys: str, members: range, out: str = "hv") -> str:
    """CTEs that end in out(item_key, i, h): Spark's hash(i, item_key) for the keys of a CTE, keys not negative."""
    seeds = ", ".join(f"({i}, {murmur_int(i)}::UBIGINT)" for i in members)
    steps = [f"{out}_seeds(i, h) AS (VALUES {seeds})"]
    steps.append(f"{out}_0 AS (SELECT item_key, i, h, (item_key & {MASK})::UBIGINT AS lo, ((item_key >> 32) & {MASK})::UBIGINT AS hi FROM {keys} CROSS JOIN {out}_seeds)")
    n = 0

    def step(h: str, k: str = "k") -> None:
        nonlocal n
        steps.append(f"{out}_{n + 1} AS (SELECT item_key, i, lo, hi, {h} AS h, {k} AS k FROM {out}_{n})")
        n += 1

    for part in ("lo", "hi"):
        step("h", f"({part} * {C1}) & {MASK}")
        step("h", f"((k << 15) | (k >> 17)) & {MASK}")
        step(f"xor(h, (k * {C2}) & {MASK})")
        step(f"((((h << 13) | (h >> 19)) & {MASK}) * 5 + {ADD}) & {MASK}")
    step("xor(h, 8::UBIGINT)")
    step(f"(xor(h, h >> 16) * {F1}) & {MASK}")
    step(f"(xor(h, h >> 13) * {F2}) & {MASK}")
    step("xor(h, h >> 16)")
    steps.append(f"{out} AS (SELECT item_key, i, CASE WHEN h >= 2147483648 THEN h::BIGINT - 4294967296 ELSE h::BIGINT END AS h FROM {out}_{n})")
    return ",\n".join(steps)


def pmod(x: str, m: str) -> str:
    return f"((({x}) % ({m})) + ({m})) % ({m})"


def fingerprint(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 15))::BIGINT"


def sketch_ctes(items: str, *, overestimate: float = 8, depth: int = 5, cells: int = 512, mode: str = "aligned", seed_base: int = 0, queries: str | None = None, n: str | None = None) -> str:
    """CTEs for the sketches of items, a SELECT of item_key and weight.

    items, counts(item_key, true_count), cfg(n, c, k, cols), asked(item_key), hv, pg(item_key, page, w), pcells, fcells, pprobe, fprobe, pest, fest.
    """
    cols = cells // depth
    width = f"ceil(exp(1.0) / ({overestimate}.0 / n))::BIGINT"
    pages = f"ceil(ceil(exp(1.0) / ({overestimate}.0 / n)) / {cols})::BIGINT" if mode == "aligned" else f"ceil(ceil(exp(1.0) / ({overestimate}.0 / n)) * {depth} / {cells})::BIGINT"
    wide = str(cols) if mode == "aligned" else f"((page + 1) * {cells} // {depth} - page * {cells} // {depth})"
    asked = queries or "SELECT item_key FROM counts"
    return f"""items AS ({items}),
counts AS (SELECT item_key, sum(weight)::BIGINT AS true_count FROM items WHERE item_key IS NOT NULL GROUP BY 1),
cfg AS (SELECT n, {width} AS c, {pages} AS k FROM (SELECT {n or "sum(true_count)::BIGINT"} AS n FROM counts)),
asked AS ({asked}),
all_keys AS (SELECT item_key FROM counts UNION SELECT item_key FROM asked),
{murmur_ctes("all_keys", range(seed_base, seed_base + depth + 1))},
pg AS (SELECT item_key, page, {wide} AS w FROM (SELECT item_key, {pmod("h", "k")} AS page FROM hv CROSS JOIN cfg WHERE i = {seed_base})),
pprobe AS (SELECT pg.item_key, page, (i - 1 - {seed_base})::INT AS row, {pmod("h", "w")} AS col FROM pg JOIN hv USING (item_key) WHERE i > {seed_base}),
pcells AS (SELECT page, row, col, sum(true_count)::BIGINT AS cnt FROM pprobe JOIN counts USING (item_key) GROUP BY ALL),
fprobe AS (SELECT item_key, (i - 1 - {seed_base})::INT AS row, {pmod("h", "c")} AS col FROM hv CROSS JOIN cfg WHERE i > {seed_base}),
fcells AS (SELECT row, col, sum(true_count)::BIGINT AS cnt FROM fprobe JOIN counts USING (item_key) GROUP BY ALL),
pread AS (SELECT item_key, page, row, col, coalesce(cnt, 0) AS cnt FROM asked JOIN pprobe USING (item_key) LEFT JOIN pcells USING (page, row, col)),
fread AS (SELECT item_key, row, col, coalesce(cnt, 0) AS cnt FROM asked JOIN fprobe USING (item_key) LEFT JOIN fcells USING (row, col)),
pest AS (SELECT item_key, min(cnt)::BIGINT AS est FROM pread GROUP BY 1),
fest AS (SELECT item_key, min(cnt)::BIGINT AS est FROM fread GROUP BY 1),
pover AS (SELECT item_key, true_count, est, est - true_count AS over FROM counts JOIN pest USING (item_key)),
fover AS (SELECT item_key, true_count, est, est - true_count AS over FROM counts JOIN fest USING (item_key))"""


SUMMARY = """count(*)::BIGINT AS items, sum(true_count)::BIGINT AS n, max(over)::BIGINT AS max_over,
round(sum(over * true_count)::DOUBLE / sum(true_count)::DOUBLE, 6) AS avg_per_element, round(sum(over)::DOUBLE / count(*), 6) AS avg_per_item,
count(*) FILTER (over < 0)::BIGINT AS undershoots"""
