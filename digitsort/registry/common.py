"""DuckDB SQL for the workloads' keys."""

TIES = "l_orderkey, l_partkey, l_suppkey, l_linenumber"
SEED = f"concat_ws(':', {TIES})"


def mix(x: str) -> str:
    return f"((('0x' || substr(md5({x}), 1, 8))::BIGINT - 2147483648) * 4294967296 + ('0x' || substr(md5({x}), 9, 8))::BIGINT)"


def unit(x: str) -> str:
    return f"((('0x' || substr(md5({x}), 1, 8))::BIGINT::DOUBLE + 0.5) / 4294967296.0::DOUBLE)"


def zipf(x: str, universe: int = 1024) -> str:
    u = unit(x)
    return f"floor({universe}.0::DOUBLE * ({u} * {u}) * ({u} * {u}))::BIGINT"


UNIFORM = f"(SELECT {mix(SEED)} AS key, l_partkey AS payload, {TIES} FROM lineitem)"
ZIPF = f"(SELECT {zipf(SEED)} AS key, l_partkey AS payload, {TIES} FROM lineitem)"
ZIPF_WIDE = f"(SELECT {zipf(SEED, 1 << 20)} AS key, l_partkey AS payload, {TIES} FROM lineitem)"
SCATTER = f"(SELECT {mix(f'({zipf(SEED)})::VARCHAR')} AS key, l_partkey AS payload, {TIES} FROM lineitem)"
ZIPF_EXACT = f"(WITH w AS (SELECT k, pow(k + 1.0::DOUBLE, -0.75::DOUBLE) AS w FROM (SELECT unnest(range(0, 256)) AS k)), s AS (SELECT k, coalesce(sum(w) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) / (SELECT sum(w) FROM w) AS low FROM w) SELECT k AS key, l_partkey AS payload, {TIES} FROM (SELECT *, {unit(SEED)} AS u FROM lineitem) ASOF JOIN s ON u >= low)"
KEY16 = f"(SELECT l_orderkey AS key_high, l_partkey AS key_low, l_suppkey AS payload, {TIES} FROM lineitem)"


def record(size: int) -> str:
    data = ["l_partkey AS data1", "l_suppkey AS data2", "l_extendedprice AS data3"][: size // 8 - 1]
    return f"(SELECT {', '.join([mix(SEED) + ' AS key', *data])}, {TIES} FROM lineitem)"


def ranked(source: str, order: str, columns: str = "*") -> str:
    return f"SELECT {columns}, row_number() OVER (ORDER BY {order}) - 1 AS pos FROM {source}"


def floor_key(key: str, level: int) -> str:
    return f"({key} & ({-1 << (64 - 8 * level)}))" if level < 8 else key


def digit(key: str, position: int, bits: int = 8) -> str:
    return f"((({key})::HUGEINT + 9223372036854775808::HUGEINT) // {1 << (bits * position)}::HUGEINT % {1 << bits})::BIGINT"


def decisions(source: str, workers: int = 16, tiny: int = 384, small: int = 32, narrow: int | None = 16, heavy: bool = True, queue_div: int = 4096) -> str:
    """CTEs c1..c8 (counts), d1..d8 (decisions) and ``bins``."""
    parts = [f"src AS (SELECT * FROM {source})", "tot AS (SELECT count(*) AS total FROM src)"]
    for level in range(1, 9):
        parts.append(f"c{level} AS (SELECT {floor_key('key', level)} AS lo, count(*) AS n FROM src GROUP BY 1)")
    tiny_test = "false" if not tiny else (f"n < {tiny}" if narrow is None else f"CASE WHEN parent_n > {narrow} * n THEN n <= {small} ELSE n < {tiny} END")
    for level in range(1, 9):
        made = "SELECT lo, n, total AS parent_n, true AS by_team, total FROM c1, tot" if level == 1 else f"SELECT c.lo, c.n, u.n AS parent_n, u.action = 'heavy' AS by_team, total FROM c{level} c JOIN d{level - 1} u ON {floor_key('c.lo', level - 1)} = u.lo AND u.action NOT IN ('tiny', 'done'), tot"
        heavy_test = f"n * {3 * workers} > total * 2" if heavy else "false"
        action = "'done'" if level == 8 else f"CASE WHEN by_team AND {heavy_test} THEN 'heavy' WHEN by_team THEN 'light' WHEN {tiny_test} THEN 'tiny' WHEN n * {queue_div} < total THEN 'recursed' ELSE 'queued' END"
        parts.append(f"d{level} AS (SELECT {level} AS level, lo, n, parent_n, CASE WHEN by_team THEN 'team' ELSE 'worker' END AS side, {action} AS action FROM ({made}))")
    parts.append("bins AS (" + " UNION ALL ".join(f"SELECT * FROM d{level}" for level in range(1, 9)) + ")")
    return "WITH " + ",\n".join(parts)
