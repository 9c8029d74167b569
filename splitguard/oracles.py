"""DuckDB twins: SQL text that computes rasters, transforms and hashes anew.

Sums run in DOUBLE lists, exact below 2 ** 53; every step is materialised once.
"""

from __future__ import annotations

from splitguard.functions.dct import ALL_OPS, BASIS, PAPER_OPS, orientation_tables, pixel_source

SPLITS = ("train", "val", "test")


def listed(values) -> str:
    return "[" + ", ".join(str(int(v)) for v in values) + "]"


def split_case(key: str) -> str:
    return f"CASE WHEN {key} % 20 < 14 THEN 'train' WHEN {key} % 20 < 17 THEN 'val' ELSE 'test' END"


def _octets(text: str) -> str:
    return f"list_transform(regexp_extract_all(hex(encode({text})), '..'), lambda h: ('0x' || h)::BIGINT)"


def _scan(table: str, key: str, text: str) -> str:
    """(image_id, g): 1,024 cells of a text."""
    cells = " + ".join(
        f"coalesce(b[((2 * (k // 32) + {dy}) * 64 + 2 * (k % 32) + {dx}) * len(b) // 4096 + 1], 0)"
        for dy in (0, 1)
        for dx in (0, 1)
    )
    octets = f"(SELECT {key} AS image_id, {_octets(text)} AS b FROM {table})"
    # Byte i of n over 4,096 falls on pixel ((i + 1) * 4096 - 1) // n; pixels are means, cells sums of four.
    return f"""SELECT image_id, list_transform(range(1024), lambda k: {cells}) AS g
    FROM {octets} WHERE coalesce(len(b), 0) <= 4096
    UNION ALL SELECT image_id, list(v ORDER BY cell) AS g FROM (
        SELECT image_id, (px // 128) * 32 + (px % 64) // 2 AS cell, sum(mean)::BIGINT AS v FROM (
            SELECT image_id, ((i + 1) * 4096 - 1) // n AS px, sum(x)::BIGINT // count(*) AS mean FROM (
                SELECT image_id, len(b) AS n, unnest(b) AS x, unnest(range(len(b))) AS i FROM {octets} WHERE len(b) > 4096)
            GROUP BY ALL) GROUP BY ALL) GROUP BY image_id"""


def _grid(table: str, key: str, row: str, col: str, value: str) -> str:
    return f"""SELECT image_id, list_transform(range(1024), lambda k: coalesce(m[k], 0)::BIGINT) AS g
    FROM (SELECT image_id, map_from_entries(list((cell, v))) AS m FROM (
        SELECT {key} AS image_id, (({row}) * 32 + {col})::BIGINT AS cell, sum({value})::INTEGER AS v
        FROM {table} GROUP BY ALL) GROUP BY image_id)"""


RASTERS = {
    "documents": _scan("documents", "doc_id", "text"),
    "pages": _scan("pages", "page_id", "html"),
    "part": _scan("part", "p_partkey", "p_name || '|' || p_type"),
    "conversations": _scan("conversations", "conv_id * 1000 + turn", "text"),
    "benchmark": _scan("benchmark", "item_id", "text"),
    "embeddings": """SELECT vec_id AS image_id, list_transform(range(1024), lambda k:
        greatest(0, least(255, floor(embedding[(k // 128) * 8 + (k % 32) // 4 + 1]::DOUBLE * 255 + 127.5)))::BIGINT) AS g
    FROM embeddings""",
    "bigram": f"""SELECT image_id, list_transform(range(1024), lambda k: coalesce(m[k], 0)::BIGINT) AS g
    FROM (SELECT image_id, map_from_entries(list((cell, n * 4096 // pairs))) AS m FROM (
        SELECT image_id, (x // 8) * 32 + y // 8 AS cell, count(*) AS n, any_value(pairs) AS pairs FROM (
            SELECT image_id, unnest(b[1 : len(b) - 1]) AS x, unnest(b[2 : len(b)]) AS y, len(b) - 1 AS pairs
            FROM (SELECT doc_id AS image_id, {_octets("text")} AS b FROM documents) WHERE len(b) > 1)
        GROUP BY image_id, cell) GROUP BY image_id)
    UNION ALL SELECT doc_id, list_transform(range(1024), lambda k: 0::BIGINT)
    FROM documents WHERE octet_length(encode(text)) < 2""",
    "activity": _grid("events", "user_id", "day(ts) - 1", "hour(ts)", "1"),
    "ledger": _grid("lineitem", "l_suppkey", "month(l_shipdate) - 1", "day(l_shipdate) - 1", "l_quantity"),
}


def raster_cte(name: str) -> str:
    return f"ras AS MATERIALIZED (SELECT image_id, {split_case('image_id')} AS split, g FROM ({RASTERS[name]}))"


def block_ctes(source: str = "ras", out: str = "blk", side: int = 8) -> str:
    """out(image_id, split, b): side * side coefficients of source(image_id, split, g)."""
    across = ", ".join(
        f"list_transform(range(32), lambda y: list_dot_product(g[32 * y + 1 : 32 * y + 32], "
        f"{listed(BASIS[v])}::DOUBLE[])) AS t{v}"
        for v in range(side)
    )
    down = ", ".join(
        f"list_dot_product({listed(BASIS[u])}::DOUBLE[], t{v})" for u in range(side) for v in range(side)
    )
    return f"""{out}_g AS MATERIALIZED (SELECT image_id, split, g::DOUBLE[] AS g FROM {source}),
{out}_t AS MATERIALIZED (SELECT image_id, split, {across} FROM {out}_g),
{out} AS MATERIALIZED (SELECT image_id, split, [{down}]::BIGINT[] AS b FROM {out}_t)"""


def _bit_sum(test: str, low: int, high: int) -> str:
    """Signed long of bits low..high of a test over t, the value at bit p."""
    weights = [1 << p if p < 63 else None for p in range(high - low)]
    words = ", ".join("-9223372036854775807 - 1" if w is None else str(w) for w in weights)
    return f"""list_sum(list_transform(range(1, {high - low + 1}), lambda p:
        CASE WHEN {test} THEN ([{words}]::BIGINT[])[p] ELSE 0 END))::BIGINT"""


def hash_of(block: str, threshold: str, low: int = 0, high: int = 64) -> str:
    """Expression: bits low..high of the hash of a block, as a signed long."""
    t = f"{block}[p + {low}]"
    count = f"len({block})"
    ac = f"p + {low} > 1 AND " if low == 0 else ""
    total = f"list_sum({block})::BIGINT"
    tests = {
        "mean_all": f"{count} * {t} > {total}",
        "mean_ac": f"{ac}({count} - 1) * {t} > {total} - {block}[1]",
        "median_all": f"2 * {t} > list_sort({block})[{count} // 2] + list_sort({block})[{count} // 2 + 1]",
        "sign_ac": f"{ac}{t} > 0",
    }
    return _bit_sum(tests[threshold], low, high)


def version_ctes(
    threshold: str, ops=("id",), block: str = "blk", out: str = "v"
) -> str:
    """out(image_id, split, nth, op, hash), one row an image and operation."""
    parts = []
    for nth, op in enumerate(ops):
        source, sign = orientation_tables(op)
        turned = ", ".join(f"{int(s)} * b[{int(i) + 1}]" for i, s in zip(source, sign))
        parts.append(f"SELECT image_id, split, {nth} AS nth, '{op}' AS op, [{turned}]::BIGINT[] AS o FROM {block}")
    union = " UNION ALL ".join(parts)
    return f"""{out}_o AS MATERIALIZED ({union}),
{out} AS MATERIALIZED (SELECT image_id, split, nth, op, {hash_of('o', threshold)} AS hash FROM {out}_o)"""


def hashed(name: str, threshold: str = "mean_ac", ops=("id",)) -> str:
    """CTEs up to v(image_id, split, nth, op, hash)."""
    return f"{raster_cte(name)},\n{block_ctes()},\n{version_ctes(threshold, ops)}"


def ahash_cte(source: str = "ras", out: str = "ah") -> str:
    """out(image_id, split, hash) of average hashes."""
    cell = " + ".join(f"g[((c // 8) * 4 + {dy}) * 32 + (c % 8) * 4 + {dx} + 1]" for dy in range(4) for dx in range(4))
    return f"""{out}_c AS MATERIALIZED (SELECT image_id, split,
    list_transform(range(64), lambda c: {cell}) AS o FROM {source}),
{out} AS MATERIALIZED (SELECT image_id, split, {_bit_sum('64 * o[p] > list_sum(o)::BIGINT', 0, 64)} AS hash FROM {out}_c)"""


def kept_cte(versions: str = "v", out: str = "kept") -> str:
    """out(image_id, split) of first-seen de-duplication inside each split."""
    return f"""{out}_own AS (SELECT split, hash, min(image_id) AS owner FROM {versions} GROUP BY ALL),
{out} AS MATERIALIZED (SELECT image_id, split FROM {versions} JOIN {out}_own USING (split, hash)
    GROUP BY ALL HAVING min(owner) = image_id)"""


def matrix(versions: str, target: str, mode: str, augmented: bool, pairs=None) -> str:
    """Rows (search, target, mode, n_search, n_hits, overlap_pct) over ordered pairs of splits."""
    rows = []
    for s in SPLITS:
        for t in SPLITS:
            if s == t and augmented:
                rows.append(f"""SELECT '{s}' AS search, '{t}' AS target, count(DISTINCT image_id) AS n_search,
    count(DISTINCT image_id) - (SELECT count(*) FROM kept WHERE split = '{s}') AS n_hits
    FROM {versions} WHERE split = '{s}'""")
            elif s == t:
                rows.append(f"""SELECT '{s}' AS search, '{t}' AS target, count(*) AS n_search,
    count(*) - count(DISTINCT hash) AS n_hits FROM {versions} WHERE split = '{s}'""")
            else:
                rows.append(f"""SELECT '{s}' AS search, '{t}' AS target, count(*) AS n_search,
    count(*) FILTER (hash IN (SELECT hash FROM {target} WHERE split = '{t}')) AS n_hits
    FROM {versions} WHERE split = '{s}'""")
    union = "\nUNION ALL ".join(rows)
    return f"""SELECT search, target, '{mode}' AS mode, n_search::BIGINT AS n_search, n_hits::BIGINT AS n_hits,
    CASE WHEN n_search > 0 THEN 100.0::DOUBLE * n_hits / n_search END AS overlap_pct FROM ({union})"""


def with_(ctes: str, body: str) -> str:
    return f"WITH {ctes}\n{body}"


def oriented_pixels(op: str) -> str:
    return f"list_transform({listed(pixel_source(op))}, lambda i: g[i + 1])"


__all__ = [
    "ALL_OPS", "PAPER_OPS", "RASTERS", "SPLITS", "ahash_cte", "block_ctes", "hash_of", "hashed", "kept_cte",
    "listed", "matrix", "oriented_pixels", "raster_cte", "split_case", "version_ctes", "with_",
]
