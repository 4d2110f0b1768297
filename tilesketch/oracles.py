"""DuckDB SQL written from the definitions: matrices, pools, and selections unrolled for a few picks."""

from __future__ import annotations

from tilesketch.functions.hashing import Family

_TERMS = r"string_split_regex(lower(text), '[^\p{L}]+')"
PAIRS = {
    "order_brand": "SELECT DISTINCT l_orderkey AS row_id, p_brand AS item FROM lineitem JOIN part ON l_partkey = p_partkey",
    "cust_typesize": "SELECT DISTINCT o_custkey AS row_id, p_type || '/' || p_size AS item FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey",
    "embed_high": "SELECT DISTINCT vec_id AS row_id, CAST(i - 1 AS VARCHAR) AS item FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE x > 0.125",
    "doc_term_mid": f"SELECT row_id, item FROM (SELECT DISTINCT doc_id AS row_id, unnest({_TERMS}) AS item FROM documents) t WHERE item <> '' AND item IN (SELECT item FROM (SELECT DISTINCT doc_id, unnest({_TERMS}) AS item FROM documents) GROUP BY item HAVING count(*) BETWEEN 0.05 * (SELECT count(*) FROM documents) AND 0.6 * (SELECT count(*) FROM documents))",
    "doc_term_wide": f"SELECT row_id, item FROM (SELECT DISTINCT doc_id AS row_id, unnest({_TERMS}) AS item FROM documents) t WHERE item <> '' AND item IN (SELECT item FROM (SELECT DISTINCT doc_id, unnest({_TERMS}) AS item FROM documents) GROUP BY item HAVING count(*) BETWEEN greatest(5, 0.01 * (SELECT count(*) FROM documents)) AND 0.6 * (SELECT count(*) FROM documents))",
    "doc_term_all": f"SELECT row_id, item FROM (SELECT DISTINCT doc_id AS row_id, unnest({_TERMS}) AS item FROM documents) t WHERE item <> ''",
    "order_part": "SELECT DISTINCT l_orderkey AS row_id, CAST(l_partkey AS VARCHAR) AS item FROM lineitem",
    "hour_user": "SELECT DISTINCT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS row_id, CAST(user_id AS VARCHAR) AS item FROM events",
    "user_typehour": "SELECT DISTINCT user_id AS row_id, event_type || '/' || hour(ts) AS item FROM events",
    "part_nation": "SELECT DISTINCT l_partkey AS row_id, CAST(s_nationkey AS VARCHAR) AS item FROM lineitem JOIN supplier ON l_suppkey = s_suppkey",
    "page_token": "SELECT DISTINCT page_id AS row_id, unnest(regexp_extract_all(html, '<([a-z0-9]+)', 1)) AS item FROM pages",
    "conv_term": f"SELECT DISTINCT row_id, role || '/' || t AS item FROM (SELECT conv_id AS row_id, role, unnest({_TERMS}) AS t FROM conversations) WHERE t <> ''",
    "bench_shingle": f"SELECT DISTINCT row_id, array_to_string(w[i : i + 4], ' ') AS item FROM (SELECT row_id, w, unnest(range(1, len(w) - 3)) AS i FROM (SELECT item_id AS row_id, list_filter({_TERMS}, lambda x: x <> '') AS w FROM benchmark))",
    "nation_region": "SELECT DISTINCT CAST(n_nationkey AS BIGINT) AS row_id, CAST(n_regionkey AS VARCHAR) AS item FROM nation",
}


def matrix(name: str) -> list[str]:
    """Common table expressions ``pairs, dict, ones, shape``."""
    return [
        f"pairs AS ({PAIRS[name]})",
        "dict AS (SELECT item, row_number() OVER (ORDER BY item) - 1 AS col_id FROM (SELECT DISTINCT item FROM pairs))",
        "ones AS (SELECT row_id, col_id FROM pairs JOIN dict USING (item))",
        "shape AS (SELECT count(DISTINCT row_id) AS n_rows, count(DISTINCT col_id) AS n_cols, count(*) AS n_ones FROM ones)",
    ]


def density(name: str) -> str:
    return f"WITH {', '.join(matrix(name))} SELECT n_rows, n_cols, n_ones, n_ones / (n_rows * n_cols) AS density FROM shape"


def pair_pool(support: float, pairs: bool = True) -> list[str]:
    """``sets, trows, tcols``: frequent columns and pairs of columns."""
    need = f"(SELECT ceil({support} * n_rows - 1e-9) FROM shape)"
    out = [f"freq AS (SELECT col_id, count(*) AS support FROM ones GROUP BY col_id HAVING count(*) >= {need})"]
    two = f" UNION ALL SELECT (a.col_id + 1) * 100000 + b.col_id + 1, a.col_id, b.col_id, count(*) FROM ones a JOIN ones b ON a.row_id = b.row_id AND a.col_id < b.col_id GROUP BY ALL HAVING count(*) >= {need}" if pairs else ""
    out.append(f"sets AS (SELECT col_id + 1 AS tile_id, col_id AS i, NULL AS j, support FROM freq{two})")
    out.append("tcols AS (SELECT tile_id, i AS col_id FROM sets UNION ALL SELECT tile_id, j FROM sets WHERE j IS NOT NULL)")
    out.append("trows AS (SELECT tile_id, row_id FROM sets JOIN ones ON col_id = i WHERE j IS NULL UNION ALL SELECT tile_id, a.row_id FROM sets JOIN ones a ON a.col_id = i JOIN ones b ON b.col_id = j AND a.row_id = b.row_id)")
    return out


def association_pool(tau: float, rule: str = "majority") -> list[str]:
    test = {"majority": "2 * count(*) > n_c", "all": "count(*) = n_c"}[rule] if rule != "item" else None
    out = [
        "sup AS (SELECT col_id, count(*) AS s FROM ones GROUP BY col_id)",
        f"acols AS (SELECT a.col_id AS tile_id, b.col_id AS col_id FROM ones a JOIN ones b USING (row_id) JOIN sup ON sup.col_id = a.col_id GROUP BY a.col_id, b.col_id, s HAVING count(*) / s >= {tau})",
        "width AS (SELECT tile_id, count(*) AS n_c FROM acols GROUP BY tile_id)",
    ]
    out.append(f"trows AS (SELECT tile_id, row_id FROM acols JOIN ones USING (col_id) JOIN width USING (tile_id) GROUP BY tile_id, row_id, n_c HAVING {test})" if test else "trows AS (SELECT tile_id, row_id FROM width JOIN ones ON ones.col_id = tile_id)")
    out.append("tcols AS (SELECT tile_id, col_id FROM acols WHERE tile_id IN (SELECT tile_id FROM trows))")
    return out


CELLS = ["cells AS (SELECT t.tile_id, row_id, t.col_id, CASE WHEN o.row_id IS NULL THEN -1 ELSE 1 END AS w FROM (SELECT tile_id, row_id, col_id FROM trows JOIN tcols USING (tile_id)) t LEFT JOIN ones o USING (row_id, col_id))", "alone AS (SELECT tile_id, sum(w)::BIGINT AS gain, count_if(w = -1) AS zeros, count(*) AS size FROM cells GROUP BY tile_id)"]


def _finish(parts: list[str], picks: int, columns: str) -> str:
    union = " UNION ALL ".join(f"SELECT {i} AS step, * FROM p{i}" for i in range(1, picks + 1))
    return f"WITH {', '.join(parts)}, picks AS ({union}) SELECT CAST(step AS INTEGER) AS step, tile_id, {columns} FROM (SELECT *, (SELECT n_ones FROM shape) - sum(gain) OVER (ORDER BY step) AS error FROM picks) CROSS JOIN shape"


def greedy(head: list[str], picks: int) -> str:
    parts = [*head, *CELLS]
    for i in range(1, picks + 1):
        seen = " AND ".join(["TRUE", *(f"tile_id <> (SELECT tile_id FROM p{j})" for j in range(1, i))])
        cov = " UNION ".join(f"SELECT row_id, col_id FROM cells WHERE tile_id = (SELECT tile_id FROM p{j})" for j in range(1, i)) or "SELECT 0 AS row_id, 0 AS col_id WHERE FALSE"
        parts.append(f"cov{i} AS ({cov})")
        parts.append(f"p{i} AS (SELECT tile_id, sum(w)::BIGINT AS gain FROM cells ANTI JOIN cov{i} USING (row_id, col_id) WHERE {seen} GROUP BY tile_id HAVING sum(w) > 0 ORDER BY gain DESC, tile_id LIMIT 1)")
    return _finish(parts, picks, "gain, error::BIGINT AS error, error / (n_rows * n_cols) AS rel_error")


def static(head: list[str], picks: int, order: str = "gain DESC, tile_id") -> str:
    parts = [*head, *CELLS, f"rank AS (SELECT tile_id, gain, row_number() OVER (ORDER BY {order}) AS step FROM alone ORDER BY {order} LIMIT {picks})", "first AS (SELECT row_id, col_id, min(step) AS step, any_value(w) AS w FROM cells JOIN rank USING (tile_id) GROUP BY row_id, col_id)", "won AS (SELECT step, sum(w) AS g FROM first GROUP BY step)"]
    return f"WITH {', '.join(parts)} SELECT CAST(step AS INTEGER) AS step, tile_id, gain, ((SELECT n_ones FROM shape) - sum(coalesce(g, 0)) OVER (ORDER BY step))::BIGINT AS error, ((SELECT n_ones FROM shape) - sum(coalesce(g, 0)) OVER (ORDER BY step)) / (SELECT n_rows * n_cols FROM shape) AS rel_error FROM rank LEFT JOIN won USING (step)"


def hash_cells(fam: Family) -> str:
    maps = ", ".join(f"({i}, {ar}, {br}, {ac}, {bc})" for i, (ar, br, ac, bc) in enumerate(fam.maps))
    p = fam.prime
    return f"fam(rep, ar, br, ac, bc) AS (VALUES {maps}), hashed AS (SELECT DISTINCT tile_id, rep, ((ar::BIGINT * row_id + br) % {p} - (ac::BIGINT * col_id + bc) % {p} + {p}) % {p} AS h FROM cells CROSS JOIN fam)"


def lists(fam: Family, k: int, cutoff: int | None = None) -> str:
    under = f" WHERE h < {cutoff}" if cutoff is not None else ""
    return f"{hash_cells(fam)}, low AS (SELECT tile_id, rep, h FROM (SELECT *, row_number() OVER (PARTITION BY tile_id, rep ORDER BY h) AS n FROM hashed{under}) WHERE n <= {k})"


def _size(k: int, prime: int) -> str:
    return f"CASE WHEN count(*) < {k} THEN count(*)::DOUBLE ELSE {float(k)}::DOUBLE / ((max(h) + 1) / {float(prime)}::DOUBLE) END"


def union_cells() -> list[str]:
    """``cells`` of patterns that are no outer product: those of a tile and of the next id together."""
    moved = "SELECT tile_id - 1, row_id, col_id, w FROM base WHERE tile_id - 1 IN (SELECT tile_id FROM base)"
    return [CELLS[0].replace("cells AS", "base AS", 1), f"cells AS (SELECT tile_id, row_id, col_id, w FROM base UNION {moved})", CELLS[1]]


def _uniform(*keys: str) -> str:
    return f"(('0x' || substr(md5(concat_ws('|', {', '.join(keys)})), 1, 13))::BIGINT / {float(2**52)}::DOUBLE)"


def planted(n_rows: int, n_cols: int, n_orig: int, copies: int, p: float, move: float, use: str, noise: float, seed: int) -> list[str]:
    """``trows, tcols, ones, shape`` of planted patterns on the first order and part keys."""
    out = [
        f"ids AS (SELECT 'r' AS side, id FROM (SELECT DISTINCT o_orderkey AS id FROM orders ORDER BY 1 LIMIT {n_rows}) UNION ALL SELECT 'c', id FROM (SELECT DISTINCT p_partkey AS id FROM part ORDER BY 1 LIMIT {n_cols}))",
        f"every AS (SELECT side, range AS t, id, {_uniform(repr(str(seed)), 'side', 'range', 'id')} < {p!r}::DOUBLE AS one FROM ids CROSS JOIN range({n_orig}))",
        "n AS (SELECT side, t, count(*) AS n FROM every WHERE one GROUP BY ALL)",
        f"moves AS (SELECT side, t, range AS c, id, one, n, row_number() OVER (PARTITION BY side, t, range, one ORDER BY {_uniform(repr(str(seed)), repr('') + ' || side || ' + repr('m'), 't', 'range', 'id')}, id) AS place FROM every JOIN n USING (side, t) CROSS JOIN range(1, {copies + 1}))",
        f"drawn AS (SELECT side, t AS tile_id, id FROM every WHERE one UNION ALL SELECT side, {n_orig} + t * {copies} + c - 1, id FROM moves WHERE (place <= floor(n * {move}::DOUBLE + 0.5)) <> one)",
        "whole AS (SELECT tile_id FROM drawn GROUP BY tile_id HAVING count(DISTINCT side) = 2)",
        "trows AS (SELECT tile_id, id AS row_id FROM drawn SEMI JOIN whole USING (tile_id) WHERE side = 'r')",
        "tcols AS (SELECT tile_id, id AS col_id FROM drawn SEMI JOIN whole USING (tile_id) WHERE side = 'c')",
        f"clean AS (SELECT DISTINCT row_id, col_id FROM trows JOIN tcols USING (tile_id){f' WHERE tile_id < {n_orig}' if use == 'orig' else ''})",
    ]
    if noise:
        out.append(f"flips AS (SELECT r.id AS row_id, c.id AS col_id FROM ids r, ids c WHERE r.side = 'r' AND c.side = 'c' AND {_uniform(repr(str(seed)), repr('n'), 'r.id', 'c.id')} < {noise}::DOUBLE)")
        out.append("ones AS (SELECT * FROM clean ANTI JOIN flips USING (row_id, col_id) UNION ALL SELECT * FROM flips ANTI JOIN clean USING (row_id, col_id))")
    else:
        out.append("ones AS (SELECT * FROM clean)")
    out.append("shape AS (SELECT count_if(side = 'r') AS n_rows, count_if(side = 'c') AS n_cols, (SELECT count(*) FROM ones) AS n_ones FROM ids)")
    return [x.replace(" AS (", " AS MATERIALIZED (", 1) for x in out]


def hashed(head: list[str], fam: Family, k: int, picks: int, max_checks: int, inexact: bool, tie: str = "alone DESC, ", verify: bool = True, union: bool = True, discard: bool = False, cells: list[str] | None = None) -> str:
    join, distinct = ("UNION", "DISTINCT ") if union else ("UNION ALL", "")
    size = _size(k, fam.prime).replace("count(*)::DOUBLE", "NULL::DOUBLE") if discard else _size(k, fam.prime)
    parts = [*head, *(cells or CELLS), lists(fam, k), "p1 AS (SELECT tile_id, gain, NULL::DOUBLE AS estimate, 1 AS n_checked FROM alone WHERE gain > 0 ORDER BY gain DESC, tile_id LIMIT 1)"]
    for i in range(2, picks + 1):
        ids = ", ".join(f"(SELECT tile_id FROM p{j})" for j in range(1, i))
        parts.append(f"q{i} AS (SELECT rep, h FROM (SELECT rep, h, row_number() OVER (PARTITION BY rep ORDER BY h) AS n FROM (SELECT {distinct}rep, h FROM low WHERE tile_id IN ({ids}))) WHERE n <= {k})")
        both = f"SELECT tile_id, rep, h FROM low WHERE tile_id NOT IN ({ids}) {join} SELECT tile_id, rep, h FROM (SELECT DISTINCT tile_id FROM low WHERE tile_id NOT IN ({ids})) CROSS JOIN q{i}"
        parts.append(f"e{i} AS (SELECT tile_id, rep, {size} AS e FROM (SELECT *, row_number() OVER (PARTITION BY tile_id, rep ORDER BY h) AS n FROM ({both})) WHERE n <= {k} GROUP BY tile_id, rep)")
        parts.append(f"s{i} AS (SELECT tile_id, median(e) - {'any_value(zeros)' if inexact else '0'} AS estimate, any_value(gain) AS alone FROM e{i} JOIN alone USING (tile_id) GROUP BY tile_id{' HAVING median(e) IS NOT NULL' if discard else ''})")
        parts.append(f"r{i} AS (SELECT *, row_number() OVER (ORDER BY estimate DESC, {tie}tile_id) AS place FROM s{i} ORDER BY place LIMIT {max_checks if verify else 1})")
        parts.append(f"p{i} AS (SELECT tile_id, gain, estimate, {'place' if verify else '0'} AS n_checked FROM (SELECT r.tile_id, r.estimate, r.place, coalesce(sum(w) FILTER (WHERE v.row_id IS NULL), 0)::BIGINT AS gain FROM r{i} r JOIN cells c USING (tile_id) LEFT JOIN (SELECT DISTINCT row_id, col_id FROM cells WHERE tile_id IN ({ids})) v USING (row_id, col_id) GROUP BY ALL){' WHERE gain > 0' if verify else ''} ORDER BY place LIMIT 1)")
    return _finish(parts, picks, "estimate, gain, error::BIGINT AS error, error / (n_rows * n_cols) AS rel_error, CAST(n_checked AS INTEGER) AS n_checked")
