"""SQL twins of the queries, for DuckDB on the same tables.

They compute each result from its definition: a merged sketch, for instance, as
the sketch of the summed vector, so that linearity and the tree are tested and
not repeated.
"""

from __future__ import annotations

from treesketch.experiments.queries import D, GRID, K, LEDGER_PPM, RATED, SEED, SMALL_D, SMALL_K, SPEC, STEP, TREE_SIZES, WIDE
from treesketch.functions.cost import METHODS
from treesketch.functions.hashing import PRIME, SketchSpec, sql_fill_order
from treesketch.learning.schedule import WARMUP_DENSITIES_PPM, WARMUP_RATES_PERMILLE
from treesketch.operators.topology import rounds
from treesketch.sources.tables import CLASSES, COMPONENTS

_CENTS = "CAST(floor({0} * 100 + 0.5) AS BIGINT)"


def _parts(workers: int = 4) -> str:
    return f"parts AS (SELECT CAST(l_orderkey % {workers} AS INT) AS worker, l_partkey AS coord, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS val FROM lineitem GROUP BY ALL)"


_PRICES = f"prices AS (SELECT CAST(l_orderkey % 4 AS INT) AS worker, l_partkey AS coord, CAST(sum({_CENTS.format('l_extendedprice')} * CASE WHEN l_returnflag = 'R' THEN -1 ELSE 1 END) AS BIGINT) AS val FROM lineitem GROUP BY ALL)"


def _tokens(workers: int = 5) -> str:
    return (
        f"tokens AS (SELECT CAST(doc_id % {workers} AS INT) AS worker, CAST('0x' || substr(md5(word), 1, 8) AS BIGINT) % {D} AS coord, count(*) AS val "
        "FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-zà-ÿß]+')) AS word FROM documents) WHERE word <> '' GROUP BY ALL)"
    )


def _cells(source: str, name: str = "cells", by: str = "worker", spec: SketchSpec = SPEC, rows: str = "hash_rows") -> str:
    keys = f"{by}, " if by else ""
    term = f"{spec.sql_sign('coord')} * val"
    return f"{name} AS (SELECT {keys}hrow, {spec.sql_bucket('coord')} AS bucket, CAST(sum({term}) AS BIGINT) AS val FROM {source} CROSS JOIN {rows} GROUP BY {keys}hrow, {spec.sql_bucket('coord')} HAVING sum({term}) <> 0)"


def _total(source: str, name: str = "total") -> str:
    return f"{name} AS (SELECT coord, CAST(sum(val) AS BIGINT) AS val FROM {source} GROUP BY coord)"


def _estimates(spec: SketchSpec = SPEC, domain: str = f"(SELECT range AS coord FROM range({D}))", cells: str = "cells") -> str:
    """Median over rows of the signed cells, a missing cell being 0."""
    return (
        f"est AS (SELECT coord, CAST(list_sort(list(v))[{(spec.rows + 1) // 2}] AS BIGINT) AS est FROM ("
        f"SELECT q.coord, coalesce(q.s * c.val, 0) AS v FROM (SELECT coord, hrow, {spec.sql_bucket('coord')} AS bucket, {spec.sql_sign('coord')} AS s FROM {domain} CROSS JOIN hash_rows) q "
        f"LEFT JOIN {cells} c ON c.hrow = q.hrow AND c.bucket = q.bucket) GROUP BY coord)"
    )


def _norm(cells: str = "cells", name: str = "norm") -> str:
    return f"{name} AS (SELECT list_sort(list(s))[{(SPEC.rows + 1) // 2}] AS l2sq FROM (SELECT h.hrow, coalesce(sum(CAST(val AS HUGEINT) * val), 0) AS s FROM hash_rows h LEFT JOIN {cells} c ON c.hrow = h.hrow GROUP BY h.hrow))"


def _with(*parts: str) -> str:
    return "WITH " + ", ".join(parts) + " "


_TOKEN_SPLIT = [SPEC.sql_rows(), _tokens(), _total("tokens"), _cells("total", by=""), _estimates(), _norm(), f"split AS (SELECT coord, est, CAST(est AS HUGEINT) * est * {K} >= l2sq AS heavy FROM est, norm)"]
_FILL = sql_fill_order("coord", SEED, STEP)
_SUPPORT = f"support AS (SELECT * FROM split ORDER BY heavy DESC, CASE WHEN heavy THEN abs(est) END DESC NULLS LAST, CASE WHEN NOT heavy THEN {_FILL} END NULLS LAST, coord LIMIT {K})"
_TOP_EST = f"support AS (SELECT coord, est, true AS heavy FROM est ORDER BY abs(est) DESC, coord LIMIT {K})"
_EXACT = "SELECT s.coord, s.est, s.heavy, coalesce(t.val, 0) AS exact FROM support s LEFT JOIN total t ON t.coord = s.coord"


def _local_top(source: str, name: str) -> str:
    return f"{name} AS (SELECT worker, coord, val FROM (SELECT *, row_number() OVER (PARTITION BY worker ORDER BY abs(val) DESC, coord) AS rn FROM {source} WHERE val <> 0) WHERE rn <= {K})"


def _tree_top(workers: int) -> str:
    parts = [_tokens(workers), _local_top("tokens", "r0")]
    for i in range(1, rounds(workers) + 1):
        parts.append(f"m{i} AS (SELECT worker // 2 AS worker, coord, CAST(sum(val) AS BIGINT) AS val FROM r{i - 1} GROUP BY ALL)")
        parts.append(_local_top(f"m{i}", f"r{i}"))
    return _with(*parts) + f"SELECT coord, val FROM r{rounds(workers)}"


def _merged(workers: int) -> str:
    return _with(SPEC.sql_rows(), _parts(workers), _total("parts"), _cells("total", by="")) + "SELECT * FROM cells"


def _values(name: str, columns: str, rows: list[tuple]) -> str:
    cell = lambda v: f"'{v}'" if isinstance(v, str) else "NULL" if v is None else str(v)
    return f"{name} AS (SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(cell, r)) + ')' for r in rows)}) AS t({columns}))"


def _tree_rows() -> str:
    """Participants of each round by repeated halving, and from them merges and byes."""
    return (
        "RECURSIVE " + _values("sizes", "workers", [(p,) for p in TREE_SIZES]) + ", "
        "halved AS (SELECT workers, 1 AS round, workers AS n FROM sizes WHERE workers > 1 UNION ALL SELECT workers, round + 1, (n + 1) // 2 FROM halved WHERE (n + 1) // 2 > 1), "
        "depth AS (SELECT workers, max(round) AS r FROM halved GROUP BY workers), "
        "seats AS (SELECT h.*, CAST(j AS BIGINT) AS j, CAST(1 AS BIGINT) << (round - 1) AS stride FROM halved h, unnest(range(h.n)) AS t(j))"
    )


_EDGES = (
    "WITH " + _tree_rows() + ", "
    "held AS (SELECT s.workers, l_orderkey % s.workers AS w, count(*) AS n FROM sizes s, lineitem WHERE l_orderkey IS NOT NULL GROUP BY ALL), edges AS ("
    "SELECT workers, 'up' AS direction, round, j * stride AS src, CASE WHEN j % 2 = 1 THEN (j - 1) * stride ELSE j * stride END AS dst, CASE WHEN j % 2 = 1 THEN 'merge' ELSE 'bye' END AS kind "
    "FROM seats WHERE j % 2 = 1 OR (n % 2 = 1 AND j = n - 1) "
    "UNION ALL SELECT s.workers, 'down', d.r + 1 - round, (j - 1) * stride, j * stride, 'copy' FROM seats s JOIN depth d ON d.workers = s.workers WHERE j % 2 = 1) "
    "SELECT e.*, CAST((SELECT coalesce(sum(n), 0) FROM held h WHERE h.workers = e.workers AND (e.direction = 'down' OR (h.w >= e.src AND h.w < e.src + (CAST(1 AS BIGINT) << (e.round - 1))))) AS BIGINT) AS lines FROM edges e"
)

#: Coordinates of the lines' vectors.
_SIZES = "vectors AS (SELECT unnest(['parts', 'suppliers', 'orders']) AS vector, unnest([max(l_partkey) + 1, max(l_suppkey) + 1, max(l_orderkey) + 1]) AS d FROM lineitem)"

# Values of one message by method and phase, for the vector by part. A star talks to all workers at once.
_LEDGER = (
    "WITH " + _tree_rows() + f", {_SIZES}, dims AS (SELECT d, greatest(1, (d * {LEDGER_PPM} + 999999) // 1000000) AS k FROM vectors WHERE vector = 'parts'), "
    f"links AS (SELECT 'dense' AS method, 'dense' AS phase, d AS v FROM dims UNION ALL SELECT 'tree_topk', 'sparse', 2 * k FROM dims UNION ALL SELECT 'tree_sketch', 'sketch', {SPEC.size} FROM dims UNION ALL SELECT 'tree_sketch', 'exact', k FROM dims), "
    f"stars AS (SELECT 'star_topk' AS method, 'sparse' AS phase, 2 * k AS up, 0 AS down_fixed, 2 * k AS down_by_worker FROM dims UNION ALL SELECT 'star_sketch', 'sketch', {SPEC.size}, {SPEC.size}, 0 FROM dims UNION ALL SELECT 'star_sketch', 'exact', k, k, 0 FROM dims)"
    + ", led AS (SELECT workers, method, phase, direction, round, n // 2 AS messages, n // 2 * v AS vals FROM halved, links, (VALUES ('up'), ('down')) AS t(direction) "
    "UNION ALL SELECT workers, method, phase, 'up', 1, workers, workers * up FROM sizes, stars "
    "UNION ALL SELECT workers, method, phase, 'down', 1, workers, workers * (down_fixed + down_by_worker * workers) FROM sizes, stars) "
)


def _grid(of: dict = GRID) -> str:
    one = lambda name, xs: _values(f"g_{name}", name, [(x,) for x in xs])
    base = ", ".join([one("workers", of["workers"]), one("ppm", of["densities_ppm"]), one("alpha", of["alphas"]), _SIZES])
    r = "CAST(CASE WHEN workers <= 1 THEN 0 ELSE ceil(log2(workers)) END AS BIGINT)"
    times = {
        "dense": (f"2 * {r} * (alpha + d)",) * 2,
        "star_topk": ("workers * (alpha + 2 * k) + workers * (alpha + 2 * k * workers)",) * 2,
        "tree_topk": (f"2 * {r} * (alpha + 2 * k)",) * 2,
        "star_sketch": ("2 * workers * (alpha + size) + 2 * workers * (alpha + k)", "2 * workers * (alpha + size)"),
        "tree_sketch": (f"2 * {r} * (alpha + size) + 2 * {r} * (alpha + k)", f"2 * {r} * (alpha + size)"),
    }
    lines = " UNION ALL ".join(f"SELECT *, '{m}' AS method, CAST({times[m][0]} AS BIGINT) AS t, CAST({times[m][1]} AS BIGINT) AS t_paper FROM points" for m in METHODS)
    return (
        f"WITH {base}, points AS (SELECT DISTINCT CAST(workers AS BIGINT) AS workers, CAST(d AS BIGINT) AS d, greatest(1, (CAST(d AS BIGINT) * ppm + 999999) // 1000000) AS k, "
        f"5 * greatest(256, CAST(d AS BIGINT) * 10000 // 1000000) AS size, CAST(alpha AS BIGINT) AS alpha FROM g_workers, vectors, g_ppm, g_alpha), times AS ({lines}) "
    )


def _micro(x: str) -> str:
    return f"CAST(floor(({x}) * 1000000 + 0.5) AS BIGINT)"


def _sketch_sizes() -> str:
    asked = [(p, f) for p in (2, 5, 10) for f in ("inverse_square", "inverse_eps")]
    rows = "CASE WHEN ceil(log2(d / 0.05)) % 2 = 1 THEN ceil(log2(d / 0.05)) ELSE ceil(log2(d / 0.05)) + 1 END"
    return (
        _with(_SIZES, _values("asked", "eps_percent, form", asked))
        + f"SELECT vector, CAST(d AS BIGINT) AS d, eps_percent, form, CAST({rows} AS INT) AS sketch_rows, CAST(CASE WHEN form = 'inverse_eps' THEN ceil(100.0 / eps_percent - 1e-9) ELSE ceil(10000.0 / (eps_percent * eps_percent) - 1e-9) END AS INT) AS width FROM vectors, asked"
    )


def _schedule() -> str:
    n = len(WARMUP_DENSITIES_PPM)
    densities = "CASE epoch " + " ".join(f"WHEN {e} THEN {p}" for e, p in enumerate(WARMUP_DENSITIES_PPM)) + " END"
    rates = "CASE epoch " + " ".join(f"WHEN {e} THEN {p}" for e, p in enumerate(WARMUP_RATES_PERMILLE)) + f" WHEN 3 THEN {WARMUP_RATES_PERMILLE[-1]} ELSE 500 END"
    return f"SELECT epoch, {densities} AS density_ppm, {rates} AS rate_permille, CASE WHEN epoch < {n} THEN greatest(1, (CAST(16384 AS BIGINT) * {densities} + 999999) // 1000000) ELSE 1024 END AS k FROM (SELECT DISTINCT CAST(date_diff('day', (SELECT min(CAST(ts AS DATE)) FROM events), CAST(ts AS DATE)) AS INT) AS epoch FROM events WHERE ts IS NOT NULL)"


def _worker(key: str, workers: int = 4) -> str:
    return f"CAST(({sql_fill_order(f'({key} % {PRIME})', 0, 0)}) % {workers} AS INT)"


_COMPONENT_ROWS = "xs AS (SELECT vec_id AS key, label, i - 1 AS j, CAST(floor(CAST(embedding[i] AS DOUBLE) * 1048576 + 0.5) AS BIGINT) AS x FROM embeddings, unnest(range(1, len(embedding) + 1)) AS t(i))"


def _token_error(spec: SketchSpec) -> str:
    cells = f"cells{spec.width}"
    return (
        f"SELECT * FROM (WITH {spec.sql_rows()}, {_cells('total', cells, '', spec)}, {_estimates(spec, cells=cells)} "
        f"SELECT count(*) AS n, max(e) AS max_error, {_micro('quantile_cont(e, 0.5)')} AS median_error_micro, CAST(sum(v * v) AS BIGINT) AS l2sq, "
        f"{_micro('max(e) / sqrt(CAST(sum(v * v) AS DOUBLE))')} AS max_error_of_norm_micro, {spec.width} AS width "
        "FROM (SELECT abs(coalesce(est, 0) - coalesce(val, 0)) AS e, CAST(coalesce(val, 0) AS HUGEINT) AS v FROM est FULL JOIN total USING (coord)))"
    )


# Where each worker's part gets to when round i pairs the ranks 0, i, 2i, ...: it stays, and from an odd one of them it also goes to the one before.
_STRIDES = (
    "WITH RECURSIVE " + _values("sizes", "workers", [(p,) for p in TREE_SIZES]) + ", "
    "present AS (SELECT DISTINCT workers, l_orderkey % workers AS w FROM sizes, lineitem WHERE l_orderkey IS NOT NULL), "
    "held AS (SELECT workers, 0 AS round, CAST(w AS BIGINT) AS w, CAST(w AS BIGINT) AS place FROM present "
    "UNION SELECT workers, round + 1, w, unnest(CASE WHEN place % (round + 1) = 0 AND (place // (round + 1)) % 2 = 1 THEN [place, place - (round + 1)] ELSE [place] END) "
    "FROM held WHERE round < ceil(log2(workers))) "
    "SELECT workers, CAST(count(DISTINCT w) AS INT) AS covered FROM held WHERE place = 0 AND round = ceil(log2(workers)) GROUP BY workers"
)


def _gradient() -> list[str]:
    one_less = f"CASE WHEN label = c THEN {1 - CLASSES} ELSE 1 END"
    return [
        _COMPONENT_ROWS,
        f"every AS (SELECT {_worker('key')} AS worker, label, j, x FROM xs WHERE label IS NOT NULL UNION ALL SELECT {_worker('vec_id')}, label, {COMPONENTS}, 1048576 FROM embeddings WHERE label IS NOT NULL)",
        f"gradient AS (SELECT worker, c * {COMPONENTS + 1} + j AS coord, CAST(sum(x * {one_less}) AS BIGINT) AS val FROM every, range({CLASSES}) AS t(c) GROUP BY ALL HAVING sum(x * {one_less}) <> 0)",
    ]


def _first_step() -> str:
    """The support and exact values of one step on the gradient at 0, from the sketch of the summed gradient."""
    heavy = f"split AS (SELECT coord, est, CAST(est AS HUGEINT) * est * {SMALL_K} >= l2sq AS heavy FROM est, norm)"
    domain = f"(SELECT range AS coord FROM range({SMALL_D}))"
    return _with(SPEC.sql_rows(), *_gradient(), _total("gradient"), _cells("total", by=""), _estimates(domain=domain), _norm(), heavy, _SUPPORT.replace(f"LIMIT {K}", f"LIMIT {SMALL_K}"))


def oracle_sql() -> dict[str, str]:
    rows = SPEC.sql_rows()
    energy_rank = "row_number() OVER (ORDER BY abs(exact) DESC, coord)"
    recursions = {
        "sketch_merge_tree_p4": _merged(4), "sketch_merge_tree_p5": _merged(5), "sketch_merge_tree_p7": _merged(7), "sketch_merge_tree_p8": _merged(8), "sketch_merge_flat": _merged(4),
    }
    cells = _with(rows, _parts(), _cells("parts")) + "SELECT * FROM cells"
    step = _with(*_TOKEN_SPLIT, _SUPPORT) + _EXACT
    top_step = _with(*_TOKEN_SPLIT[:5], _TOP_EST) + _EXACT
    grid = _grid()
    wide = "wide AS (SELECT workers, d, k, size, alpha, " + ", ".join(f"max(CASE WHEN method = '{m}' THEN t END) AS {m}" for m in METHODS) + " FROM times GROUP BY ALL)"
    return recursions | {
        "shard_vector": _with(_parts()) + "SELECT * FROM parts",
        "sketch_sizes": _sketch_sizes(),
        "sketch_cells": cells,
        "sketch_blocks": cells,
        "sketch_sql": cells,
        "sketch_cells_cents": _with(rows, _PRICES, _cells("prices")) + "SELECT * FROM cells",
        "sketch_subtract": _with(rows, _parts(), _PRICES, "diff AS (SELECT worker, coord, CAST(sum(val) AS BIGINT) AS val FROM (SELECT * FROM parts UNION ALL SELECT worker, coord, -val FROM prices) GROUP BY ALL)", _cells("diff")) + "SELECT * FROM cells",
        "sketch_scale": _with(rows, _parts(), "scaled AS (SELECT worker, coord, -3 * val AS val FROM parts)", _cells("scaled")) + "SELECT * FROM cells",
        "sketch_norm": _with(rows, _parts(), _tokens(), _total("parts", "t1"), _total("tokens", "t2"), _cells("t1", "c1", ""), _cells("t2", "c2", ""), _norm("c1", "n1"), _norm("c2", "n2")) + "SELECT 'parts' AS vector, CAST(l2sq AS BIGINT) AS l2sq FROM n1 UNION ALL SELECT 'tokens', CAST(l2sq AS BIGINT) FROM n2",
        "point_query": _with(rows, _parts(), _total("parts"), _cells("total", by=""), _estimates(domain="(SELECT DISTINCT coord FROM parts)")) + "SELECT * FROM est",
        "point_query_blocks": _with(*_TOKEN_SPLIT[:5]) + "SELECT * FROM est",
        "heavy_split": _with(*_TOKEN_SPLIT) + "SELECT * FROM split",
        "heavy_split_signed": _with(*_TOKEN_SPLIT[:6]) + f"SELECT coord, est, CAST(est AS HUGEINT) * {K} >= l2sq AS heavy FROM est, norm",
        "random_fill": _with(*_TOKEN_SPLIT) + f"SELECT * FROM split WHERE NOT heavy ORDER BY {_FILL}, coord LIMIT {K}",
        "recover_heavy_random": _with(*_TOKEN_SPLIT, _SUPPORT) + "SELECT * FROM support",
        "recover_top_estimate": _with(*_TOKEN_SPLIT[:5], _TOP_EST) + "SELECT * FROM support",
        "recover_heavy_only": _with(*_TOKEN_SPLIT) + f"SELECT * FROM split WHERE heavy ORDER BY abs(est) DESC, coord LIMIT {K}",
        "exact_round": step,
        "tree_sketch_step": step,
        "star_sketch_step": step,
        "tree_sketch_step_top_estimate": top_step,
        "tree_sketch_step_estimates": _with(*_TOKEN_SPLIT, _SUPPORT) + "SELECT *, est AS exact FROM support",
        "dense_sum": _with(_parts(), _total("parts")) + "SELECT * FROM total WHERE val <> 0",
        "dense_tree_p5": _with(_parts(5), _total("parts")) + "SELECT * FROM total WHERE val <> 0",
        "local_topk": _with(_tokens(), _local_top("tokens", "top")) + "SELECT * FROM top",
        "star_topk_step": _with(_tokens(), _local_top("tokens", "top"), _total("top")) + "SELECT * FROM total WHERE val <> 0",
        "tree_topk_step_p4": _tree_top(4),
        "tree_topk_step_p5": _tree_top(5),
        "exact_topk": _with(_parts(), _total("parts")) + f"SELECT * FROM total ORDER BY abs(val) DESC, coord LIMIT {K}",
        "random_k": _with(_parts(), _total("parts")) + f"SELECT * FROM total WHERE val <> 0 ORDER BY {_FILL}, coord LIMIT {K}",
        "quantize": _with(_tokens(), "m AS (SELECT worker, CAST(max(abs(val)) AS DOUBLE) AS m FROM tokens GROUP BY worker)") + "SELECT worker, coord, CAST(floor(val / m * 127 + 0.5) AS BIGINT) AS level FROM tokens JOIN m USING (worker)",
        "support_agreement": _with(_tokens(), _local_top("tokens", "top"), _total("tokens"), f"best AS (SELECT coord FROM total ORDER BY abs(val) DESC, coord LIMIT {K})")
        + "SELECT 'all' AS part, count(*) AS n FROM (SELECT coord FROM top GROUP BY coord HAVING count(DISTINCT worker) = 5) UNION ALL SELECT 'any', count(DISTINCT coord) FROM top UNION ALL SELECT 'missed', count(*) FROM best WHERE coord NOT IN (SELECT coord FROM top)",
        "merged_maps": _with(_tokens(), _local_top("tokens", "top"), "two AS (SELECT coord, CAST(sum(val) AS BIGINT) AS val FROM top WHERE worker < 2 GROUP BY coord HAVING sum(val) <> 0)") + f"SELECT * FROM two ORDER BY abs(val) DESC, coord LIMIT {K}",
        "builtin_top_k": "SELECT event_type AS item, count(*) AS n FROM events GROUP BY event_type ORDER BY n DESC LIMIT 5",
        "event_property_vector": "SELECT CAST(event_id % 4 AS INT) AS worker, CAST(json_extract_string(props, '$.k') AS BIGINT) AS coord, count(*) AS val FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY ALL",
        "tree_edges": _EDGES,
        "tree_ledger": _LEDGER + "SELECT workers, method, phase, direction, max(round) AS rounds, CAST(sum(messages) AS BIGINT) AS messages, CAST(sum(vals) AS BIGINT) AS values FROM led GROUP BY ALL",
        "ledger_rollup": _LEDGER + "SELECT coalesce(method, 'all') AS method, coalesce(phase, 'all') AS phase, CAST(sum(messages) AS BIGINT) AS messages, CAST(sum(vals) AS BIGINT) AS values, CAST(8 * sum(vals) AS BIGINT) AS bytes FROM led GROUP BY ROLLUP (method, phase)",
        "counted_ledger": _with(rows, _parts(5), _cells("parts", "c0")) + " UNION ALL ".join(
            f"SELECT {i} AS round, CAST({n // 2} AS BIGINT) AS messages, count(*) AS values FROM (SELECT worker // {2 ** (i - 1)} AS w, hrow, bucket, sum(val) AS v FROM c0 GROUP BY ALL HAVING sum(val) <> 0) WHERE w % 2 = 1" for i, n in ((1, 5), (2, 3), (3, 2))
        ),
        "literal_stride_coverage": _STRIDES,
        "cost_grid": grid + "SELECT * FROM times",
        "cost_speedup": grid + f", {wide} SELECT workers, d, k, size, alpha, " + ", ".join(f"{_micro(f'CAST({m} AS DOUBLE) / tree_sketch')} AS over_{m}_micro" for m in METHODS if m != "tree_sketch") + ", CAST(alpha < k - size AS INT) AS beats_tree_topk FROM wide",
        "compression_ratio": _with(*_TOKEN_SPLIT, _local_top("tokens", "top"), _SUPPORT, f"""sizes AS (SELECT (SELECT 2 * max(n) FROM (SELECT count(*) AS n FROM top GROUP BY worker)) AS t, (SELECT count(*) + {SPEC.size} FROM support) AS s), t AS (SELECT unnest(['dense', 'star_topk', 'tree_topk', 'star_sketch', 'tree_sketch']) AS method, unnest([{D}, t, t, s, s]) AS values FROM sizes)""") + f"SELECT method, CAST(values AS BIGINT) AS values, {_micro(f'CAST({D} AS DOUBLE) / values')} AS ratio_micro FROM t",
        "warmup_schedule": _schedule(),
        "minibatch": f"SELECT key, worker FROM (SELECT *, row_number() OVER (PARTITION BY worker ORDER BY {sql_fill_order(f'(key % {PRIME})', SEED, 3)}, key) AS rn FROM (SELECT vec_id AS key, {_worker('vec_id')} AS worker FROM embeddings)) WHERE rn <= 16",
        "shard_counts": f"SELECT {_worker('doc_id')} AS worker, count(*) AS n FROM documents GROUP BY ALL",
        "planted_label": _with(_COMPONENT_ROWS) + f"SELECT key, CAST(arg_max(c, (s, -c)) AS INT) AS label FROM (SELECT key, c, sum(CAST(x AS HUGEINT) * ({sql_fill_order(f'(c * {COMPONENTS} + j)', 99, 0)} % 2001 - 1000)) AS s FROM xs, range({CLASSES}) AS t(c) GROUP BY ALL) GROUP BY key",
        "softmax_gradient": _with(*_gradient()) + "SELECT * FROM gradient",
        "training_step": _first_step() + f"SELECT d.coord, CAST(coalesce(CASE WHEN s.coord IS NOT NULL THEN -t.val END, 0) AS BIGINT) AS w FROM (SELECT range AS coord FROM range({SMALL_D})) d LEFT JOIN support s ON s.coord = d.coord LEFT JOIN total t ON t.coord = d.coord",
        "training_residual": _first_step() + "SELECT worker, coord, val FROM gradient WHERE coord NOT IN (SELECT coord FROM support)",
        "linear_gradient": "SELECT worker, coord, CAST(sum(-y * x) AS BIGINT) AS val FROM (SELECT CAST(l_orderkey % 4 AS INT) AS worker, CAST(floor(l_extendedprice + 0.5) AS BIGINT) AS y, "
        f"unnest([CAST(0 AS BIGINT), 1, 2, 3]) AS coord, unnest([CAST(l_quantity AS BIGINT), {_CENTS.format('l_discount')}, {_CENTS.format('l_tax')}, 1]) AS x FROM lineitem) GROUP BY ALL HAVING sum(-y * x) <> 0",
        "estimate_error": _with(_tokens(), _total("tokens")) + _token_error(SPEC) + " UNION ALL " + _token_error(WIDE),
        "heavy_recall": _with(*_TOKEN_SPLIT, _SUPPORT) + f"SELECT count(*) AS heavy, count(s.coord) AS found FROM total t LEFT JOIN support s USING (coord) WHERE CAST(t.val AS HUGEINT) * t.val * {K} >= (SELECT sum(CAST(val AS HUGEINT) * val) FROM total)",
        "support_overlap": _with(*_TOKEN_SPLIT, _SUPPORT, f"tops AS (SELECT coord FROM total ORDER BY abs(val) DESC, coord LIMIT {K})", _TOP_EST.replace("support AS", "est_top AS"))
        + " UNION ALL ".join(f"SELECT '{name}' AS recovery, count(*) FILTER (WHERE a.coord IS NOT NULL AND b.coord IS NOT NULL) AS both, count(*) FILTER (WHERE b.coord IS NULL) AS only_support, count(*) FILTER (WHERE a.coord IS NULL) AS only_top FROM {table} a FULL JOIN tops b ON a.coord = b.coord" for name, table in (("heavy_random", "support"), ("top_estimate", "est_top"))),
        "captured_energy": _with(*_TOKEN_SPLIT[:5], _TOP_EST, f"step AS ({_EXACT})") + f"SELECT {energy_rank} AS rank, coord, exact, {_micro('CAST(sum(CAST(exact AS HUGEINT) * exact) OVER (ORDER BY abs(exact) DESC, coord ROWS UNBOUNDED PRECEDING) AS DOUBLE) / (SELECT CAST(sum(CAST(val AS HUGEINT) * val) AS DOUBLE) FROM total)')} AS captured_micro FROM step",
        "speedup_table": _grid(RATED) + ", " + ", ".join(["r AS (SELECT vector AS model, method, CAST(1e9 AS DOUBLE) / t AS v FROM times JOIN vectors USING (d))", "ratios AS (SELECT a.model, b.method AS over, a.v / b.v AS s FROM r a JOIN r b ON a.model = b.model WHERE a.method = 'tree_sketch' AND b.method IN ('tree_topk', 'star_sketch'))"]) + " "
        + f"SELECT model, over, {_micro('s')} AS speedup_micro FROM ratios UNION ALL SELECT 'mean', over, {_micro('avg(s)')} FROM ratios GROUP BY over",
        "token_counts": _with(_tokens()) + "SELECT * FROM tokens",
        "event_user_vector": f"SELECT CAST(event_id % 4 AS INT) AS worker, user_id AS coord, CAST(sum({_CENTS.format('value')}) AS BIGINT) AS val FROM events GROUP BY ALL",
        "event_daily_sketch": _with(rows, f"days AS (SELECT strftime(ts, '%Y-%m-%d') AS day, user_id AS coord, CAST(sum({_CENTS.format('value')}) AS BIGINT) AS val FROM events GROUP BY ALL)", _cells("days", by="day")) + "SELECT * FROM cells",
        "stream_daily_sketch": _with(rows, f"days AS (SELECT strftime(ts, '%Y-%m-%d') AS day, user_id AS coord, CAST(sum({_CENTS.format('value')}) AS BIGINT) AS val FROM events GROUP BY ALL)", _cells("days", by="day")) + "SELECT * FROM cells",
        "event_session_counts": f"SELECT user_id, count(*) AS sessions, max(n) AS longest, CAST(sum(v) AS BIGINT) AS val FROM (SELECT user_id, s, count(*) AS n, sum(v) AS v FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, event_id, ts, {_CENTS.format('value')} AS v, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s) GROUP BY user_id",
    }
