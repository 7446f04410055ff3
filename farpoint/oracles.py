"""DuckDB SQL of the methods, put together from a few parts; the tests and the driver compare with it."""

from __future__ import annotations

from farpoint.functions.hashing import duck_number, duck_uniform
from farpoint.sources.views import duck_points

BIG = "9000000000000000000"


def squared(a: str, b: str, dims: int) -> str:
    return " + ".join(f"({a}.c{i} - {b}.c{i}) * ({a}.c{i} - {b}.c{i})" for i in range(dims))


def manhattan(a: str, b: str, dims: int) -> str:
    return " + ".join(f"abs({a}.c{i} - {b}.c{i})" for i in range(dims))


def chebyshev(a: str, b: str, dims: int) -> str:
    return f"greatest({', '.join(f'abs({a}.c{i} - {b}.c{i})' for i in range(dims))})"


def jaccard(a: str, b: str, dims: int) -> str:
    both = " + ".join(f"CAST({a}.c{i} > 0 AND {b}.c{i} > 0 AS INT)" for i in range(dims))
    some = " + ".join(f"CAST({a}.c{i} > 0 OR {b}.c{i} > 0 AS INT)" for i in range(dims))
    return f"(1.0::DOUBLE - CAST({both} AS DOUBLE) / CAST({some} AS DOUBLE))"


def cs(dims: int, prefix: str = "") -> str:
    return ", ".join(f"{prefix}c{i}" for i in range(dims))


def points_cte(view: str, groups: int = 25) -> tuple[str, int]:
    sql, dims = duck_points(view, groups)
    return f"pts AS MATERIALIZED ({sql})", dims


def traversal(name: str, source: str, dims: int, k: int, block: str | None = None, seed: str = "id", key=squared, kind: str = "BIGINT") -> list[str]:
    """CTEs for farthest-first on ``source`` (in each ``block``): ``name`` has rank, id, key, c0, ... [, block].

    ``seed`` is what the first center has least of.
    """
    part, on = (f"PARTITION BY {block} ", f"p.{block} = s.{block}") if block else ("", "true")
    b, pb = (f", {block}", f", p.{block}") if block else ("", "")
    picks = ", ".join(f"first_value(c{i}) OVER w AS n{i}" for i in range(dims))
    state = f"SELECT 1 AS rank, p.id, {cs(dims, 'p.')}{pb}, s.id AS cid, {', '.join(f's.c{i} AS s{i}' for i in range(dims))}, CAST(NULL AS {kind}) AS ckey, {key('p', 's', dims)} AS d"
    first = f"(SELECT * FROM {source} QUALIFY row_number() OVER ({part}ORDER BY {seed}) = 1)"
    new = key("f", "m", dims)
    for i in range(dims):
        new = new.replace(f"m.c{i} ", f"f.n{i} ").replace(f"m.c{i})", f"f.n{i})")
    inner = f"SELECT *, first_value(id) OVER w AS nid, {picks}, first_value(d) OVER w AS nd FROM {name}_all WHERE rank < {k} WINDOW w AS ({part}ORDER BY d DESC, id)"
    step = f"SELECT f.rank + 1, f.id, {cs(dims, 'f.')}{', f.' + block if block else ''}, f.nid, {', '.join(f'f.n{i}' for i in range(dims))}, f.nd, least(f.d, {new}) FROM ({inner}) f WHERE f.nd > 0"
    return [
        f"{name}_all AS ({state} FROM {source} p JOIN {first} s ON {on} UNION ALL {step})",
        f"{name} AS (SELECT DISTINCT rank, cid AS id, ckey AS key, {', '.join(f's{i} AS c{i}' for i in range(dims))}{b} FROM {name}_all)",
    ]


def query(ctes: list[str], final: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes) + "\n" + final


PICKED = "SELECT rank, id, coalesce(CAST(key AS BIGINT), 0) AS key FROM {}"


def farthest_first(view: str, k: int, seed: str = "id", key=squared, final: str = PICKED.format("ff"), groups: int = 25, kind: str = "BIGINT") -> str:
    pts, dims = points_cte(view, groups)
    return query([pts, *traversal("ff", "pts", dims, k, seed=seed, key=key, kind=kind)], final)


def blocks_sql(strategy: str, m: int, seed: int = 42) -> str:
    """pts with a block column."""
    if strategy == "id_mod":
        b = f"id % {m}"
    elif strategy == "hash":
        b = f"{duck_number(repr(str(seed)), repr('block'), 'CAST(id AS VARCHAR)')} % {m}"
    elif strategy == "ntile":
        b = f"ntile({m}) OVER (ORDER BY id) - 1"
    elif strategy == "range":
        return f"SELECT p.*, least(floor(((c0 - lo) * {m}) / CAST(hi - lo + 1 AS DOUBLE)), {m - 1}) AS block FROM pts p, (SELECT min(c0) AS lo, max(c0) AS hi FROM pts)"
    else:
        raise ValueError(strategy)
    return f"SELECT *, {b} AS block FROM pts"


def blocked(view: str, k: int, m: int, strategy: str = "id_mod", more: tuple[int, ...] = (), final: str = PICKED.format("last"), groups: int = 25) -> str:
    """Two rounds, with further levels of ``more`` blocks (by id) between them."""
    pts, dims = points_cte(view, groups)
    return query([pts, *blocked_ctes(dims, k, m, strategy, more)], final)


def blocked_ctes(dims: int, k: int, m: int, strategy: str = "id_mod", more: tuple[int, ...] = ()) -> list[str]:
    ctes, at = [f"dealt AS MATERIALIZED ({blocks_sql(strategy, m)})", *traversal("level0", "dealt", dims, k, "block")], "level0"
    for i, blocks in enumerate(more, 1):
        ctes += [f"dealt{i} AS MATERIALIZED (SELECT id, {cs(dims)}, id % {blocks} AS block FROM {at})", *traversal(f"level{i}", f"dealt{i}", dims, k, "block")]
        at = f"level{i}"
    return [*ctes, f"survivors AS MATERIALIZED (SELECT DISTINCT id, {cs(dims)} FROM {at})", *traversal("last", "survivors", dims, k)]


def sampling_ctes(dims: int, k: int, phi: float, iterations: int, eps: float = 0.1, seed: int = 42, keep_equal: bool = False, guarded: bool = False) -> list[str]:
    """The unrolled loop: members{i}, live{i}, pivot{i}, and ``sample`` (id, c0, ..., part).

    With ``guarded`` an iteration does nothing once the live points are few enough (go{i}), so ``iterations`` may be any number that is large enough.
    """
    ctes = [f"size AS (SELECT count(*) AS n, pow(count(*), {eps}) AS g, ln(count(*)) AS l FROM pts)", f"live0 AS (SELECT id, {cs(dims)}, CAST({BIG} AS BIGINT) AS d FROM pts)"]
    for i in range(1, iterations + 1):
        draw = lambda tag: duck_uniform(repr(str(seed)), repr(str(i - 1)), repr(tag), "CAST(id AS VARCHAR)")  # noqa: B023, E731
        go = f"m > 4 / {eps} * {k} * g * l" if guarded else "true"
        ctes += [
            f"count{i} AS (SELECT count(*) AS m FROM live{i - 1})",
            f"go{i} AS MATERIALIZED (SELECT {go} AS go FROM size, count{i})",
            f"drawn{i} AS MATERIALIZED (SELECT r.*, go AND {draw('S')} < 9 * {k} * g * l / m AS in_s, go AND {draw('H')} < 4 * g * l / m AS in_h FROM live{i - 1} r, size, count{i}, go{i})",
            f"members{i} AS MATERIALIZED (SELECT id, {cs(dims)} FROM drawn{i} WHERE in_s)",
            f"near{i} AS MATERIALIZED (SELECT a.id, min({squared('a', 'b', dims)}) AS e FROM drawn{i} a, members{i} b GROUP BY a.id)",
            f"lower{i} AS MATERIALIZED (SELECT a.id, {cs(dims, 'a.')}, least(a.d, coalesce(e, a.d)) AS d, in_s, in_h FROM drawn{i} a LEFT JOIN near{i} USING (id))",
            f"pivot{i} AS (SELECT d AS p FROM (SELECT d, row_number() OVER (ORDER BY d DESC, id) AS r FROM lower{i} WHERE in_h) WHERE r <= (SELECT greatest(1, floor({phi} * l)) FROM size) ORDER BY r DESC LIMIT 1)",
            f"live{i} AS MATERIALIZED (SELECT id, {cs(dims)}, d FROM lower{i} WHERE d {'>=' if keep_equal else '>'} (SELECT p FROM pivot{i}) OR NOT (SELECT go FROM go{i}))",
        ]
    parts = [f"SELECT id, {cs(dims)}, 'S' AS part FROM members{i}" for i in range(1, iterations + 1)]
    rest = f"SELECT id, {cs(dims)}, 'R' AS part FROM live{iterations}" + (f" WHERE id NOT IN (SELECT id FROM members{iterations})" if keep_equal and iterations else "")
    return [*ctes, f"sample AS MATERIALIZED ({' UNION ALL '.join([*parts, rest])})"]


def iterations_run(iterations: int) -> str:
    """How many iterations a guarded loop has run."""
    return "CAST(" + " + ".join(f"(SELECT CAST(go AS INT) FROM go{i})" for i in range(1, iterations + 1)) + " AS INT)"


def sampled(view: str, k: int, phi: float, final: str, iterations: int = 8, eps: float = 0.1, seed: int = 42, keep_equal: bool = False, traverse: bool = True, groups: int = 25) -> str:
    """A guarded loop and, over its sample, the traversal ``ff``; ``final`` may name iterations as {runs} and the radius key as {radius}."""
    pts, dims = points_cte(view, groups)
    ctes = [pts, *sampling_ctes(dims, k, phi, iterations, eps, seed, keep_equal, guarded=True), *(traversal("ff", "sample", dims, k) if traverse else [])]
    return query(ctes, final.replace("{runs}", iterations_run(iterations)).replace("{radius}", f"CAST({radius_key('ff', dims)} AS BIGINT)"))


def all_of(queries: list[str]) -> str:
    """One table of several queries, each with its own names."""
    return " UNION ALL ".join(f"SELECT * FROM ({q})" for q in queries)


def sampling(view: str, k: int, phi: float, iterations: int, final: str = "SELECT id, part FROM sample", keep_equal: bool = False, traverse: bool = False) -> str:
    pts, dims = points_cte(view)
    ctes = [pts, *sampling_ctes(dims, k, phi, iterations, keep_equal=keep_equal)]
    return query(ctes + (traversal("ff", "sample", dims, k) if traverse else []), final)


def sampling_trace(view: str, k: int, phi: float, iterations: int, keep_equal: bool = False) -> str:
    rows = [
        f"SELECT {i} AS iteration, (SELECT m FROM count{i}) AS live, (SELECT count(*) FROM members{i}) AS new_sample, (SELECT count(*) FROM drawn{i} WHERE in_h) AS probes, "
        f"CAST((SELECT p FROM pivot{i}) AS BIGINT) AS pivot_key, (SELECT count(*) FROM live{i}) AS live_after" for i in range(1, iterations + 1)
    ]
    return sampling(view, k, phi, iterations, " UNION ALL ".join(rows), keep_equal)


def assigned_cte(centers: str, dims: int, source: str = "pts", name: str = "assigned", key=squared) -> str:
    """id, center_id, key."""
    return f"{name} AS MATERIALIZED (SELECT p.id, min(struct_pack(key := {key('p', 'c', dims)}, center_id := c.id)) AS n FROM {source} p, {centers} c GROUP BY p.id)"


def radius_key(centers: str, dims: int, source: str = "pts") -> str:
    return f"(SELECT max(e) FROM (SELECT min({squared('p', 'c', dims)}) AS e FROM {source} p, {centers} c GROUP BY p.id))"
