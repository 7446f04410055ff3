"""Point views of the given tables, each told once for Spark and once for DuckDB.

Coordinates are whole numbers (value times a scale, rounded by floor(v + 0.5)), so squared
distances are exact and equal in both engines.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from farpoint.functions.hashing import DIGITS, SPAN


@dataclass(frozen=True)
class View:
    table: str
    id: str
    spark: tuple[str, ...]
    duck: tuple[str, ...] = ()
    distinct: bool = False
    extra: str = ""

    @property
    def duck_coords(self) -> tuple[str, ...]:
        return self.duck or self.spark

    @property
    def dims(self) -> int:
        return len(self.spark)


def _scaled(column: str, by: int) -> str:
    return f"CAST(floor({column} * {by} + 0.5) AS BIGINT)"


def _packed(parts: list[tuple[str, int]]) -> str:
    """An id that sorts as the tuple of the parts does; each has the number of values given."""
    out = ""
    for expr, size in parts:
        out = f"({out}) * {size} + {expr}" if out else expr
    return f"CAST({out} AS BIGINT)"


_grid = [("CAST(l_linenumber AS BIGINT)", 64), ("CAST(l_quantity AS BIGINT)", 1024), (_scaled("l_discount", 100), 1024), (_scaled("l_tax", 100), 1024)]
_four = [(_scaled("l_quantity", 100), 1), (_scaled("l_extendedprice", 100), 1 << 30), (_scaled("l_discount", 100), 1024), (_scaled("l_tax", 100), 1024)]
_minutes = "timestampdiff(MINUTE, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)"
_duck_minutes = "CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01 00:00:00')) / 60) AS BIGINT)"
_cents = _scaled("o_totalprice", 100)

VIEWS: dict[str, View] = {
    "orders_2d": View("orders", "o_orderkey", (_cents, "datediff(o_orderdate, DATE'1992-01-01') * 10000"), (_cents, "date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) * 10000")),
    "events_2d": View("events", "event_id", (_scaled("value", 100), _minutes), (_scaled("value", 100), _duck_minutes)),
    "customer_2d": View("customer", "c_custkey", (_scaled("c_acctbal", 100), "CAST(c_nationkey AS BIGINT) * 2000000"), extra="c_mktsegment"),
    "part_2d": View("part", "p_partkey", ("CAST(p_size AS BIGINT) * 100", _scaled("p_retailprice", 10))),
    "lineitem_4d": View("lineitem", _packed(_four), tuple(e for e, _ in _four), distinct=True),
    "lineitem_grid": View("lineitem", _packed(_grid), tuple(e for e, _ in _grid), distinct=True),
    "supplier_tiny": View("supplier", "s_suppkey", (_scaled("s_acctbal", 100), "CAST(s_nationkey AS BIGINT) * 10000")),
    "nation_tiny": View("nation", "CAST(n_nationkey AS BIGINT)", ("CAST(n_nationkey AS BIGINT)", "CAST(n_regionkey AS BIGINT) * 10")),
    "region_trivial": View("region", "CAST(r_regionkey AS BIGINT)", ("CAST(r_regionkey AS BIGINT)",)),
}


def md5_unit(text: str, engine: str) -> str:
    """Uniform in [0, 1) from a text expression."""
    if engine == "spark":
        return f"(CAST(conv(substring(md5(CAST({text} AS BINARY)), 1, {DIGITS}), 16, 10) AS BIGINT) / {float(SPAN)!r}D)"
    return f"(CAST(('0x' || substr(md5({text}), 1, {DIGITS})) AS BIGINT) / {float(SPAN)!r})"


def clustered_sql(kind: str, groups: int, engine: str, side: float = 100.0, sigma: float = 0.1, scale: int = 10_000, seed: int = 42, offset: str = "axis") -> tuple[str, list[str]]:
    """Group and coordinates of the clustered views on orders: ``gauss`` has equal groups, ``skew`` half of all points in one.

    Centers are uniform in a cube; points lie around them by a normal offset on each axis, or
    (``radial``) at a normal length in a random direction.
    """
    if kind == "gauss":
        g = f"o_custkey % {groups}"
    else:
        g = f"CASE WHEN o_orderkey % 2 = 0 THEN 0 ELSE 1 + o_custkey % {groups - 1} END"
    text = "STRING" if engine == "spark" else "VARCHAR"
    u = lambda tag, key: md5_unit(f"concat('{seed}:{tag}:', CAST({key} AS {text}))", engine)
    normal = lambda a: f"sqrt(-2 * ln(1 - {u('r' + a, 'o_orderkey')})) * cos({2 * 3.141592653589793!r} * {u('t' + a, 'o_orderkey')})"
    if offset == "axis":
        shift = {a: f"{sigma} * {normal(a)}" for a in "xyz"}
    else:
        length, z, turn = f"({sigma} * abs({normal('x')}))", f"(2 * {u('dz', 'o_orderkey')} - 1)", f"({2 * 3.141592653589793!r} * {u('da', 'o_orderkey')})"
        flat = f"sqrt(1 - {z} * {z})"
        shift = {"x": f"{length} * {flat} * cos({turn})", "y": f"{length} * {flat} * sin({turn})", "z": f"{length} * {z}"}
    return g, [f"CAST(floor(({side} * {u('c' + a, f'({g})')} + {shift[a]}) * {scale} + 0.5) AS BIGINT)" for a in "xyz"]


def points_of(spark: SparkSession, sf_dir: str, name: str, groups: int = 25) -> DataFrame:
    """id, coords ARRAY<DOUBLE> (and group or extra columns) of a view."""
    if name in ("gauss_on_orders", "skew_on_orders"):
        g, xs = clustered_sql(name[:5].rstrip("_"), groups, "spark")
        rows = spark.read.parquet(f"{sf_dir}/orders.parquet")
        return rows.selectExpr("o_orderkey AS id", f"array({', '.join(f'CAST({x} AS DOUBLE)' for x in xs)}) AS coords", f"{g} AS g")
    if name == "embeddings_64d":
        rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
        return rows.selectExpr("vec_id AS id", "transform(embedding, v -> floor(CAST(v AS DOUBLE) * 1000000 + 0.5) * 1.0D) AS coords", "label")
    if name.endswith("_tf"):
        from farpoint.functions.features import term_counts

        table, key, text = {"documents_tf": ("documents", "doc_id", "text"), "pages_tf": ("pages", "page_id", "regexp_replace(html, '<[^>]*>', ' ')"), "benchmark_tf": ("benchmark", "item_id", "text"), "conversations_tf": ("conversations", "conv_id", "text")}[name]
        return term_counts(spark.read.parquet(f"{sf_dir}/{table}.parquet").selectExpr(f"{key} AS id", f"{text} AS text"))
    return _points(spark.read.parquet(f"{sf_dir}/{VIEWS[name].table}.parquet"), VIEWS[name])


def stream_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The view as a stream over the table's files, for views that need no distinct rows."""
    v, path = VIEWS[name], f"{sf_dir}/{VIEWS[name].table}.parquet"
    if v.distinct:
        raise ValueError(f"{name} keeps one of equal rows, which takes state over the whole stream")
    reader, where = spark.readStream.schema(spark.read.parquet(path).schema), spark._jvm.org.apache.hadoop.fs.Path(path)
    if where.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(where).isFile():  # a stream reads folders
        return _points(reader.option("pathGlobFilter", f"{v.table}.parquet").parquet(sf_dir), v)
    return _points(reader.parquet(path), v)


def _points(rows: DataFrame, v: View) -> DataFrame:
    coords = f"array({', '.join(f'CAST({x} AS DOUBLE)' for x in v.spark)}) AS coords"
    out = rows.selectExpr(f"CAST({v.id} AS BIGINT) AS id", coords, *([v.extra] if v.extra else []))
    return out.dropDuplicates(["id"]) if v.distinct else out


def duck_points(name: str, groups: int = 25) -> tuple[str, int]:
    """A DuckDB SELECT of (id, c0, c1, ...), and the number of coordinates."""
    if name in ("gauss_on_orders", "skew_on_orders"):
        g, xs = clustered_sql(name[:5].rstrip("_"), groups, "duck")
        return f"SELECT o_orderkey AS id, {', '.join(f'{x} AS c{i}' for i, x in enumerate(xs))}, {g} AS g FROM orders", 3
    if name == "embeddings_64d":
        return f"SELECT vec_id AS id, {', '.join(f'CAST(floor(CAST(embedding[{i + 1}] AS DOUBLE) * 1000000 + 0.5) AS BIGINT) AS c{i}' for i in range(64))} FROM embeddings", 64
    if name == "documents_tf":
        lower = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
        word = f"SELECT doc_id AS id, unnest(string_split({lower}, ' ')) AS w FROM documents"
        bucket = "SELECT id, CAST(('0x' || substr(md5(w), 1, 4)) AS BIGINT) % 32 AS b FROM words"
        sums = ", ".join(f"count(*) FILTER (WHERE b = {i}) AS c{i}" for i in range(32))
        return f"WITH words AS ({word}), hashed AS ({bucket}) SELECT id, {sums} FROM hashed GROUP BY id", 32
    v = VIEWS[name]
    xs = ", ".join(f"{x} AS c{i}" for i, x in enumerate(v.duck_coords))
    extra = f", {v.extra}" if v.extra else ""
    return f"SELECT {'DISTINCT ' if v.distinct else ''}{v.id} AS id, {xs}{extra} FROM {v.table}", v.dims
