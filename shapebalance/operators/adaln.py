"""Fused normalise-and-modulate over vector columns, its gradients, and the discrete baselines (M31-M36, Bl4, Bl5, Bl7).

A token is a row whose vector is contiguous. Fused forms make one pass per row: in SQL by array functions of one
projection, in Arrow by array operations over the flattened vectors of a batch. Discrete forms materialise each step in
long form, one row per (token, feature), which is the cost that fusing saves.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..ship import ship

EPS = 1e-6


def _sum(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda a, v: a + v)


def _with_params(x: DataFrame, params: DataFrame, *columns: str) -> DataFrame:
    """Left join on label, so that no token is lost; a label without parameters gives nulls downstream. The table has a row per label."""
    return x.join(params.select("label", *columns), "label", "left")


def let(value: Column, use) -> Column:
    """use(value) with the value bound once per row: named outside a lambda, the optimizer would copy it into each element's evaluation."""
    return F.transform(F.array(value), use)[0]


def _moments(algo: str, eps: float) -> Column:
    """struct(mu, rstd) of x."""
    n = F.size("x")

    def of(mu: Column) -> Column:
        if algo == "one_pass":
            var = _sum(F.transform("x", lambda v: v * v)) / n - mu * mu
        else:
            var = _sum(F.transform("x", lambda v: (v - mu) * (v - mu))) / n
        return F.struct(mu.alias("mu"), (1 / F.sqrt(F.greatest(var, F.lit(0.0)) + eps)).alias("rstd"))

    return let(_sum(F.col("x")) / n, of)


def _standardised(x: Column, mu: Column, rstd: Column) -> Column:
    return let(F.struct(mu.alias("mu"), rstd.alias("rstd")), lambda st: F.transform(x, lambda v: (v - st["mu"]) * st["rstd"]))


def row_stats(x: DataFrame, eps: float = EPS, stats_algo: str = "two_pass", tile: int | None = None, acc: str = "float64") -> DataFrame:
    """Adds mu and rstd of each row's x. Narrow.

    stats_algo: two_pass, one_pass (sum and sum of squares) or welford. tile: partial sums over that many features are
    added up in order, accumulated in `acc` (float32 or float64).
    """
    if stats_algo == "welford":
        zero = F.struct(F.lit(0.0).alias("n"), F.lit(0.0).alias("m"), F.lit(0.0).alias("q"))

        def step(a, v):
            n, d = a["n"] + 1, v - a["m"]
            m = a["m"] + d / n
            return F.struct(n.alias("n"), m.alias("m"), (a["q"] + d * (v - m)).alias("q"))

        w = F.aggregate("x", zero, step)
        return x.withColumn("_w", w).withColumns({"mu": F.col("_w.m"), "rstd": 1 / F.sqrt(F.col("_w.q") / F.col("_w.n") + eps)}).drop("_w")
    if tile:
        kind = acc.replace("64", "").replace("float32", "float") if acc == "float32" else "double"
        starts = F.sequence(F.lit(1), F.size("x"), F.lit(tile))
        total = lambda of: F.aggregate(F.transform(starts, lambda i: F.aggregate(F.slice("x", i, tile), F.lit(0.0).cast(kind), lambda a, v: (a + of(v)).cast(kind))), F.lit(0.0).cast(kind), lambda a, v: (a + v).cast(kind)).cast("double")
        st = let(total(lambda v: v) / F.size("x"), lambda mu: F.struct(mu.alias("mu"), (1 / F.sqrt(total(lambda v: (v - mu) * (v - mu)) / F.size("x") + eps)).alias("rstd")))
    else:
        st = _moments(stats_algo, eps)
    return x.withColumn("_st", st).withColumns({"mu": F.col("_st.mu"), "rstd": F.col("_st.rstd")}).drop("_st")


def _whole(value: str) -> Column:
    """The vector of a row's values in long form by d; null where one is null."""
    vector = F.transform(F.array_sort(F.collect_list(F.struct("d", value))), lambda r: r[value])
    return F.when(F.count(value) == F.count("*"), vector)


def forward(x: DataFrame, params: DataFrame, impl: str = "sql", eps: float = EPS, emit_stats: bool = False, scale_offset: float = 1.0, materialize: bool = False) -> DataFrame:
    """M31, Bl4: y = xhat * (scale_offset + scale) + shift per token, for x (vec_id, label, x) and params per label.

    impl: sql or arrow (fused), discrete (baseline: mean, variance, standardise, multiply, add in long form; with
    materialize each step is written to executors' storage before the next). Adds mu and rstd with emit_stats. A null vector, or a
    label without parameters, gives a null y in all forms.
    """
    keep = ["vec_id", "label", *(["mu", "rstd"] if emit_stats else [])]
    if impl == "sql":
        rows = row_stats(_with_params(x, params, "shift", "scale"), eps)
        xhat = _standardised(F.col("x"), F.col("mu"), F.col("rstd"))
        scaled = F.zip_with(xhat, "scale", lambda v, s: v * (scale_offset + s))
        return rows.withColumn("y", F.zip_with(scaled, "shift", lambda v, s: v + s)).select(*keep, "y")
    if impl == "arrow":
        return _arrow(_with_params(x, params, "shift", "scale"), _forward_kernel(eps, scale_offset, emit_stats), "vec_id long, label int" + (", mu double, rstd double" if emit_stats else "") + ", y array<double>", ("x", "shift", "scale"))
    hold = (lambda df: df.persist()) if materialize else (lambda df: df)
    long = hold(x.select("vec_id", "label", F.posexplode_outer("x").alias("d", "v")))
    mean = hold(long.groupBy("vec_id").agg(F.avg("v").alias("mu")))
    centred = hold(long.join(mean, "vec_id"))
    var = hold(centred.groupBy("vec_id").agg(F.avg((F.col("v") - F.col("mu")) * (F.col("v") - F.col("mu"))).alias("var")))
    xhat = hold(centred.join(var, "vec_id", "left").withColumn("rstd", 1 / F.sqrt(F.col("var") + eps)).withColumn("xhat", (F.col("v") - F.col("mu")) * F.col("rstd")))
    flat = params.select("label", F.posexplode(F.arrays_zip("scale", "shift")).alias("d", "m")).select("label", "d", "m.scale", "m.shift")
    scaled = hold(xhat.join(flat, ["label", "d"], "left").withColumn("z", F.col("xhat") * (scale_offset + F.col("scale"))))
    y = scaled.withColumn("y1", F.col("z") + F.col("shift"))
    return y.groupBy("vec_id", "label", *(["mu", "rstd"] if emit_stats else [])).agg(_whole("y1").alias("y")).select(*keep, "y")


def _matrix(batch: pa.RecordBatch, name: str) -> np.ndarray:
    """The vectors of a batch as (rows, features), without a copy where they are doubles."""
    column = batch.column(name)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(batch.num_rows, -1)


def _vectors(m: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(m) + 1, dtype=np.int32) * (m.shape[1] if m.ndim > 1 else 0)), pa.array(m.ravel()))


def _arrow(df: DataFrame, kernel, schema: str, vectors: tuple[str, ...]) -> DataFrame:
    """Runs a kernel over Arrow batches. A row of which one of `vectors` is null keeps its other columns and gets nulls for what the kernel adds."""

    ship(df.sparkSession)
    lists = [f.name for f in df.schema.fields if f.name in vectors]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            whole = np.logical_and.reduce([np.asarray(batch.column(c).is_valid()) for c in lists])
            good = batch if whole.all() else batch.filter(pa.array(whole))
            out = kernel(good) if good.num_rows else None
            if out is not None:
                yield out
            if len(bad := batch.filter(pa.array(~whole))):
                types = out.schema if out is not None else kernel(_sample_row(batch, lists)).schema
                yield pa.record_batch([bad.column(f.name) if f.name in bad.schema.names and f.name not in vectors else pa.nulls(len(bad), f.type) for f in types], schema=types)

    return df.mapInArrow(run, schema)


def _sample_row(batch: pa.RecordBatch, lists: list[str]) -> pa.RecordBatch:
    """The first row with vectors of four zeros, to learn what a kernel returns."""
    zeros = pa.array([[0.0] * 4], pa.list_(pa.float64()))
    return pa.record_batch([zeros if f.name in lists else batch.column(f.name).slice(0, 1) for f in batch.schema], batch.schema.names)


def _normalised(x: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    mu = x.mean(axis=1)
    xc = x - mu[:, None]
    rstd = 1 / np.sqrt((xc * xc).mean(axis=1) + eps)
    return xc * rstd[:, None], mu, rstd


def _forward_kernel(eps: float, offset: float, stats: bool):
    def kernel(b: pa.RecordBatch) -> pa.RecordBatch:
        xhat, mu, rstd = _normalised(_matrix(b, "x"), eps)
        y = xhat * (offset + _matrix(b, "scale")) + _matrix(b, "shift")
        more = [("mu", pa.array(mu)), ("rstd", pa.array(rstd))] if stats else []
        return pa.record_batch({"vec_id": b.column("vec_id"), "label": b.column("label"), **dict(more), "y": _vectors(y)})

    return kernel


def grad_params(x: DataFrame, impl: str = "tiled", stats: str = "recompute", d_tile: int = 64, n_tile: int = 256, acc: str = "float64", eps: float = EPS, ordered: bool = False) -> DataFrame:
    """M33, M33a, Bl5: label, d, grad_shift = sum dy, grad_scale = sum dy * xhat over the tokens of a label.

    tiled: Arrow partials per (label, feature tile, token tile by vec_id) of each batch, then their sums; wide: one sum per
    feature in a hash aggregate; strided: one row per (token, feature). stats=cached reads mu and rstd from x.
    With `ordered` (tiled) tokens are dealt by token tile and sorted by vec_id, and partials are added in the tiles' order,
    a thousand at a time: gradients are the same bits for any partitioning and batch size, at the cost of a shuffle of
    the vectors. Rows with a null x or dy take no part; a null label is a group.
    """
    x = x.where("x IS NOT NULL AND dy IS NOT NULL")
    if impl == "tiled" and ordered:
        return _ordered(x, stats, d_tile, n_tile, acc, eps)
    if impl == "tiled":
        return _tiled(x, stats, d_tile, n_tile, acc, eps)
    rows = x if stats == "cached" else row_stats(x, eps)
    rows = rows.withColumn("xhat", _standardised(F.col("x"), F.col("mu"), F.col("rstd")))
    if impl == "strided":
        long = rows.select("label", F.posexplode(F.arrays_zip("dy", "xhat")).alias("d", "r"))
        return long.groupBy("label", "d").agg(F.sum("r.dy").alias("grad_shift"), F.sum(F.col("r.dy") * F.col("r.xhat")).alias("grad_scale"))
    n = x.select(F.max(F.size("x"))).first()[0] or 0
    out = None
    for lo in range(0, n, d_tile):  # a hash aggregate per feature tile keeps generated methods small
        hi = min(n, lo + d_tile)
        sums = [F.sum(F.get("dy", F.lit(d))).alias(f"s{d}") for d in range(lo, hi)] + [F.sum(F.get("dy", F.lit(d)) * F.get("xhat", F.lit(d))).alias(f"c{d}") for d in range(lo, hi)]
        part = rows.groupBy("label").agg(*sums)
        cells = F.array(*[F.struct(F.lit(d).alias("d"), F.col(f"s{d}").alias("grad_shift"), F.col(f"c{d}").alias("grad_scale")) for d in range(lo, hi)])
        part = part.select("label", F.inline(cells))
        out = part if out is None else out.unionByName(part)
    return out


_PARTS = "label int, lo int, tile long, gs array<double>, gc array<double>"


def _partials(b: pa.RecordBatch, stats: str, d_tile: int, n_tile: int, acc: str, eps: float) -> pa.RecordBatch:
    """Sums of dy and dy * xhat of each (label, feature tile, token tile) in a batch, rows in their order."""
    kind = np.dtype(acc)
    if stats == "cached":
        xhat = (_matrix(b, "x") - b.column("mu").to_numpy()[:, None]) * b.column("rstd").to_numpy()[:, None]
    else:
        xhat = _normalised(_matrix(b, "x"), eps)[0]
    dy = _matrix(b, "dy")
    coded = b.column("label").dictionary_encode(null_encoding="encode")
    label, tile = np.asarray(coded.indices), b.column("vec_id").to_numpy() // n_tile
    names = coded.dictionary.to_pylist()
    group, place = np.unique(np.column_stack([label, tile]), axis=0, return_inverse=True)
    order = np.argsort(place.ravel(), kind="stable")
    starts = np.searchsorted(place.ravel()[order], np.arange(len(group)))
    rows = []
    for lo in range(0, dy.shape[1], d_tile):
        a = np.add.reduceat(dy[order, lo : lo + d_tile].astype(kind), starts, axis=0)
        c = np.add.reduceat((dy[order, lo : lo + d_tile] * xhat[order, lo : lo + d_tile]).astype(kind), starts, axis=0)
        rows += [(names[int(g[0])], lo, int(g[1]), a[i].astype(float), c[i].astype(float)) for i, g in enumerate(group)]
    types = (pa.int32(), pa.int32(), pa.int64(), pa.list_(pa.float64()), pa.list_(pa.float64()))
    columns = list(zip(*rows, strict=True)) or [[]] * len(types)
    return pa.record_batch([pa.array(col, t) for col, t in zip(columns, types, strict=True)], ["label", "lo", "tile", "gs", "gc"])


def _used(x: DataFrame, stats: str) -> DataFrame:
    return x.select("vec_id", "label", "x", "dy", *(["mu", "rstd"] if stats == "cached" else []))


def _tiled(x: DataFrame, stats: str, d_tile: int, n_tile: int, acc: str, eps: float) -> DataFrame:
    parts = _arrow(_used(x, stats), lambda b: _partials(b, stats, d_tile, n_tile, acc, eps), _PARTS, ("x", "dy"))
    flat = parts.select("label", "tile", "lo", F.posexplode(F.arrays_zip("gs", "gc")).alias("i", "r"))
    return flat.groupBy("label", (F.col("lo") + F.col("i")).alias("d")).agg(F.sum("r.gs").alias("grad_shift"), F.sum("r.gc").alias("grad_scale"))


def _ordered(x: DataFrame, stats: str, d_tile: int, n_tile: int, acc: str, eps: float, width: int = 1000) -> DataFrame:
    """One partial per (label, feature tile, token tile), merged in the tiles' order in groups of `width`."""
    ship(x.sparkSession)
    kind = "float" if acc == "float32" else "double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []  # the rows of the last tile, which the next batch may go on with
        for b in batches:
            if not b.num_rows:
                continue
            tiles = b.column("vec_id").to_numpy() // n_tile
            cut = int(np.searchsorted(tiles, tiles[-1]))
            if held and (cut or held[-1].column("vec_id")[0].as_py() // n_tile != tiles[0]):
                for whole in pa.Table.from_batches([*held, b.slice(0, cut)]).combine_chunks().to_batches():
                    yield _partials(whole, stats, d_tile, n_tile, acc, eps)
                held = []
            elif cut:
                yield _partials(b.slice(0, cut), stats, d_tile, n_tile, acc, eps)
            held.append(b.slice(cut))
        if held:
            for whole in pa.Table.from_batches(held).combine_chunks().to_batches():
                yield _partials(whole, stats, d_tile, n_tile, acc, eps)

    tile = F.floor(F.col("vec_id") / n_tile).cast("long")
    dealt = _used(x, stats).repartition(tile).sortWithinPartitions("vec_id")
    rows = dealt.mapInArrow(run, _PARTS).select("label", "tile", "lo", F.posexplode(F.arrays_zip("gs", "gc")).alias("i", "r")).select("label", (F.col("lo") + F.col("i")).alias("d"), "tile", F.col("r.gs").alias("gs"), F.col("r.gc").alias("gc"))
    low, high = x.agg(F.min(tile), F.max(tile)).first()
    zero = F.lit(0.0).cast(kind)
    fold = lambda c: F.aggregate(F.array_sort(F.collect_list(F.struct("tile", "gs", "gc"))), zero, lambda a, v: (a + v[c].cast(kind)).cast(kind)).cast("double").alias(c)
    left = (high or 0) - (low or 0) + 1
    while True:  # groups of neighbours, until one is left
        rows = rows.withColumn("up", F.floor((F.col("tile") - F.lit(low or 0)) / width).cast("long")).groupBy("label", "d", "up").agg(fold("gs"), fold("gc")).withColumnRenamed("up", "tile")
        low, left = 0, -(-left // width)
        if left <= 1:
            return rows.select("label", "d", F.col("gs").alias("grad_shift"), F.col("gc").alias("grad_scale"))


def grad_input(x: DataFrame, params: DataFrame, eps: float = EPS, scale_offset: float = 1.0) -> DataFrame:
    """vec_id, dx = rstd * (g - mean(g) - xhat * mean(g * xhat)) with g = dy * (scale_offset + scale). Narrow but for the parameters."""

    def kernel(b: pa.RecordBatch) -> pa.RecordBatch:
        xhat, _, rstd = _normalised(_matrix(b, "x"), eps)
        g = _matrix(b, "dy") * (scale_offset + _matrix(b, "scale"))
        dx = rstd[:, None] * (g - g.mean(axis=1, keepdims=True) - xhat * (g * xhat).mean(axis=1, keepdims=True))
        return pa.record_batch({"vec_id": b.column("vec_id"), "dx": _vectors(dx)})

    return _arrow(_with_params(x, params, "scale").select("vec_id", "x", "dy", "scale"), kernel, "vec_id long, dx array<double>", ("x", "dy", "scale"))


def qk_norm(x: DataFrame, q: str, k: str, heads: int = 4, kind: str = "rms", eps: float = EPS, impl: str = "arrow", weight_q: list[float] | None = None, weight_k: list[float] | None = None) -> DataFrame:
    """M35, Bl7: vec_id, q, k normalised per head in one pass. kind: rms (divide by the root mean square) or layer. discrete: long form."""
    if impl == "discrete":
        out = None
        for name, col, weight in (("q", q, weight_q), ("k", k, weight_k)):
            long = x.select("vec_id", F.size(col).alias("n"), F.posexplode(col).alias("d", "v")).withColumn("head", F.floor(F.col("d") * heads / F.col("n")))
            stat = long.groupBy("vec_id", "head").agg(F.avg("v").alias("mu"), F.avg(F.col("v") * F.col("v")).alias("sq"))
            y = long.join(stat, ["vec_id", "head"])
            value = F.col("v") / F.sqrt(F.col("sq") + eps) if kind == "rms" else (F.col("v") - F.col("mu")) / F.sqrt(F.greatest(F.col("sq") - F.col("mu") * F.col("mu"), F.lit(0.0)) + eps)
            if weight:
                value = value * F.get(F.array(*[F.lit(w) for w in weight]), F.col("d"))
            part = y.withColumn("y", value).groupBy("vec_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("d", "y"))), lambda r: r["y"]).alias(name))
            out = part if out is None else out.join(part, "vec_id")
        return out

    def kernel(b: pa.RecordBatch) -> pa.RecordBatch:
        out = {"vec_id": b.column("vec_id")}
        for name, col, weight in (("q", q, weight_q), ("k", k, weight_k)):
            m = _matrix(b, col)
            h = m.reshape(len(m), heads, -1)
            if kind == "layer":
                h = h - h.mean(axis=2, keepdims=True)
            y = (h / np.sqrt((h * h).mean(axis=2, keepdims=True) + eps)).reshape(m.shape)
            out[name] = _vectors(y * np.array(weight) if weight else y)
        return pa.record_batch(out)

    return _arrow(x.select("vec_id", q, *([k] if k != q else [])), kernel, "vec_id long, q array<double>, k array<double>", (q, k, "q", "k"))


def gate_norm(x: DataFrame, branch: str, params: DataFrame, order: str = "norm_then_gate", eps: float = EPS, impl: str = "arrow") -> DataFrame:
    """M36, Bl7: vec_id, y. norm_then_gate: x + gate * norm(branch); gate_then_norm: norm(x + gate * branch)."""
    rows = _with_params(x, params, "gate")
    if impl == "discrete":
        long = rows.select("vec_id", F.posexplode(F.arrays_zip("x", F.col(branch).alias("br"), "gate")).alias("d", "r")).select("vec_id", "d", "r.*")
        value = F.col("br") if order == "norm_then_gate" else F.col("x") + F.col("gate") * F.col("br")
        long = long.withColumn("v", value)
        mean = long.groupBy("vec_id").agg(F.avg("v").alias("mu"))
        centred = long.join(mean, "vec_id")
        var = centred.groupBy("vec_id").agg(F.avg((F.col("v") - F.col("mu")) * (F.col("v") - F.col("mu"))).alias("var"))
        norm = (F.col("v") - F.col("mu")) / F.sqrt(F.col("var") + eps)
        y = F.col("x") + F.col("gate") * norm if order == "norm_then_gate" else norm
        return centred.join(var, "vec_id").withColumn("y1", y).groupBy("vec_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("d", "y1"))), lambda r: r["y1"]).alias("y"))

    def kernel(b: pa.RecordBatch) -> pa.RecordBatch:
        xs, br, gate = _matrix(b, "x"), _matrix(b, "br"), _matrix(b, "gate")
        y = xs + gate * _normalised(br, eps)[0] if order == "norm_then_gate" else _normalised(xs + gate * br, eps)[0]
        return pa.record_batch({"vec_id": b.column("vec_id"), "y": _vectors(y)})

    return _arrow(rows.select("vec_id", "x", F.col(branch).alias("br"), "gate"), kernel, "vec_id long, y array<double>", ("x", "br", "gate", "y"))
