"""Build partial summaries in Arrow workers, merge them along a tree, answer quantiles. Only summaries cross a shuffle."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankspark import exact, shipping, synopsis, theory
from rankspark.params import ExecutionSpec, MethodSpec, fraction
from rankspark.sources import long_codec, require_numeric

SUMMARY = "method string, node long, n long, n_null long, eps double, vmin double, vmax double, payload binary, bytes long"
#: Groups that one worker holds at once; more are sent on and merged later.
MOST_GROUPS = 20_000
#: Partial summaries to expect where the number of partitions is not given: the tree has the depth for so many, so that no merge
#: takes more than `fan_in` summaries of a group.
NODES = 1 << 20
#: Chunks that each partial gets when sorted rows are dealt in turn.
CHUNKS = 8
#: Values in a packed row, about, and values that a worker holds while it packs.
BLOCK, MOST_PACKED = 1 << 17, 1 << 22
PACKED = [("piece", pa.int32()), ("seq", pa.int64()), ("nulls", pa.int64()), ("kind", pa.string()), ("held", pa.string()), ("block", pa.binary())]


def shaped(df: DataFrame, column: str, spec: ExecutionSpec) -> DataFrame:
    """The number of partitions and the order of arrival, if asked for; else the input's own, without a shuffle.

    Rows are dealt by their places, never by their values: one value meets all partials. "random": by a hash of a row's place.
    "sorted": the increasing order is cut into consecutive chunks, and chunk c goes to partial c mod `partitions`.
    Packed rows go by whole pieces, to the same chunks."""
    k = spec.partitions
    if spec.pieces:
        partial = F.pmod(F.floor(F.col("piece") / F.lit(spec.pieces // k)), F.lit(k)).cast("int")
        return df.repartitionById(k, partial).sortWithinPartitions("seq", "piece")
    if k and spec.order == "sorted":
        chunk = df.repartitionByRange(k * CHUNKS, column).withColumn("__chunk", F.spark_partition_id())
        df = chunk.repartitionById(k, F.pmod("__chunk", F.lit(k)).cast("int")).drop("__chunk")
    elif k:
        df = df.repartition(k) if spec.order == "stored" else df.withColumn("__place", F.xxhash64(F.monotonically_increasing_id())).repartition(k, "__place").drop("__place")
    return df.sortWithinPartitions(column) if spec.order == "sorted" else df


def pack(df: DataFrame, column: str, pieces: int, order: str) -> DataFrame:
    """All values of a column as blocks, so that rows are dealt and sorted once for every number of partials that divides
    `pieces`. "random": a piece takes rows by a hash of their places; "sorted": a piece is a chunk of the increasing order."""
    shipping.ensure(df.sparkSession)
    require_numeric(df, column)
    rows, by_place = df.select(column), order != "sorted"
    if not by_place:
        rows = rows.repartitionByRange(pieces * CHUNKS, column).sortWithinPartitions(column).withColumn("__chunk", F.spark_partition_id()).coalesce(pieces)
    full, schema = min(MOST_PACKED, pieces * BLOCK) if by_place else BLOCK, pa.schema(PACKED)

    def build(batches: Iterator[pa.RecordBatch]):
        task, waiting, size, nulls, place, flushes = TaskContext.get().partitionId(), [], 0, 0, 0, 0

        def packed():
            x, *chunk = (np.concatenate(a) for a in zip(*waiting, strict=True))
            if not by_place:  # a chunk's values come one after the other
                first = np.flatnonzero(np.diff(chunk[0], prepend=-1))
                cuts = list(zip(chunk[0][first].tolist(), np.split(x, first[1:]), strict=True))
            else:
                to = (mixed(np.arange(place, place + len(x), dtype=np.uint64) + np.uint64(task << 40)) % np.uint64(pieces)).astype(np.uint16 if pieces <= 1 << 16 else np.int64)
                ends = np.cumsum(np.bincount(to, minlength=pieces))
                cuts = list(enumerate(np.split(x[np.argsort(to, kind="stable")], ends[:-1])))
            rows = []
            for piece, part in cuts or [(0, x)]:
                if len(part) or not rows:
                    narrow = part.dtype.kind == "i" and len(part) and -(1 << 31) <= part.min() and part.max() < 1 << 31
                    held = part.astype("<i4") if narrow else part
                    rows.append((piece, (task if by_place else piece) << 32 | flushes, 0 if rows else nulls, part.dtype.str, held.dtype.str, held.tobytes()))
            return _batch(rows, schema)

        for b in batches:
            nulls += b.column(0).null_count
            waiting.append([c.to_numpy(zero_copy_only=False) for c in (b if not b.column(0).null_count else b.filter(b.column(0).is_valid())).columns])
            size += len(waiting[-1][0])
            if size >= full:
                yield packed()
                waiting, size, nulls, place, flushes = [], 0, 0, place + size, flushes + 1
        if waiting:
            yield packed()

    return rows.mapInArrow(build, ", ".join(f"{name} {kind}" for name, kind in zip([n for n, _ in PACKED], ("int", "long", "long", "string", "string", "binary"), strict=True)))


@contextmanager
def batched_by_rows(spark) -> Iterator[None]:
    """Arrow batches end at their number of rows alone, not at a number of bytes, which Spark adds up anew at every row: for
    plans over plain numbers that run inside."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key, None)
    spark.conf.set(key, str((1 << 31) - 1))
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


def mixed(x: np.ndarray) -> np.ndarray:
    """A hash of unsigned 64-bit integers: shifts and odd factors in turn."""
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def _arrays(b: pa.RecordBatch, packed: bool) -> Iterator[tuple[int, np.ndarray]]:
    """Nulls and values of plain or packed rows."""
    if not packed:
        yield b.column(0).null_count, b.column(0).drop_null().to_numpy(zero_copy_only=False)
        return
    blocks = b.column("block")
    for i, (nulls, kind, held) in enumerate(zip(*[b.column(c).to_pylist() for c in ("nulls", "kind", "held")], strict=True)):
        yield nulls, np.frombuffer(blocks[i].as_buffer(), held).astype(kind)


def _row(spec: MethodSpec, node: int, s: synopsis.Synopsis, nulls: int, low: float, high: float) -> tuple:
    payload = s.pack()
    return spec.method, node, s.n, nulls, float(spec.eps), low, high, payload, len(payload)


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], f.type) for i, f in enumerate(schema)], schema=schema)


def _types(by_fields) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_type

    fixed = [("method", pa.string()), ("node", pa.int64()), ("n", pa.int64()), ("n_null", pa.int64()), ("eps", pa.float64()), ("vmin", pa.float64()), ("vmax", pa.float64()), ("payload", pa.binary()), ("bytes", pa.int64())]
    return pa.schema([(f.name, to_arrow_type(f.dataType)) for f in by_fields] + fixed)


def summarize(df: DataFrame, column: str, spec: MethodSpec, by: list[str] | None = None, run: ExecutionSpec = ExecutionSpec()) -> DataFrame:
    """One summary row for each partition and group. One narrow pass over the measured column and the keys."""
    shipping.ensure(df.sparkSession)
    require_numeric(df, column)
    by = by or []
    pruned = shaped(df.select(*by, column), column, run)
    fields = [df.schema[b] for b in by]

    def build(batches: Iterator[pa.RecordBatch]):
        node, schema = TaskContext.get().partitionId(), _types(fields)
        held: dict[tuple, list] = {}

        def finished():
            rows = []
            for key, (s, nulls, low, high) in held.items():
                s.end_chunk()
                s.local_finalize()
                rows.append((*key, *_row(spec, node, s, nulls, low, high)))
            held.clear()
            return _batch(rows, schema)

        for b in batches:
            parts = [((), b.column(b.num_columns - 1))]
            if by:
                t = pa.Table.from_batches([b]).append_column("__at", pa.array(np.arange(b.num_rows)))
                lists = t.group_by(by, use_threads=False).aggregate([("__at", "list")])
                keys = zip(*[lists[k].to_pylist() for k in by], strict=True)
                parts = [(k, b.column(b.num_columns - 1).take(at.values)) for k, at in zip(keys, lists["__at_list"], strict=True)]
            for key, values in parts:
                if key not in held:
                    held[key] = [synopsis.new(spec, node), 0, float("inf"), float("-inf")]
                    held[key][0].begin_chunk()
                state = held[key]
                state[1] += values.null_count
                x = values.drop_null().to_numpy(zero_copy_only=False)
                if x.dtype.kind == "f":
                    x = x[~np.isnan(x)]
                if len(x):
                    state[0].absorb(x)
                    state[2], state[3] = min(state[2], float(x.min())), max(state[3], float(x.max()))
            if len(held) > MOST_GROUPS:
                yield finished()
        yield finished()

    keys = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in fields)
    return pruned.mapInArrow(build, keys + SUMMARY)


def summarize_each(df: DataFrame, column: str, specs: list[MethodSpec], run: ExecutionSpec = ExecutionSpec()) -> DataFrame:
    """Summaries by several specs from one pass: a row for each partition and spec, with the spec's place in the list as `spec`."""
    shipping.ensure(df.sparkSession)
    packed = run.pieces is not None
    if not packed:
        require_numeric(df, column)
        df = df.select(column)

    def build(batches: Iterator[pa.RecordBatch]):
        node, held, nulls, low, high = TaskContext.get().partitionId(), [], 0, float("inf"), float("-inf")
        for b in batches:
            if not held:
                held = [synopsis.new(spec, node) for spec in specs]
                for s in held:
                    s.begin_chunk()
            for none, x in _arrays(b, packed):
                nulls += none
                if x.dtype.kind == "f":
                    x = x[~np.isnan(x)]
                if len(x):
                    low, high = min(low, float(x.min())), max(high, float(x.max()))
                    for s in held:
                        s.absorb(x)
        for i, s in enumerate(held):
            s.end_chunk()
            s.local_finalize()
            yield _batch([(i, *_row(specs[i], node, s, nulls, low, high))], schema)

    schema = pa.schema([("spec", pa.int32()), *_types([])])
    return shaped(df, column, run).mapInArrow(build, "spec int, " + SUMMARY)


def merge_summaries(summaries: DataFrame, by: list[str] | None = None, fan_in: int = 32, nodes: int | None = None) -> DataFrame:
    """One row for each group: levels of groupBy(node div fan_in), each a shuffle of summaries only."""
    by = by or []
    shipping.ensure(summaries.sparkSession)
    nodes = nodes or NODES
    fields = [summaries.schema[b] for b in by]
    schema_text = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in fields) + SUMMARY

    def join(table: pa.Table) -> pa.Table:
        rows = sorted(table.to_pylist(), key=lambda r: r["node"])
        first = synopsis.unpack(rows[0]["payload"])
        for r in rows[1:]:
            first.merge(synopsis.unpack(r["payload"]))
        payload = first.pack()
        out = {**rows[0], "node": rows[0]["node"] // fan_in, "n": first.n, "n_null": sum(r["n_null"] for r in rows), "vmin": min(r["vmin"] for r in rows), "vmax": max(r["vmax"] for r in rows), "payload": payload, "bytes": len(payload)}
        return pa.Table.from_pylist([out], schema=_types(fields))

    while nodes > fan_in:
        summaries = summaries.groupBy(*by, F.floor(F.col("node") / fan_in).alias("up")).applyInArrow(join, schema_text)
        nodes = -(-nodes // fan_in)
    return summaries.groupBy(*by, F.lit(0).alias("up")).applyInArrow(join, schema_text)  # whatever is left of a group, so that one row remains


def merge_components(summaries: DataFrame, by: list[str] | None = None, fan_in: int = 32, nodes: int | None = None, height: int | None = None) -> DataFrame:
    """Rank samples in two stages: a tree inside each component of `height` neighbouring nodes, then a flat sum of the components."""
    by, nodes = by or [], nodes or NODES
    height = height or theory.tree_height(nodes, fan_in)
    count, fields = -(-nodes // height), [summaries.schema[b] for b in by]
    parted = summaries.withColumn("component", F.floor(F.col("node") / height)).withColumn("node", F.pmod("node", F.lit(height)))
    inside = merge_summaries(parted, [*by, "component"], fan_in, height)

    def leave(batches: Iterator[pa.RecordBatch]):
        for b in batches:
            rows = b.to_pylist()
            for r in rows:
                s = synopsis.unpack(r["payload"])
                s.leave_component(count)
                r["node"], r["payload"] = r["component"], s.pack()
                r["bytes"] = len(r["payload"])
            schema = _types(fields)
            yield _batch([tuple(r[name] for name in schema.names) for r in rows], schema)

    keys = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in fields)
    return merge_summaries(inside.mapInArrow(leave, keys + SUMMARY), by, fan_in, count)


def answer(merged: DataFrame, phis: list[tuple[int, int]], by: list[str] | None = None, whole: bool = False, **how) -> DataFrame:
    """by..., phi_num, phi_den, value, n, eps. With `whole` the value is a long, and r_lo and r_hi bound how many values are
    not larger than it."""
    by = by or []
    fields = [merged.schema[b] for b in by]
    more = ", r_lo long, r_hi long" * whole
    kind = (pa.int64(), int) if whole else (pa.float64(), float)

    def ask(batches: Iterator[pa.RecordBatch]):
        from pyspark.sql.pandas.types import to_arrow_type

        bounds = [("r_lo", pa.int64()), ("r_hi", pa.int64())] * whole
        schema = pa.schema([(f.name, to_arrow_type(f.dataType)) for f in fields] + [("phi_num", pa.int32()), ("phi_den", pa.int32()), ("value", kind[0]), ("n", pa.int64()), ("eps", pa.float64()), *bounds])
        for b in batches:
            rows = []
            for r in b.to_pylist():
                s = synopsis.unpack(r["payload"])
                for (a, d), v in zip(phis, s.query(phis, **how), strict=True):
                    span = () if not whole else (None, None) if v is None else s.rank(v)
                    rows.append((*[r[k] for k in by], a, d, None if v is None else kind[1](v), r["n"], r["eps"], *span))
            yield _batch(rows, schema)

    keys = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in fields)
    return merged.mapInArrow(ask, keys + f"phi_num int, phi_den int, value {'long' if whole else 'double'}, n long, eps double" + more)


def quantiles(df: DataFrame, column: str, phis: list[tuple[int, int]], eps, method: str = "gap", by: list[str] | None = None, run: ExecutionSpec = ExecutionSpec(), how: dict | None = None, **options) -> DataFrame:
    """The whole cycle as one lazy plan."""
    spec = MethodSpec.of(method, eps, **options)
    nodes, parts = run.partitions or NODES, summarize(df, column, spec, by, run)
    merged = merge_components(parts, by, run.fan_in, run.partitions or options.get("nodes")) if options.get("mode") == "components" else merge_summaries(parts, by, run.fan_in, nodes)
    return answer(merged, phis, by, **(how or {}))


def typed_quantiles(df: DataFrame, column: str, phis: list[tuple[int, int]], eps, by: list[str] | None = None, run: ExecutionSpec = ExecutionSpec(), mode: str = "batch") -> DataFrame:
    """by..., phi_num, phi_den, value, n, eps, r_lo, r_hi by the gap summary, for columns whose order a long can carry: integers of
    any size, dates, timestamps, decimals of up to 18 digits. Values keep the column's type."""
    encode, decode = long_codec(df.schema[column].dataType)
    rows = df.select(*(by or []), encode(F.col(column)).alias(column))
    merged = merge_summaries(summarize(rows, column, MethodSpec.of("gap", eps, mode=mode), by, run), by, run.fan_in, run.partitions)
    return answer(merged, phis, by, whole=True).withColumn("value", decode(F.col("value")))


def refresh(stored: DataFrame, new: DataFrame, column: str, spec: MethodSpec, by: list[str] | None = None, run: ExecutionSpec = ExecutionSpec()) -> DataFrame:
    """Stored summary rows with the summaries of new data merged in; the old data are not read."""
    return merge_summaries(stored.unionByName(summarize(new, column, spec, by, run)), by, run.fan_in, run.partitions or NODES)


def guaranteed(df: DataFrame, column: str, phis: list[tuple[int, int]], eps, answers: DataFrame, factor: int = 1) -> DataFrame:
    """phi_num, phi_den, exact_value, within_eps: answers of a deterministic summary held against the data."""
    ranks = exact.ranks_of(df, column, answers)
    e = fraction(eps) * factor
    told = answers.select("phi_num", "phi_den", "value").join(ranks, "value").withColumn("r", F.expr("phi_num * n div phi_den"))
    off = F.greatest(F.lit(0), F.col("below") - F.col("r"), F.col("r") - F.greatest(F.col("upto") - 1, F.col("below")))
    told = told.select("phi_num", "phi_den", (off * e.denominator <= F.col("n") * e.numerator).alias("within_eps"))
    true = exact.exact_quantiles(df, column, phis).select("phi_num", "phi_den", F.col("value").cast("double").alias("exact_value"))
    return true.join(told, ["phi_num", "phi_den"])


def errors(df: DataFrame, column: str, answers: DataFrame, keys: list[str]) -> DataFrame:
    """keys..., avg_err, max_err: rank errors of any number of answer sets in one pass over the data."""
    return errors_by(exact.ranks_of(df, column, answers), answers, keys)


def errors_by(ranks: DataFrame, answers: DataFrame, keys: list[str]) -> DataFrame:
    """The same from ranks (value, below, upto, n) of all answers."""
    told = answers.drop("n").join(ranks, "value").withColumn("err", exact.rank_error(F.expr("phi_num * n div phi_den"), F.col("below"), F.col("upto"), F.col("n")))
    return told.groupBy(*keys).agg(F.avg("err").alias("avg_err"), F.max("err").alias("max_err"), F.count_if(F.col("err") > F.col("eps")).alias("violations"))


def packed_ranks(packed: DataFrame, probes: DataFrame) -> DataFrame:
    """value, below, upto, n for each probe, as `exact.ranks_of`, from all values of packed rows: each block is sorted, and the
    probes, which come as one array beside it, are looked up in it."""
    shipping.ensure(packed.sparkSession)
    ordered = probes.select(F.col("value").cast("double").alias("p")).distinct().agg(F.array_sort(F.collect_set("p")).alias("ps"))

    def count(batches: Iterator[pa.RecordBatch]):
        wanted, n = np.zeros(0), 0
        for b in batches:
            if not n and b.num_rows:
                wanted = b.column("ps")[0].values.to_numpy()
                below, upto = np.zeros(len(wanted), np.int64), np.zeros(len(wanted), np.int64)
            for _, x in _arrays(b, True):
                x = np.sort(x)
                below += np.searchsorted(x, wanted, side="left")
                upto += np.searchsorted(x, wanted, side="right")
                n += len(x)
        if len(wanted):
            yield pa.RecordBatch.from_arrays([pa.array(wanted), pa.array(below), pa.array(upto), pa.array(np.full(len(wanted), n))], ["value", "below", "upto", "n"])

    told = packed.join(F.broadcast(ordered)).mapInArrow(count, "value double, below long, upto long, n long")
    return told.groupBy("value").agg(*[F.sum(c).alias(c) for c in ("below", "upto", "n")])


def packed_count(packed: DataFrame) -> int:
    """Rows in packed rows, nulls included."""
    width = F.regexp_extract("held", "([0-9]+)$", 1).cast("long")
    return packed.agg(F.coalesce(F.sum(F.col("nulls") + F.expr("octet_length(block)") / width), F.lit(0)).cast("long")).first()[0]


def space(partials: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Bytes of the summaries before merging: in total and of the largest."""
    return partials.groupBy(*(by or [])).agg(F.sum("bytes").alias("total_bytes"), F.max("bytes").alias("max_bytes"), F.count(F.lit(1)).alias("summaries"))
