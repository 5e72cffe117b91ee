"""Building and searching indexes: one packed row a shard, so a search scans the shards it needs and moves only results."""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import store
from . import exact, kernels
from .exact import ranked, vectors
from .methods import IntervalGraph, Method, Query

PACKED = "shard int, n long, lo_min double, lo_max double, hi_min double, hi_max double, blob binary"
SHARD_LIMIT = 2_000_000  # objects; a shard is one task's memory


def _shard(table) -> kernels.Shard:
    ids = table.column("id").to_numpy()
    order = np.argsort(ids, kind="stable")
    return kernels.Shard(ids[order], vectors(table.column("vec"))[order], *(table.column(c).to_numpy()[order] for c in ("lo", "hi")))


def _dump(**arrays: np.ndarray) -> bytes:
    out = io.BytesIO()
    np.savez(out, **arrays)
    return out.getvalue()


def _load(blob: bytes) -> tuple[kernels.Shard, dict[str, np.ndarray]]:
    with np.load(io.BytesIO(blob)) as z:
        data = {k: z[k] for k in z.files}
    return kernels.Shard(data.pop("ids"), data.pop("x").astype(np.float64), data.pop("lo"), data.pop("hi")), data


def build(objects: DataFrame, method: Method, shard: Column | None = None, shards: int | None = None) -> DataFrame:
    """The packed index: every shard of the objects is built in one task, of its own where their number is given."""
    dealt = objects.select((F.lit(0) if shard is None else shard).cast("int").alias("shard"), F.col("id").cast("long").alias("id"), "vec", F.col("lo").cast("double").alias("lo"), F.col("hi").cast("double").alias("hi"))

    def make(table: pa.Table) -> pa.Table:
        if table.num_rows > SHARD_LIMIT:
            raise ValueError(f"a shard has {table.num_rows} objects; use more shards")
        s = _shard(table)
        single = s.x.astype(np.float32)
        blob = _dump(ids=s.ids, x=single if (single == s.x).all() else s.x, lo=s.lo, hi=s.hi, **method.build(s))
        row = [[table.column("shard")[0].as_py()], [len(s.ids)], [s.lo.min()], [s.lo.max()], [s.hi.min()], [s.hi.max()], [blob]]
        return pa.table(row, schema=pa.schema([("shard", pa.int32()), ("n", pa.int64()), *((c, pa.float64()) for c in ("lo_min", "lo_max", "hi_min", "hi_max")), ("blob", pa.binary())]))

    if shards is None:
        return dealt.groupBy("shard").applyInArrow(make, PACKED)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [b for b in batches if b.num_rows]
        if not rows:
            return
        table = pa.Table.from_batches(rows)
        for number in pc.unique(table.column("shard")).to_pylist():
            yield from make(table.filter(pc.equal(table.column("shard"), number))).to_batches()

    # Dealt out by number: small shards would else be put together in one task.
    return dealt.repartitionById(shards, "shard").mapInArrow(each, PACKED)


def edges(packed: DataFrame) -> DataFrame:
    """(shard, src, dst, d, bits) of a packed graph; d is squared."""

    def out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for number, blob in zip(batch.column("shard").to_pylist(), batch.column("blob").to_pylist(), strict=True):
                s, data = _load(blob)
                n = len(data["src"])
                d = data["d"] if "d" in data else s.sq(data["src"], data["dst"])
                bits = data.get("bits", np.full(n, 3))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, number, np.int32)), pa.array(s.ids[data["src"]]), pa.array(s.ids[data["dst"]]), pa.array(d), pa.array(bits.astype(np.int32))], names=["shard", "src", "dst", "d", "bits"])

    return packed.select("shard", "blob").mapInArrow(out, "shard int, src long, dst long, d double, bits int")


def repairs(packed: DataFrame) -> DataFrame:
    """(src, dst): witness and lost candidate of the last round."""

    def out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for blob in batch.column("blob").to_pylist():
                s, data = _load(blob)
                yield pa.RecordBatch.from_arrays([pa.array(s.ids[data["repair_src"]]), pa.array(s.ids[data["repair_dst"]])], names=["src", "dst"])

    return packed.select("blob").mapInArrow(out, "src long, dst long")


def wanted(packed: DataFrame, block: list) -> DataFrame:
    """The shards that can hold a valid object of one of the queries (at most a block of them)."""
    asked = packed.sparkSession.createDataFrame([(r["ql"], r["qr"], r["mode"]) for r in block], "ql double, qr double, mode string")
    shards = store.routed(asked, packed).select("shard").distinct()
    return packed.join(F.broadcast(shards), "shard", "left_semi")


def search(packed: DataFrame, queries: DataFrame, ef: int, method: Method | None = None, effort: bool = False) -> DataFrame:
    """(qid, rank, id, d) of every query; with ``effort`` (qid, shards, hops, edges, distances) instead.

    Queries are broadcast in blocks; a task answers those that can have a valid object in the shards it reads. Where
    there are fewer shards than the cluster has places, several tasks share a shard's queries.
    """
    method = method or IntervalGraph()
    found = None
    shards = packed.select("shard").count()
    share = max(1, packed.sparkSession.sparkContext.defaultParallelism // max(1, shards))
    for block in exact._blocks_of(queries):
        for r in block:
            if r["ql"] > r["qr"]:
                raise ValueError(f"query {r['qid']}: its range is inverted")
        shared = packed.sparkSession.sparkContext.broadcast([(r["qid"], np.array(r["qvec"], np.float64), r["ql"], r["qr"], r["k"], r["mode"]) for r in block])

        def answer(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in range(batch.num_rows):
                    b = {c: batch.column(c)[row].as_py() for c in ("lo_min", "lo_max", "hi_min", "hi_max", "blob", "part")}
                    s, data = _load(b.pop("blob"))
                    out: list[tuple] = []
                    for qid, q, ql, qr, k, mode in shared.value[b["part"] :: share]:
                        if mode == "within" and (b["lo_max"] < ql or b["hi_min"] > qr) or mode == "covers" and (b["lo_min"] > ql or b["hi_max"] < qr):
                            continue
                        got, cost = method.search(s, data, Query(q, ql, qr, k, mode, ef))
                        if effort:
                            out.append((qid, 1, cost.get("hops", 0), cost.get("edges", 0), cost.get("distances", 0)))
                        else:
                            out.extend((qid, int(s.ids[i]), float(np.sqrt(((s.x[i] - q) ** 2).sum()))) for i in got)
                    types = [pa.int64()] * 5 if effort else [pa.int64(), pa.int64(), pa.float64()]
                    names = ["qid", "shards", "hops", "edges", "distances"] if effort else ["qid", "id", "d"]
                    yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(types)], names=names)

        # Shards that no query of the block can need are left out before their blobs reach a worker.
        read = wanted(packed, block).select("shard", "lo_min", "lo_max", "hi_min", "hi_max", "blob", F.explode(F.sequence(F.lit(0), F.lit(share - 1))).alias("part"))
        part = read.repartitionById(shards * share, F.col("shard") * share + F.col("part")).drop("shard").mapInArrow(answer, "qid long, shards long, hops long, edges long, distances long" if effort else exact.RESULT)
        found = part if found is None else found.union(part)
    if found is None:
        found = packed.sparkSession.createDataFrame([], exact.RESULT)
    if effort:
        return found.groupBy("qid").agg(*[F.sum(c).alias(c) for c in ("shards", "hops", "edges", "distances")])
    return ranked(found, queries)
