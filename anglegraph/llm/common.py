"""Helpers shared by the operators: plan sizes, shared scratch tables, document blocks."""

from __future__ import annotations

import atexit
import io
import tempfile
import uuid

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BLOCK_BYTES = 16 << 20
_roots: dict[str, SparkSession] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a local one only where the session names none."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = "file://" + tempfile.gettempdir() + "/anglegraph-checkpoints"
    return base.rstrip("/")


def _remove_scratch() -> None:
    for path, spark in list(_roots.items()):
        try:
            p = spark._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # the session is gone; its scratch stays for the cluster's own cleaner
            pass
    _roots.clear()


atexit.register(_remove_scratch)


def written(df: DataFrame, name: str) -> DataFrame:
    """Cut lineage: write a table in the shared folder (zstd) and read it again."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    schema = df.schema
    df.write.option("compression", "zstd").parquet(path)
    _roots[path] = spark
    out = spark.read.schema(schema).parquet(path)
    out._scratch = path
    return out


def dropped(*tables: DataFrame) -> None:
    """Delete `written` tables that nothing will read again, and the shuffle files that led to them."""
    for df in tables:
        path = df._scratch
        spark = _roots.pop(path, None)
        if spark is not None:
            p = spark._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
    if tables:
        release(tables[0].sparkSession)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner drop the shuffle files of steps that are written and no longer referred to."""
    import gc

    gc.collect()
    spark._jvm.System.gc()


def plan_bytes(df: DataFrame, column: str = "text") -> int:
    """Bytes at rest of what the plan reads, as the optimizer knows them, or a sum over the column."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    size = sum(int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size()))
    if size > 1 << 58:
        size = df.agg(F.sum(F.octet_length(column))).first()[0] or 0
    return size


def n_blocks(df: DataFrame, target: int = BLOCK_BYTES) -> int:
    """Parts of about `target` bytes, counting 2 bytes of text for each one at rest."""
    return max(1, -(-2 * plan_bytes(df) // target))


def row_ranges(offsets, limit: int):
    """Consecutive row ranges whose bytes stay under the limit, single long rows apart."""
    start, n = 0, len(offsets) - 1
    while start < n:
        end = start + 1
        while end < n and offsets[end + 1] - offsets[start] <= limit:
            end += 1
        yield start, end
        start = end


def pack_blocks(docs: DataFrame, blocks: int, level: int = 3) -> DataFrame:
    """Documents as zstd fragments (block, part), dealt by block; rows keep every field given."""
    keyed = docs.withColumn("_block", F.pmod(F.xxhash64(*docs.columns[:2]), F.lit(blocks)).cast("int"))

    def pack(batches):
        import zstandard

        squeeze = zstandard.ZstdCompressor(level=level)
        held, size = [], 0

        def flush():
            table = pa.Table.from_batches(held).combine_chunks()
            order = pc.sort_indices(table, sort_keys=[("_block", "ascending")])
            table = table.take(order)
            block = table.column("_block").to_numpy()
            table = table.drop_columns(["_block"])
            cuts = [0, *((block[1:] != block[:-1]).nonzero()[0] + 1).tolist(), len(block)]
            for a, b in zip(cuts, cuts[1:]):
                sink = io.BytesIO()
                part = table.slice(a, b - a).combine_chunks()
                with pa.ipc.new_stream(sink, part.schema) as out:
                    out.write_table(part)
                yield pa.RecordBatch.from_pydict({"block": pa.array([block[a]], pa.int32()), "part": pa.array([squeeze.compress(sink.getvalue())], pa.binary())})

        for batch in batches:
            held.append(batch)
            size += batch.nbytes
            if size > 32 << 20:
                yield from flush()
                held, size = [], 0
        if held and sum(b.num_rows for b in held):
            yield from flush()

    return keyed.mapInArrow(pack, "block int, part binary").repartition(blocks, "block")


def unpack(parts: pa.Table) -> pa.Table:
    """The rows of a block from its fragments, in an order that does not depend on arrival."""
    import zstandard

    expand = zstandard.ZstdDecompressor()
    blobs = sorted(p.as_py() for p in parts.column("part"))
    tables = [pa.ipc.open_stream(expand.decompress(b)).read_all() for b in blobs]
    return pa.concat_tables(tables).combine_chunks()


def arrow_schema(ddl: str) -> pa.Schema:
    """The Arrow schema of a DDL string; made on the driver, used in tasks."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    return to_arrow_schema(StructType.fromDDL(ddl))
