"""Shared pieces: the shared scratch folder, lineage cuts and connected components."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The columns of ``documents``, in order.
DOCUMENT_COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")

#: White space between words (Java and RE2 syntax): blank and U+0009 to U+000D.
SPACE = r"[ \t\n\x0B\f\r]+"


def scratch_dir(spark: SparkSession) -> str:
    """A new folder name below ``spark.checkpoint.dir``.

    All executors must see that folder. Where the setting is missing, a local session (one machine by
    definition) uses a folder below Spark's warehouse; elsewhere that raises.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = spark.conf.get("spark.sql.warehouse.dir") + "/scratch"
    if "://" not in base and not base.startswith("file:"):
        base = spark._jvm.org.apache.hadoop.fs.Path(base).getFileSystem(spark._jsc.hadoopConfiguration()).makeQualified(
            spark._jvm.org.apache.hadoop.fs.Path(base)
        ).toString()
    return f"{base.rstrip('/')}/kbmap-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    """Delete a scratch folder through Hadoop's file system layer."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


class Cut:
    """Tables written to the shared folder, so that lost executors recompute nothing before them.

    ``cut(df)`` writes and rereads; ``drop(df)`` deletes a table that no later plan reads. Results are read from the
    folder when they are asked for, so what is left of it goes when the driver ends (or by ``close``).
    """

    def __init__(self, spark: SparkSession):
        self.spark, self.root, self.n, self.paths = spark, scratch_dir(spark), 0, {}
        atexit.register(self.close)

    def close(self) -> None:
        if self.spark.sparkContext._jsc is not None:
            remove(self.spark, self.root)

    def __call__(self, df: DataFrame) -> DataFrame:
        path = f"{self.root}/{self.n:04d}"
        self.n += 1
        df.write.mode("overwrite").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(out)] = (out, path)
        return out

    def drop(self, df: DataFrame) -> None:
        held = self.paths.pop(id(df), None)
        if held:
            remove(self.spark, held[1])

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"


def located(docs: DataFrame, cut: Cut, *columns: Column) -> DataFrame:
    """The columns with ``path``, ``file`` (its number) and ``row``: the file that a row comes from and its place there.

    Together these name a row wherever the table is read again, without a shuffle. Tables that no file holds are written first.
    """
    place = [F.col("_metadata.file_path").alias("path"), F.xxhash64("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row")]
    try:
        plain = docs.select(*columns, *place)
        plain.schema  # noqa: B018  resolves the plan
        return plain
    except AnalysisException:
        return cut(docs.select(*columns)).select("*", *place)


def folder_of(folder: str, file: int) -> str:
    return f"{folder}/{file & (1 << 64) - 1:016x}"


def named_whole(system, name: str, target: str) -> None:
    """Give a whole file its name. Every attempt of a task writes the same, so one that comes second does no harm."""
    from pyarrow import fs

    try:
        system.move(name, target)
    except OSError:
        if system.get_file_info(target).type != fs.FileType.File:
            raise


def write_row_sets(rows: DataFrame, folder: str) -> int:
    """Write the row numbers of (file, row) as one small file per input file; returns their number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        held: dict[int, list[np.ndarray]] = {}

        def close(file: int) -> int:
            numbers = np.unique(np.concatenate(held.pop(file)))
            system, at = fs.FileSystem.from_uri(folder_of(folder, file))
            system.create_dir(at, recursive=True)
            with system.open_output_stream(part := f"{at}/{uuid.uuid4().hex}.part") as f:
                f.write(numbers.astype("<i8").tobytes())
            named_whole(system, part, f"{at}/rows")
            return len(numbers)

        n = 0
        for b in batches:
            files, numbers = (b.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            for file in np.unique(files).tolist():
                for done in [f for f in held if f != file]:
                    n += close(done)
                held.setdefault(file, []).append(numbers[files == file])
        for file in list(held):
            n += close(file)
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], ["n"])

    dealt = rows.select("file", "row").repartition("file").sortWithinPartitions("file")
    return dealt.mapInArrow(run, "n long").agg(F.coalesce(F.sum("n"), F.lit(0))).collect()[0][0]


class RowSets:
    """For workers: whether (file, row) pairs are in the sets below a folder; one file's set is held at a time."""

    def __init__(self, folder: str):
        self.folder, self.file, self.numbers = folder, None, np.empty(0, np.int64)

    def mask(self, files: np.ndarray, rows: np.ndarray) -> np.ndarray:
        from pyarrow import fs

        out = np.zeros(len(files), bool)
        for file in np.unique(files).tolist():
            if file != self.file:
                system, at = fs.FileSystem.from_uri(folder_of(self.folder, file))
                there = system.get_file_info(f"{at}/rows").type == fs.FileType.File
                self.numbers = np.frombuffer(system.open_input_file(f"{at}/rows").read(), "<i8") if there else np.empty(0, np.int64)
                self.file = file
            mine = files == file
            out[mine] = np.isin(rows[mine], self.numbers)
        return out


def words(text: Column) -> Column:
    """Array of the words ``[^\\x20\\x09-\\x0D]+``; null text gives an empty array."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), SPACE), lambda w: w != "")


def connected_components(cut: Cut, edges: DataFrame) -> DataFrame:
    """(v, root) for every vertex that an edge (a, b) joins to a smaller one; roots are left out.

    ``root`` is the smallest vertex of the component. Each round hooks every vertex that has a
    smaller neighbour to the smallest of them, flattens the chains by pointer doubling and contracts
    the edges; at least half of the vertices with edges go in each round. Hot vertices meet only
    partial aggregates and joins whose large side Spark can split.
    """
    rest = cut(
        edges.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).where("hi > lo").distinct()
    )
    found = None
    while not rest.isEmpty():
        hook = cut(rest.groupBy("hi").agg(F.min("lo").alias("p")).withColumnRenamed("hi", "v"))
        while True:
            nxt = hook.select(F.col("v").alias("p"), F.col("p").alias("pp"))
            jumped = cut(
                hook.join(nxt, "p", "left").select("v", F.coalesce("pp", "p").alias("p"), F.col("pp").isNotNull().alias("moved"))
            )
            cut.drop(hook)
            hook = jumped
            if hook.where("moved").isEmpty():
                break
        to_hi = hook.select(F.col("v").alias("hi"), F.col("p").alias("x"))
        to_lo = hook.select(F.col("v").alias("lo"), F.col("p").alias("y"))
        contracted = cut(
            rest.join(to_hi, "hi")
            .join(to_lo, "lo", "left")
            .select("x", F.coalesce("y", "lo").alias("y"))
            .where("x <> y")
            .select(F.greatest("x", "y").alias("hi"), F.least("x", "y").alias("lo"))
            .distinct()
        )
        cut.drop(rest)
        rest = contracted
        if found is None:
            found = hook.select("v", F.col("p").alias("root"))
        else:
            later = hook.select(F.col("v").alias("root"), F.col("p").alias("q"))
            found = cut(
                found.join(later, "root", "left")
                .select("v", F.coalesce("q", "root").alias("root"))
                .unionByName(hook.select("v", F.col("p").alias("root")))
            )
    if found is None:
        found = rest.select(F.col("hi").alias("v"), F.col("lo").alias("root"))
    return found
