"""Helpers shared by the corpus operators.

Conventions that hold for every operator here:

* a null text counts as an empty one, a null ``doc_id`` stays null in the result;
* only the named input columns are read, so further columns (whatever their names) do no harm;
* an empty table gives an empty result with the same schema.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

WHITE = rb" \t\n\x0b\x0c\r"  # bytes.split() without arguments splits at exactly these
WORD_SQL = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def lower_ascii(col: Column) -> Column:
    """Lower case for A-Z alone; Spark's own lower() also folds other letters."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Column names that do not clash (Spark's names are case-insensitive) with those of ``df``."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        taken.add(name.lower())
        out.append(name)
    return out


def held_out(doc_id: Column, modulus: int, remainder: int) -> Column:
    """Whether crc32 of the id's decimal text leaves the remainder; a null id is never held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % modulus == remainder, F.lit(False))


def per_document(df: DataFrame, columns: list[str], schema: str, run: Callable[[list[list]], list[list]]) -> DataFrame:
    """Applies ``run`` to Arrow batches: lists of the named columns in, lists of the schema's columns out.

    Row-local, so a lost executor costs its own tasks only. ``run`` sees slices of at most
    ``SLICE_ROWS`` rows, which bounds what one call holds besides the batch itself.
    """
    from pyspark.sql.types import StructType
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(at, SLICE_ROWS)
                out = run([part.column(i).to_pylist() for i in range(part.num_columns)])
                yield pa.RecordBatch.from_arrays([pa.array(v, type=f.type) for v, f in zip(out, arrow, strict=True)], schema=arrow)

    return df.select(*columns).mapInArrow(batches, schema)


SLICE_ROWS = 1024


def training_labels(labels: DataFrame, label: str, modulus: int, remainder: int, bound: int) -> DataFrame:
    """At most ``bound`` labelled ids outside the held-out fold, by smallest hash: (doc_id, label).

    The bound is what makes a broadcast of the result safe. Labels of one id that disagree are
    settled by their mean (ties count as 1); null ids and null labels are left out.
    """
    one = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & ~held_out(F.col("doc_id"), modulus, remainder))
    one = one.groupBy("doc_id").agg((F.avg(label) >= 0.5).cast("int").alias("label"))
    return one.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)


def shared_base(df: DataFrame) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, a local session may use a folder of
    its own (tests); on a cluster that would be wrong data, so it is an error."""
    session = df.sparkSession
    base = session.conf.get("spark.checkpoint.dir", None)
    if not base:
        found = session.sparkContext._jsc.sc().getCheckpointDir()
        base = found.get() if found.isDefined() else None
    if base:
        return base.rstrip("/")
    if not session.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    import tempfile

    session.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="reelspark-"))
    return shared_base(df)


class Scratch:
    """Tables written to the shared folder: they cut lineage, survive lost executors and can be dropped."""

    def __init__(self, df: DataFrame, name: str):
        self.session = df.sparkSession
        self.folder = f"{shared_base(df)}/{name}-{uuid.uuid4().hex}"
        self.made = 0

    def keep(self, df: DataFrame, codec: str = "snappy") -> DataFrame:
        path = f"{self.folder}/{self.made}"
        self.made += 1
        df.write.option("compression", codec).parquet(path)
        out = self.session.read.schema(df.schema).parquet(path)
        out._scratch = path
        return out

    def drop(self, df: DataFrame) -> None:
        """Removes a table that ``keep`` returned and nothing reads any more."""
        jvm = self.session._jvm
        path = jvm.org.apache.hadoop.fs.Path(df._scratch)
        path.getFileSystem(self.session._jsparkSession.sessionState().newHadoopConf()).delete(path, True)
