"""Session helpers shared by the operators."""

from __future__ import annotations

import gc
import os
import tempfile
import uuid

from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Characters of text that Python works on together; a longer text stands alone.
BATCH_CHARS = 2_000_000
#: Bytes of rows that travel to a Python worker at once: its memory must not grow with the texts.
BATCH_BYTES = 4 << 20
#: ASCII white space; everything else belongs to a word.
WORD_GAP = "[\\x20\\x09-\\x0D]+"


def ready(spark: SparkSession) -> None:
    """Let Python workers import this package from the driver's source tree, and bound the rows they get by bytes."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    env = spark.sparkContext.environment
    if root not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (root, env.get("PYTHONPATH", "")) if x)


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share; a temporary one only where the session names none."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not named:
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="graphdelta-checkpoint-"))
        named = sc.getCheckpointDir()
    return named.rstrip("/")


def saved(df: DataFrame, name: str) -> DataFrame:
    """Cut lineage through a Parquet table in the shared folder; a lost executor only re-reads it."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/graphdelta/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def dropped(df: DataFrame) -> None:
    """Delete the files of a table made by ``saved`` once nothing reads it any more."""
    spark = df.sparkSession
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
        if "/graphdelta/" in folder:
            path = jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(conf).delete(path, True)


def released(spark: SparkSession) -> None:
    """Let the driver drop shuffle files of finished jobs now; Spark does so when it collects its garbage."""
    gc.collect()
    spark._jvm.System.gc()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(column: str, modulus: int) -> Column:
    """crc32 of the id's decimal text, modulo ``modulus``; a null id falls in fold 0."""
    return F.coalesce(F.crc32(F.col(column).cast("string").cast("binary")) % modulus, F.lit(0))


def lower_ascii(column: Column) -> Column:
    return F.translate(column, UPPER, UPPER.lower())


def words(column: Column) -> Column:
    """Words of a text after lower-casing A-Z only; null and blank texts give an empty array."""
    return F.filter(F.split(lower_ascii(F.coalesce(column, F.lit(""))), WORD_GAP), lambda w: w != "")


def runs(texts: list[str | None], most: int = BATCH_CHARS) -> Iterator[list[str]]:
    """Stretches of a list, nulls as empty texts, of about ``most`` characters each."""
    run, size = [], 0
    for text in texts:
        text = text or ""
        if run and size + len(text) > most:
            yield run
            run, size = [], 0
        run.append(text)
        size += len(text)
    if run:
        yield run


def map_texts(docs: DataFrame, keep: tuple[str, ...], make: Callable[[list[str]], dict], added: str, most: int = BATCH_CHARS) -> DataFrame:
    """``keep`` columns of every row, untouched, plus the columns ``added`` that ``make`` returns for its text."""
    ready(docs.sparkSession)
    new = StructType.fromDDL(added)

    def work(batches):
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_type

        for batch in batches:
            at = 0
            for texts in runs(batch.column("text").to_pylist(), most):
                part, got = batch.slice(at, len(texts)), make(texts)
                at += len(texts)
                made = [got[f.name] if isinstance(got[f.name], pa.Array) else pa.array(got[f.name], type=to_arrow_type(f.dataType)) for f in new]
                columns = [part.column(k) for k in keep] + made
                yield pa.RecordBatch.from_arrays(columns, names=[*keep, *new.names])

    kept = docs.select(*keep)
    return docs.select(*dict.fromkeys((*keep, "text"))).mapInArrow(work, StructType([*kept.schema, *new]))


def filter_texts(docs: DataFrame, test: Callable[[list[str]], list[bool]]) -> DataFrame:
    """The rows, with all their columns as they are, whose text passes ``test``."""
    ready(docs.sparkSession)

    def work(batches):
        import pyarrow as pa

        for batch in batches:
            passed = [bool(x) for texts in runs(batch.column("text").to_pylist()) for x in test(texts)]
            yield batch.filter(pa.array(passed, type=pa.bool_()))

    return docs.mapInArrow(work, docs.schema)
