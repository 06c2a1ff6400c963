"""What several operators share: shared-folder staging, word splitting, Arrow helpers, salted ranks."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Upper case ASCII letters become lower case, digits and every non-ASCII byte stay, the rest is a gap.
_ALNUM = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names for checkpoints; a local one only under a local master that names none."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        named = f"file:///tmp/prefix_credit_checkpoints/{sc.applicationId}"
        sc.setCheckpointDir(named)
    return named


def staged(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it back: cuts the lineage and outlives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/staged/{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.staged_path = path
    return out


def unstaged(df: DataFrame) -> None:
    """Delete a staged table that nothing reads any more."""
    jvm = df.sparkSession.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(df.staged_path)
    path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_bytes(column: pa.Array | pa.ChunkedArray) -> Iterator[bytes]:
    """UTF-8 of each text, null as empty, without decoding."""
    for x in column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()):
        yield x.as_py() or b""


def space_words(raw: bytes) -> list[bytes]:
    """Words between ASCII white space (0x20, 0x09-0x0D), A-Z lower-cased."""
    return raw.lower().split()


def alnum_words(raw: bytes) -> list[bytes]:
    """Runs of ASCII letters and digits and of non-ASCII characters, A-Z lower-cased."""
    return raw.translate(_ALNUM).split()


class WordHashes(dict):
    """64-bit hashes of words, kept up to a bound so that a long task stays small."""

    bound = 400_000

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.bound:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def map_arrow(df: DataFrame, f: Callable[[pa.RecordBatch], Iterator[dict] | dict], schema: str) -> DataFrame:
    """mapInArrow with a function from a batch to columns (one dict, or several)."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType, _parse_datatype_string

    kind = _parse_datatype_string(schema) if not isinstance(schema, StructType) else schema
    arrow = to_arrow_schema(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = f(b)
            for cols in [got] if isinstance(got, dict) else got:
                yield pa.RecordBatch.from_arrays([c if isinstance(c := cols[x.name], pa.Array) and c.type == x.type else pa.array(c, x.type, from_pandas=isinstance(c, np.ndarray) and c.dtype == object) for x in arrow], schema=arrow)

    return df.mapInArrow(run, kind)


def keep_where(df: DataFrame, text_col: str, f: Callable[[Iterator[bytes]], list[bool]]) -> DataFrame:
    """Rows, all columns as they are, whose text `f` (over a batch's texts) keeps: no join, so ids don't matter."""
    place = df.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array(f(text_bytes(b.column(place))), pa.bool_()))

    return df.mapInArrow(run, df.schema)
