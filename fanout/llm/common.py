"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space of all operators here: blank, tab, line feed, vertical tab, form feed, carriage return.
BLANKS = r"[\x20\x09-\x0D]+"
#: A key with more than one in so many rows is hot; so there are fewer hot keys than this.
HOT_KEYS = 1_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The Parquet table `name` of the data folder, opened by Spark (any store it can read)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Where that is unset: a temporary one of a local session (tests); a cluster has to name one."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        path = spark.conf.get("spark.checkpoint.dir", None)
        if path is None and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(path or tempfile.mkdtemp(prefix="fanout-"))
    return sc.getCheckpointDir()


def checkpointed(df: DataFrame) -> DataFrame:
    """df with its rows on shared storage: lineage ends here and partition numbers stay what they are."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


#: Paths of the tables that `stored` made and `dropped` has not deleted.
_TABLES: list[str] = []


def stored(df: DataFrame) -> tuple[DataFrame, str]:
    """df written as Parquet to the shared folder and read again, and its path for `dropped`."""
    path = f"{shared_dir(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    _TABLES.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


def tables() -> list[str]:
    """Paths of the tables made by `stored` that are still there."""
    return list(_TABLES)


def dropped(spark: SparkSession, *paths: str) -> None:
    """Deletes tables made by `stored` that no later plan reads."""
    jvm = spark.sparkContext._jvm
    for p in paths:
        if p in _TABLES:
            _TABLES.remove(p)
        path = jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def looked_up(rows: DataFrame, lookup: DataFrame, on: str, n: str = "_n") -> DataFrame:
    """Inner join of rows with lookup, which has each `on` once and in `n` how many rows have it; n does not come along.

    Rows of hot keys stay where they are: fewer than HOT_KEYS keys can have over a 1/HOT_KEYS of the rows, so these are
    sent to all tasks whatever the data. The others are joined by a shuffle in which no key has more than that share.
    Both sides are read twice, so they should be stored tables. Null keys meet nothing.
    """
    total = lookup.agg(F.sum(n)).first()[0] or 0
    hot = F.broadcast(lookup.filter(F.col(n) * HOT_KEYS > total).drop(n))
    rest = lookup.filter(F.col(n) * HOT_KEYS <= total).drop(n)
    return rows.join(hot, on).unionByName(rows.join(hot.select(on), on, "left_anti").join(rest, on))


def whole(text: str | Column = "text") -> Column:
    """A text column with null as the empty text."""
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))
