"""What the operators of this subpackage share: tables in the shared folder, struct-valued Arrow functions, bounded memo tables."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import functools
import tempfile
import uuid
from collections.abc import Callable, Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"
MOST_BYTES = 4 << 20
_made: list[tuple[SparkSession, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where that is unset, a temporary one in local mode; on a cluster an error, as each machine would have its own."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="tallywalk-")
        spark.conf.set("spark.checkpoint.dir", found)
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new path below the shared folder; it is removed when the driver's Python ends."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


def remove(spark: SparkSession, path: str) -> None:
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def forget(spark: SparkSession, table: DataFrame) -> None:
    """Removes a written table that nothing needs any more."""
    gone = {p.rsplit("/", 1)[0].rsplit("/", 1)[1] for p in table.inputFiles()}
    for own in [x for x in _made if x[1].rsplit("/", 1)[1] in gone]:
        _made.remove(own)
        remove(*own)


@atexit.register
def _clear() -> None:
    for spark, path in _made:
        try:
            remove(spark, path)
        except Exception:  # noqa: BLE001  the session has ended before us; the cluster's own cleaning takes over
            return


def written(df: DataFrame, name: str) -> DataFrame:
    """The rows of df, computed once and kept as Parquet in the shared folder: lineage ends there, so a lost executor costs a re-read."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.parquet(path)
    trim_driver(spark)
    return spark.read.schema(df.schema).parquet(path)


def written_alone(make: Callable[[], DataFrame], name: str) -> DataFrame:
    """written(make()), after which all tables that were written on the way are removed."""
    before = len(_made)
    df = make()
    out = written(df, name)
    for spark, path in _made[before:-1]:
        remove(spark, path)
    _made[before:] = _made[-1:]
    return out


def small_batches() -> None:
    """At most MOST_BYTES in an Arrow batch of this session from now on, or what the caller has set below that: texts are long, and a batch is held several times, in the JVM and in
    Python. Spark has no such limit for one query alone."""
    spark = SparkSession.getActiveSession()
    if spark is not None and not 0 < int(spark.conf.get(BATCH_BYTES, None) or 0) <= MOST_BYTES:
        spark.conf.set(BATCH_BYTES, MOST_BYTES)


def unclashing(keys: list[str], *results: str) -> list[str]:
    """The keys that are not named like a result, which takes the place of a key of its name (case aside, as in Spark)."""
    taken = {r.lower() for r in results}
    return [k for k in keys if k.lower() not in taken]


def with_row_key(df: DataFrame, key: str = "__row") -> DataFrame:
    """A key of each row that does not depend on the caller's ids, which may be null or repeat. Fixed only once the result is written."""
    return df.withColumn(key, F.monotonically_increasing_id())


def struct_udf(fn: Callable[..., dict[str, Iterable]], fields: str):
    """An Arrow function that takes lists of values (one list for each argument) and gives the columns of `fields`, a DDL string."""
    from pyspark.sql.pandas.types import to_arrow_type

    small_batches()
    schema = T.StructType.fromDDL(fields)
    kinds = {f.name: to_arrow_type(f.dataType) for f in schema.fields}

    def run(*columns: pa.Array) -> pa.Array:
        got = fn(*(c.to_pylist() for c in columns))
        out = pa.StructArray.from_arrays([pa.array(got[n], k) for n, k in kinds.items()], names=list(kinds))
        give_back()
        return out

    run.__annotations__ = {}
    return F.arrow_udf(run, schema, functionType=F.ArrowUDFType.SCALAR) if hasattr(F, "ArrowUDFType") else F.arrow_udf(run, schema)


def join_counted(rows: DataFrame, table: DataFrame, key: str, weight: str, share: int = 1000) -> DataFrame:
    """rows left-joined to a table with one row for each key, where weight is the number of rows that have it.

    Keys with at least 1/share of all rows, of which there can be no more than share, are broadcast; the others go by a shuffle, in which
    none of them is large. Null keys find nothing. Both inputs should be written tables: they are read twice."""
    total = table.agg(F.sum(weight)).first()[0] or 0
    added = [c for c in table.columns if c != key]
    heavy = F.col(weight) * share >= F.lit(total)
    few = table.where(heavy).withColumn("__heavy", F.lit(True))
    first = rows.join(F.broadcast(few), key, "left")
    rest = first.where(F.col("__heavy").isNull()).drop("__heavy", *added).join(table.where(~heavy), key, "left")
    return first.where("__heavy").drop("__heavy").unionByName(rest)


def give_back() -> None:
    """Freed memory goes back to the system: Python workers live long, and share their executor's memory with others."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):  # not every C library has it
        ctypes.CDLL(None).malloc_trim(0)


def trim_executors(spark: SparkSession) -> None:
    """Asks the JVM of each executor once to collect its garbage and give free heap back to the system: for between stages, when Python workers are to share the machine's memory with a JVM
    whose heap an earlier stage has stretched. One short task for each executor; where two of them meet on one, another keeps its heap, and only memory is lost."""
    n = max(1, spark._jsc.sc().getExecutorMemoryStatus().size() - 1)
    spark.range(0, n, 1, n).select(F.expr("java_method('java.lang.System', 'gc')").alias("done")).write.format("noop").mode("overwrite").save()


_left = [0]  # bytes of the driver's heap after trim_driver last collected its garbage


def trim_driver(spark: SparkSession, share: float = 0.6) -> bool:
    """Collects the garbage of the driver's JVM, and gives free heap and Python's freed memory back to the system, if the heap has stretched to this share of its limit and by a quarter since the
    last time: an operator of a hundred queries leaves plans, generated classes and broadcasts behind. Whether it did."""
    runtime = spark._jvm.java.lang.Runtime.getRuntime()
    if runtime.totalMemory() < max(share * runtime.maxMemory(), 1.25 * _left[0]):
        return False
    spark._jvm.java.lang.System.gc()
    _left[0] = runtime.totalMemory()
    give_back()
    return True


_alone: list = []


def alone(make: Callable) -> Callable:
    """make, remembering its last value; a worker that has gone over to another such function forgets this one's, so that stages of a pipeline don't add up."""
    kept = functools.lru_cache(maxsize=1)(make)
    _alone.append(kept)

    @functools.wraps(make)
    def get(*args):
        if any(k is not kept and k.cache_info().currsize for k in _alone):
            for k in _alone:
                if k is not kept:
                    k.cache_clear()
            give_back()
        return kept(*args)

    return get


def may_hold(keys: DataFrame, key: str) -> Callable[[Column], Column]:
    """A test that is true for all of the keys (longs, a written table), and false for most others: a bit filter of bounded size. It keeps the wide rows of other keys out
    of a shuffle; the join that follows is exact."""
    bits = 1 << max(16, min(26, (16 * keys.count()).bit_length()))
    both = F.explode(F.array(F.xxhash64(key), F.xxhash64(key, F.lit(1)))).alias("h")
    words = keys.select(both).select(F.pmod("h", F.lit(bits)).alias("p")).groupBy(F.shiftright("p", 6).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p & 63 as int))")).alias("b")).collect()
    table = np.zeros(bits // 64, np.int64)
    for w, b in words:
        table[w] = b
    sent = keys.sparkSession.sparkContext.broadcast(table.view(np.uint64))

    def run(p, q):
        hit = lambda z: sent.value[z >> 6] >> (z & 63).astype(np.uint64) & np.uint64(1)
        return {"v": (hit(np.array(p, np.int64)) & hit(np.array(q, np.int64))).astype(bool).tolist()}

    return lambda c: struct_udf(run, "v boolean")(F.pmod(F.xxhash64(c), F.lit(bits)), F.pmod(F.xxhash64(c, F.lit(1)), F.lit(bits)))["v"]


class Memo:
    """Values by key for keys that repeat, in the dict `now`. Two generations of about `size` are held; the older goes when the younger is full."""

    def __init__(self, size: int):
        self.size, self.now, self.old = size, {}, {}

    def make_room(self, keys: Iterable) -> list:
        """The keys that have no value yet, for the caller to fill; all others stay in `now` at least until the next call."""
        keys = list(keys)
        new = [k for k in keys if k not in self.now]
        if len(self.now) + len(new) > self.size:
            self.old, self.now, new = self.now, {}, keys
        if self.old and new:
            self.now.update((k, self.old[k]) for k in new if k in self.old)
            new = [k for k in new if k not in self.now]
        return new


def in_parts(texts: list[str | None], chars: int) -> Iterable[list[str | None]]:
    """The list cut into lists of about so many characters, a text at least."""
    part, total = [], 0
    for t in texts:
        part.append(t)
        total += len(t or "")
        if total >= chars:
            yield part
            part, total = [], 0
    if part:
        yield part
