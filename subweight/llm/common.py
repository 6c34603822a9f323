"""What several operators share: words, durable intermediate tables, blocks of rows and their exchange.

A *block* is a few MB of whole rows in one compressed binary.  Operators that must ask the whole
corpus about something (is this window repeated? how frequent is this word?) let each block send
its distinct questions to hash buckets and get answers back as small blobs; one block asks about
one key at most once, so no key, however frequent, makes a task larger than the number of blocks.
"""

from __future__ import annotations

import atexit
import gc
import math
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Words are runs of anything but these six ASCII characters; ``bytes.split()`` cuts at the same six.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
SEPARATORS = " \t\n\x0b\x0c\r"
#: Text bytes in a block, and at most for very large inputs.
BLOCK_BYTES, LARGE_BLOCK = 2_000_000, 32_000_000
#: Text bytes whose questions go to one bucket, and for very large inputs.
BUCKET_BYTES, LARGE_BUCKET = 16_000_000, 64_000_000
#: Bytes of input up to which blocks and buckets have the smaller sizes; beyond, both grow with its square root.
SMALL_INPUT = 1_000_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def durable(df: DataFrame) -> DataFrame:
    """The same rows, computed once and kept in the shared folder named by spark.checkpoint.dir.

    Lineage ends there, so a lost executor costs a read, not the work before it.  A cluster must
    name the folder; only a local session, as in tests, gets one of its own.  What was kept is
    removed when the process ends.
    """
    context = df.sparkSession.sparkContext
    scala = context._jsc.sc()
    if not scala.getCheckpointDir().isDefined():
        folder = context.getConf().get("spark.checkpoint.dir", None)
        if folder is None:
            if not context.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
            folder = "/tmp/checkpoints"
        context.setCheckpointDir(folder)
    kept = scala.getCheckpointDir().get()
    if kept not in _KEPT:
        _KEPT.add(kept)
        atexit.register(_remove, context, kept)
    return df.checkpoint(eager=True)


#: Folders of this process that are removed at its end.
_KEPT: set[str] = set()


def _remove(context, folder: str) -> None:
    """Remove a folder by the file system it is on; a gateway that is gone leaves it."""
    try:
        path = context._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)
    except Exception:  # noqa: BLE001 the process is ending
        pass


def release(df: DataFrame) -> None:
    """Let go of shuffle files that nothing can read any more: the engine removes them once the driver's plans are collected, which takes a few rounds."""
    jvm = df.sparkSession.sparkContext._jvm
    gc.collect()
    for _ in range(4):
        jvm.System.gc()
        time.sleep(0.5)


def words_of(text: str | bytes | None) -> list[bytes]:
    """Words of a text as UTF-8; none of a null."""
    if text is None:
        return []
    return (text.encode("utf-8", "surrogatepass") if isinstance(text, str) else text).split()


def word_array(column: str = "text"):
    """The words of a text column as an array (empty for a null), by JVM functions only."""
    return F.regexp_extract_all(F.coalesce(F.col(column), F.lit("")), F.lit(WORD_PATTERN), F.lit(0))


def utf8_columns(batch: pa.RecordBatch, column: str) -> list[bytes | None]:
    """The values of a string column as UTF-8 bytes, without decoding them."""
    values = batch.column(column)
    kind = pa.large_binary() if pa.types.is_large_string(values.type) else pa.binary()
    return values.cast(kind).to_pylist() if not pa.types.is_binary(values.type) else values.to_pylist()


def arrow_rows(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [[] for _ in schema]
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


# ---------------------------------------------------------------- blocks


BLOCK_SCHEMA = T.StructType([T.StructField("block_id", T.LongType()), T.StructField("block_bytes", T.LongType()), T.StructField("payload", T.BinaryType())])
_BLOCK_ARROW = pa.schema([("block_id", pa.int64()), ("block_bytes", pa.int64()), ("payload", pa.binary())])


def pack(batch: pa.RecordBatch) -> bytes:
    sink = pa.BufferOutputStream()
    options = pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", compression_level=3))
    with pa.ipc.new_stream(sink, batch.schema, options=options) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


def unpack(payload: bytes) -> pa.RecordBatch:
    with pa.ipc.open_stream(payload) as source:
        return source.read_next_batch()


def grown(least: int, most: int, held: int) -> int:
    """A size between two, for an input of ``held`` bytes."""
    return int(min(most, least * max(1.0, math.sqrt(held / SMALL_INPUT))))


def input_bytes(df: DataFrame) -> int:
    """The optimizer's estimate of the bytes of ``df``; 0 if it knows nothing."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return size if size < 1 << 60 else 0


def to_blocks(df: DataFrame, text_column: str = "text", target: int | None = None) -> DataFrame:
    """Rows of ``df`` packed whole into blocks of about ``target`` text bytes (one longer row: alone). Durable.

    Without a target a block has 2 MB, and for inputs over 1 GB more, up to 32 MB: a large input has
    few questions a bucket and block otherwise.
    """
    target = grown(BLOCK_BYTES, LARGE_BLOCK, input_bytes(df)) if target is None else target

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        number = (TaskContext.get().partitionId() if TaskContext.get() else 0) << 32
        for batch in batches:
            if not batch.num_rows:
                continue
            sizes = [len(x) if x else 0 for x in utf8_columns(batch, text_column)]
            start, held = 0, 0
            for i, size in enumerate(sizes):
                if i > start and (held + size > target or i - start >= 8192):
                    yield arrow_rows([(number, held, pack(batch.slice(start, i - start)))], _BLOCK_ARROW)
                    number, start, held = number + 1, i, 0
                held += size
            yield arrow_rows([(number, held, pack(batch.slice(start)))], _BLOCK_ARROW)
            number += 1

    return durable(df.mapInArrow(run, BLOCK_SCHEMA))


def bucket_count(blocks: DataFrame) -> int:
    """So many that a bucket gets the questions of 16 MB of text (64 MB for very large inputs); at least one a shuffle partition."""
    held = blocks.agg(F.sum("block_bytes")).first()[0] or 0
    least = int(blocks.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return max(1, least, -(-held // grown(BUCKET_BYTES, LARGE_BUCKET, held)))


QUESTION_SCHEMA = "bucket int, level int, block_id long, keys binary, extra binary"
QUESTION_ARROW = pa.schema([("bucket", pa.int32()), ("level", pa.int32()), ("block_id", pa.int64()), ("keys", pa.binary()), ("extra", pa.binary())])
ANSWER_SCHEMA = "block_id long, level int, bucket int, answer binary"
ANSWER_ARROW = pa.schema([("block_id", pa.int64()), ("level", pa.int32()), ("bucket", pa.int32()), ("answer", pa.binary())])


def ask(questions: DataFrame, answer: Callable[[list[bytes], list[bytes]], list[bytes | None] | tuple[list[bytes | None], bytes]], tasks: int | None = None) -> DataFrame:
    """Bring the questions of a bucket together; ``answer`` gets the blobs of all blocks and returns one for each (None: nothing to say).

    ``tasks``: at most so many, for few questions.  If it returns a summary of the bucket too, that comes as the answer to a block -1.
    """

    def run(group: pa.Table) -> pa.Table:
        got = group.to_pydict()
        told = answer(got["keys"], got["extra"])
        told, summary = told if isinstance(told, tuple) else (told, None)
        rows = [(-1, got["level"][0], got["bucket"][0], summary)] if summary is not None else []
        rows += [(b, v, k, x) for b, v, k, x in zip(got["block_id"], got["level"], got["bucket"], told, strict=True) if x is not None]
        return pa.Table.from_batches([arrow_rows(rows, ANSWER_ARROW)])

    answers = questions.groupBy("bucket").applyInArrow(run, ANSWER_SCHEMA)
    return durable(answers if tasks is None else answers.coalesce(tasks))


def with_answers(blocks: DataFrame, answers: list[DataFrame]) -> DataFrame:
    """Each block beside all its answers, as an array of (level, bucket, answer); a block has a bounded number of them."""
    if not answers:
        return blocks.withColumn("answers", F.lit(None).cast("array<struct<level:int,bucket:int,answer:binary>>"))
    told = answers[0]
    for more in answers[1:]:
        told = told.unionByName(more)
    told = told.groupBy("block_id").agg(F.collect_list(F.struct("level", "bucket", "answer")).alias("answers"))
    return blocks.join(told, "block_id", "left")


# ---------------------------------------------------------------- words of a block, as arrays


_MIX = (0xBF58476D1CE4E5B9, 0x94D049BB133111EB)  # fixed values: the multipliers of the SplitMix64 finaliser


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(_MIX[0])
    h = (h ^ (h >> np.uint64(27))) * np.uint64(_MIX[1])
    return h ^ (h >> np.uint64(31))


class Words:
    """The words of several texts end to end: one buffer, word bounds, and the text each word is of."""

    def __init__(self, texts: list[bytes | None]):
        self.normal = [b" ".join(t.split()) if t else b"" for t in texts]
        self.buffer = b" ".join([x for x in self.normal if x])
        array = np.frombuffer(self.buffer, np.uint8)
        gaps = np.flatnonzero(array == 32)
        empty = not self.buffer
        self.starts = np.zeros(0, np.int64) if empty else np.concatenate([[0], gaps + 1])
        self.ends = np.zeros(0, np.int64) if empty else np.concatenate([gaps, [len(array)]])
        self.counts = np.array([x.count(b" ") + 1 if x else 0 for x in self.normal], np.int64)
        self.text = np.repeat(np.arange(len(texts)), self.counts)
        self.first = np.cumsum(self.counts) - self.counts

    def __len__(self) -> int:
        return len(self.starts)

    def hashes(self, length: int, seed: int, step: int = 1 << 15) -> np.ndarray:
        """64-bit hashes of all windows of ``length`` words, spaces between words included; worked out ``step`` words at a time."""
        n = len(self) - length + 1
        if n <= 0:
            return np.zeros(0, np.uint64)
        rng = np.random.Generator(np.random.PCG64(seed))
        of_byte = rng.integers(0, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        base = int(rng.integers(1 << 61, 1 << 62)) * 2 + 1
        array = np.frombuffer(self.buffer, np.uint8)
        parts = [(a, min(n, a + step)) for a in range(0, n, step)]
        spans = [(int(self.starts[a]), int(self.ends[b + length - 2])) for a, b in parts]
        longest = max(high - low for low, high in spans)
        powers, inverses = (np.full(longest, x, np.uint64) for x in (base, pow(base, -1, 1 << 64)))
        for x in (powers, inverses):
            np.multiply.accumulate(x, out=x)
        total = np.zeros(longest + 1, np.uint64)
        out = np.empty(n, np.uint64)
        for (a, b), (low, high) in zip(parts, spans, strict=True):
            size = high - low
            value = of_byte[array[low:high]]
            value *= powers[:size]
            np.cumsum(value, out=total[1 : size + 1])
            s = self.starts[a:b] - low
            out[a:b] = (total[self.ends[a + length - 1 : b + length - 1] - low] - total[s]) * inverses[s]
        return mix(out)


def split_buckets(sorted_keys: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Bounds of the runs of sorted 64-bit keys that fall in the same bucket, and the buckets."""
    of = ((sorted_keys >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)
    edges = np.flatnonzero(np.diff(of)) + 1 if len(of) else np.zeros(0, np.int64)
    bounds = np.concatenate([[0], edges, [len(of)]]) if len(of) else np.zeros(1, np.int64)
    return bounds, of[bounds[:-1]].astype(np.int64)
