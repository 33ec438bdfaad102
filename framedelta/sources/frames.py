"""Frames made of the given tables: ordered, time-like rows stand in for video.

All makers return video_id, frame_no (from 1, without gaps) and tokens, the frame's raw tokens one after another, the class
token (their mean) first. Values are non-null doubles.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..model import FRAMES
from ..operators import encode

#: Units of texts, and frames, that are in a task's arrays at once; a text is never divided.
SCROLL_UNITS, SCROLL_FRAMES = 1 << 19, 4096
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
TICK_HOURS, RING = 6, 12


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def packed(patches: Column, dim: int) -> Column:
    """An array of token vectors as one array, with their mean before them."""

    def whole(p):
        sums = F.aggregate(p, F.array_repeat(F.lit(0.0), dim), lambda a, v: F.zip_with(a, v, lambda x, y: x + y))
        return F.concat(F.transform(sums, lambda x: x / F.size(p)), F.flatten(p))

    return F.transform(F.array(patches), whole)[0]  # so that the patches are made once


def ticks_of(events: DataFrame) -> DataFrame:
    """(start, last): the day of the first event and the last event's tick; one row."""
    start = F.date_trunc("day", F.min("ts")).cast("timestamp_ntz")
    return events.agg(start.alias("start"), F.max("ts").alias("_end")).select("start", tick_of(F.col("_end"), F.col("start")).alias("last"))


def tick_of(ts: Column, start: Column) -> Column:
    return F.floor(F.timestamp_diff("HOUR", start, ts) / TICK_HOURS).cast("int")


def activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events: a video for each user, a frame every six hours from the day of the first event to the last event, a token for each event type with a ring of the last 72 hours."""
    e = table(spark, sf_dir, "events").where(F.col("user_id").isNotNull() & F.col("ts").isNotNull())
    span = F.broadcast(ticks_of(e))  # one row
    kind = F.coalesce(F.array_position(F.array(*map(F.lit, EVENT_TYPES)), F.col("event_type")).cast("int") - 1, F.lit(-1))
    cells = e.crossJoin(span).select("user_id", kind.alias("kind"), tick_of(F.col("ts"), F.col("start")).alias("b"), "value", "last")
    cells = cells.groupBy("user_id", "last", "kind", "b").agg(F.sum("value").alias("v"))
    cells = cells.select("user_id", "last", "kind", "b", F.coalesce(F.log1p("v"), F.lit(0.0)).alias("v"))
    # cells are far smaller than frames, so a user's cells meet and the frames are made of them where they are
    users = cells.repartition(encode.encode_partitions(cells), "user_id").groupBy("user_id", "last").agg(F.collect_list(F.struct("kind", "b", "v")).alias("cells"))
    encode.ship(spark)

    def run(batches):
        n = len(EVENT_TYPES)
        for x in batches:
            of, size = x.column("user_id"), x.column("cells").value_lengths().to_numpy().astype(np.int64)
            kind, b, v = (f.to_numpy(zero_copy_only=False) for f in x.column("cells").flatten().flatten())
            end = np.cumsum(size)
            ticks = x.column("last").to_numpy().astype(np.int64) + 1
            for row in range(len(size)):
                at = slice(end[row] - size[row], end[row])
                known = kind[at] >= 0
                held = np.zeros((n, RING - 1 + ticks[row]))
                held[kind[at][known], RING - 1 + b[at][known]] = v[at][known]
                for lo in range(0, ticks[row], SCROLL_FRAMES):
                    k = np.arange(lo, min(ticks[row], lo + SCROLL_FRAMES))
                    ring = k[:, None] - (k[:, None] - np.arange(RING)) % RING  # the tick whose cell is in each slot
                    patches = held[:, RING - 1 + ring].transpose(1, 0, 2)
                    mean = np.zeros((len(k), 1, RING))
                    for t in range(n):  # added up in order, as SQL does
                        mean[:, 0] += patches[:, t]
                    tokens = np.concatenate([mean / n, patches], 1).reshape(len(k), -1)
                    yield pa.RecordBatch.from_arrays([of.take(pa.array(np.full(len(k), row))), pa.array((k + 1).astype(np.int32)), encode._lists(tokens)], ["video_id", "frame_no", "tokens"])

    return users.mapInArrow(run, f"video_id {dict(users.dtypes)['user_id']}, frame_no int, tokens array<double>")


def morph(spark: SparkSession, sf_dir: str, steps: int = 8) -> DataFrame:
    """embeddings: a video for each label, whose vectors are key frames with `steps` - 1 frames between two of them; 8 tokens of 8 numbers."""
    w = Window.partitionBy("label").orderBy("vec_id")
    k = table(spark, sf_dir, "embeddings").where("label is not null and embedding is not null").select("label", "embedding", F.lead("embedding").over(w).alias("after"), F.row_number().over(w).alias("n")).where("after is not null")
    encode.ship(spark)

    def run(batches):
        j = np.arange(steps)
        for whole in batches:
            for at in range(0, whole.num_rows, SCROLL_FRAMES // steps):
                x = whole.slice(at, SCROLL_FRAMES // steps)
                a, b = (encode.fixed(x, c, 64, "label", "key frame").reshape(-1, 1, 8, 8) for c in ("embedding", "after"))
                w = j.reshape(-1, 1, 1)
                mix = a * (steps - w) / steps + b * w / steps
                mean = np.zeros((*mix.shape[:2], 1, 8))
                for i in range(8):  # added up in order, as SQL does
                    mean[:, :, 0] += mix[:, :, i]
                tokens = np.concatenate([mean / 8, mix], 2).reshape(-1, 72)
                no = (x.column("n").to_numpy()[:, None] - 1) * steps + j + 1
                video = x.column("label").to_numpy().astype(np.int64).repeat(steps)
                yield pa.RecordBatch.from_arrays([pa.array(video), pa.array(no.ravel().astype(np.int32)), encode._lists(tokens)], ["video_id", "frame_no", "tokens"])

    # a label's key frames meet in one task; the frames between them are made in all
    return k.repartition(encode.encode_partitions(k)).mapInArrow(run, FRAMES)


def hashed_words(text: Column, buckets: int) -> Column:
    """The bucket of each word of a text."""
    return F.transform(F.split(text, " "), lambda w: F.pmod(F.conv(F.substring(F.md5(F.lower(w).cast("binary")), 1, 6), 16, 10).cast("bigint"), F.lit(buckets)).cast("int"))


def counted(part: Column, buckets: int) -> Column:
    """How many words of `part` each bucket has."""
    return F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda k: F.size(F.filter(part, lambda y: y == k)).cast("double"))


def scrolled(df: DataFrame, units: Column, buckets: int = 16, block: int = 8) -> DataFrame:
    """Scrolling text: a window of eight blocks of units which moves on by two blocks, up to the last unit; each block is a token of counts by bucket.

    df has video_id; units is the text as bucket numbers. The last window is shorter where the text ends in it. A text is cut once, so the
    work grows with its length and not with its square; a block is counted once, not in each of the frames that show it.
    """
    kind = dict(df.dtypes)["video_id"]
    spark = df.sparkSession
    encode.ship(spark)

    def run(batches):
        for b in batches:
            ids, h = b.column("video_id"), b.column("h")
            size = h.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
            word = h.flatten().fill_null(-1).to_numpy(zero_copy_only=False)
            end = np.cumsum(size)
            for docs in np.split(np.arange(len(size)), np.flatnonzero(np.diff(end // SCROLL_UNITS)) + 1):
                if not len(docs):
                    continue
                n = np.maximum(1, -(-(size[docs] - 8 * block) // (2 * block)) + 1)  # frames
                blocks = 2 * (n - 1) + 8
                first = np.cumsum(blocks) - blocks
                at = np.arange(size[docs].sum()) - np.repeat(np.cumsum(size[docs]) - size[docs], size[docs])
                w = word[end[docs[0]] - size[docs[0]] : end[docs[-1]]]
                known = (w >= 0) & (w < buckets)
                cell = (np.repeat(first, size[docs]) + at // block) * buckets + w
                counts = np.bincount(cell[known], minlength=int(blocks.sum()) * buckets).reshape(-1, buckets).astype(float)
                of = np.repeat(np.arange(len(docs)), n)
                no = np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n)
                for lo in range(0, len(of), SCROLL_FRAMES):
                    d, i = of[lo : lo + SCROLL_FRAMES], no[lo : lo + SCROLL_FRAMES]
                    ring = (np.arange(8) - 2 * i[:, None]) % 8  # blocks keep their place while they are in view
                    tokens = counts[(first[d] + 2 * i)[:, None] + ring]
                    tokens = np.concatenate([tokens.sum(1, keepdims=True) / 8, tokens], 1).reshape(len(d), -1)
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(docs[d])), pa.array((i + 1).astype(np.int32)), encode._lists(tokens)], ["video_id", "frame_no", "tokens"])

    # texts are far smaller than frames, so they are dealt evenly before frames are made of them
    x = df.repartition(encode.encode_partitions(df)).select("video_id", units.alias("h"))
    return x.mapInArrow(run, f"video_id {kind}, frame_no int, tokens array<double>")


def prose(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents as scrolling text: windows of 64 words."""
    d = table(spark, sf_dir, "documents").where("text is not null")
    return scrolled(d.select(F.col("doc_id").cast("bigint").alias("video_id"), "text"), hashed_words(F.col("text"), 16))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """pages as scrolling layout: windows of 512 characters of their html, bucketed by code point."""
    d = table(spark, sf_dir, "pages").where("html is not null")
    units = F.transform(F.filter(F.split("html", ""), lambda c: c != ""), lambda c: F.pmod(F.ascii(c), F.lit(16)))
    return scrolled(d.select(F.col("page_id").cast("bigint").alias("video_id"), "html"), units, block=64)


def talk(spark: SparkSession, sf_dir: str, buckets: int = 16) -> DataFrame:
    """conversations: a video for each of them, a frame for each turn; the whole turn in eight equal blocks of words, each a token."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    t = table(spark, sf_dir, "conversations").where("conv_id is not null and text is not null").select(F.col("conv_id").cast("bigint").alias("video_id"), F.row_number().over(w).alias("frame_no"), hashed_words(F.col("text"), buckets).alias("h"))

    return t.select("video_id", "frame_no", blocks_as_tokens(F.col("h"), buckets).alias("tokens"))


def blocks_as_tokens(units: Column, buckets: int) -> Column:
    """A text's bucket numbers in eight equal blocks, each a token of counts."""

    def block(h):
        def one(i):
            start, end = (F.floor(F.size(h) * k / 8).cast("int") for k in (i, i + 1))
            return counted(F.slice(h, start + 1, end - start), buckets)

        return F.transform(F.sequence(F.lit(0), F.lit(7)), one)

    return packed(F.transform(F.array(units), block)[0], buckets)


def shipping(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem as frames of its suppliers."""
    return shipping_of(table(spark, sf_dir, "lineitem"))


def shipping_of(lineitem: DataFrame) -> DataFrame:
    """A video for each supplier, a frame for each month with shipments, six tokens of quantities by line number."""
    i = lineitem.where("l_suppkey is not null and l_shipdate is not null")
    month = F.year("l_shipdate") * 12 + F.month("l_shipdate")
    slot = (F.array_position(F.array(*map(F.lit, ("A", "N", "R"))), F.col("l_returnflag")) - 1) * 2 + F.when(F.col("l_linestatus") == "O", 1).otherwise(0)
    x = i.select("l_suppkey", month.alias("month"), (slot * 7 + F.col("l_linenumber") - 1).cast("int").alias("slot"), "l_quantity")
    per = x.groupBy("l_suppkey", "month").agg(*[F.coalesce(F.sum(F.when(F.col("slot") == s, F.col("l_quantity"))), F.lit(0.0)).alias(f"s{s}") for s in range(42)])
    rows = F.array(*[F.array(*[F.log1p(F.col(f"s{t * 7 + s}")) for s in range(7)]) for t in range(6)])
    n = F.row_number().over(Window.partitionBy("l_suppkey").orderBy("month"))
    return per.select(F.col("l_suppkey").alias("video_id"), n.alias("frame_no"), packed(rows, 7).alias("tokens"))
