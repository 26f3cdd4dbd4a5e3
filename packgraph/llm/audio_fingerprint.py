"""Chroma audio fingerprints and their alignment.

A recording becomes pitch-class frames (energy of each of twelve pitch classes, smoothed over time and scaled), seen as an image
of time by pitch. Sixteen filters compare sums over areas of that image, read off an integral image; each gives two bits in Gray
code, so that a frame's packed 32-bit integer changes little when the sound does.

Two recordings are aligned by the histogram of time offsets between equal integers; at the offset with
the most votes the share of differing bits says how alike they are.

Recordings with the same integers are one class; classes are compared, not copies. Every equal integer votes, however
many classes hold it (silence, a held tone); such an integer's classes are dealt to several tasks.

Defined results: null or short sound (less than one filter's width) has no integers and no match; null ids are left out; repeated
rows fall into one class; no rows give no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import written

PITCHES = 12
#: (kind, first pitch, pitches, frames) by rule: kinds take turns, places step through the octave, widths grow.
FILTERS = tuple((k % 6, (5 * k) % 9, 2 + k % 3 * 1 if (5 * k) % 9 + 2 + k % 3 <= 12 else 2, 2 + k // 3) for k in range(16))
WIDEST = max(f[3] for f in FILTERS)
GRAY = np.array([0, 1, 3, 2], np.uint32)
#: Cuts of a filter's log ratio between its four levels.
CUTS = np.array([-0.12, 0.0, 0.12])
#: Tasks that the places of one integer are dealt to.
SALTS = 16


def chroma(samples: np.ndarray, rate: int, frame: int = 1024, hop: int = 512, low: float = 60.0, high: float = 3500.0) -> np.ndarray:
    """frames by pitch classes; each frame's energies scaled to length one, zero where it is silent."""
    n = 1 + (len(samples) - frame) // hop if len(samples) >= frame else 0
    if not n:
        return np.zeros((0, PITCHES))
    cut = np.lib.stride_tricks.sliding_window_view(samples, frame)[::hop]
    power = np.abs(np.fft.rfft(cut * np.hanning(frame), axis=1)) ** 2
    freq = np.fft.rfftfreq(frame, 1 / rate)
    use = np.flatnonzero((freq >= low) & (freq <= high))
    pitch = np.round(PITCHES * np.log2(freq[use] / 440.0)).astype(int) % PITCHES
    image = power[:, use] @ np.eye(PITCHES)[pitch]
    smooth = np.array([0.25, 0.75, 1.0, 0.75, 0.25])
    padded = np.pad(image, ((2, 2), (0, 0)))
    image = sum(w * padded[k : k + n] for k, w in enumerate(smooth))
    norm = np.sqrt((image**2).sum(axis=1, keepdims=True))
    return np.where(norm > 1e-6, image / np.maximum(norm, 1e-6), 0)


def _halves(area, kind: int, y: int, h: int, w: int):
    """Sums over the two sides that a kind of filter compares; area(t0, t1, y0, y1) for all places at once."""
    t, p = w // 2, h // 2
    whole = area(0, w, y, y + h)
    if kind == 0:  # the whole against nothing
        return whole, 0
    if kind == 1:  # lower against upper pitches
        a = area(0, w, y, y + p)
    elif kind == 2:  # earlier against later
        a = area(0, t, y, y + h)
    elif kind == 3:  # opposite corners
        a = area(0, t, y, y + p) + area(t, w, y + p, y + h)
    elif kind == 4:  # middle pitches against the outer ones
        q = max(1, h // 3)
        a = area(0, w, y + q, y + h - q) if h > 2 * q else area(0, w, y, y + q)
    else:  # middle time against its sides
        q = max(1, w // 3)
        a = area(q, w - q, y, y + h) if w > 2 * q else area(0, q, y, y + h)
    return a, whole - a


def fingerprint(image: np.ndarray) -> np.ndarray:
    """A packed 32-bit integer for each place where the widest filter fits."""
    n = len(image) - WIDEST + 1
    if n <= 0:
        return np.zeros(0, np.uint32)
    total = np.zeros((len(image) + 1, PITCHES + 1))
    total[1:, 1:] = image.cumsum(axis=0).cumsum(axis=1)

    def area(t0: int, t1: int, y0: int, y1: int) -> np.ndarray:
        return total[t1 : t1 + n, y1] - total[t0 : t0 + n, y1] - total[t1 : t1 + n, y0] + total[t0 : t0 + n, y0]

    out = np.zeros(n, np.uint32)
    for kind, y, h, w in FILTERS:
        a, b = _halves(area, kind, y, h, w)
        b = b if kind else h * w / 4
        level = np.searchsorted(CUTS, np.log((1 + np.maximum(a, 0)) / (1 + np.maximum(b, 0))))
        out = (out << np.uint32(2)) | GRAY[level]
    return out


def fingerprints(recordings: DataFrame) -> DataFrame:
    """rec_id, prints (array<int>) from (rec_id, pcm, rate): 16-bit little-endian mono samples."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for pcm, rate in zip(b.column(1), b.column(2).to_pylist()):
                raw = pcm.as_py() or b""
                x = np.frombuffer(raw[: len(raw) // 2 * 2], "<i2") / 32768.0
                rows.append(fingerprint(chroma(x, rate)).view(np.int32) if rate else np.zeros(0, np.int32))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(rows, pa.list_(pa.int32()))], names=["rec_id", "prints"])

    return recordings.where("rec_id IS NOT NULL").select(F.col("rec_id").cast("long"), "pcm", F.col("rate").cast("int")).mapInArrow(run, "rec_id long, prints array<int>")


def classes(prints: DataFrame) -> DataFrame:
    """class_id (smallest rec_id with these integers), prints, copies; without empty ones."""
    keyed = prints.where(F.size("prints") > 0).withColumn("k", F.sha2(F.array_join(F.transform("prints", lambda x: x.cast("string")), ","), 256))
    return keyed.groupBy("k").agg(F.min("rec_id").alias("class_id"), F.first("prints").alias("prints"), F.count("*").alias("copies"))


def align(prints: DataFrame, is_query, least_votes: int = 3) -> DataFrame:
    """query_id, class_id, copies, offset, votes, overlap, bit_errors, error_rate.

    prints: a (written) rec_id, prints. is_query: a condition on rec_id. A row for each query and class that
    share ``least_votes`` integers at their best offset (ties: the smallest offset in size, then the negative one);
    offset is the place in the class's recording less that in the query. A query's own class is among them.
    """
    found = classes(prints)
    reps = written(found, "prints")
    member = prints.where(is_query).where(F.size("prints") > 0).withColumn("k", F.sha2(F.array_join(F.transform("prints", lambda x: x.cast("string")), ","), 256))
    queries = written(member.select(F.col("rec_id").alias("query_id"), "k").join(reps.select("k", F.col("class_id").alias("query_class")), "k").select("query_id", "query_class"), "queries")

    # an integer's places in one class travel as one row, dealt to SALTS tasks; its queries' places go to all of them
    post = reps.select("class_id", F.posexplode("prints").alias("t", "v"))
    held = written(post.groupBy("class_id", "v").agg(F.collect_list("t").alias("ts")), "postings")
    asked = held.join(queries.select(F.col("query_class").alias("class_id")).distinct(), "class_id", "left_semi").select(F.col("class_id").alias("query_class"), "v", F.col("ts").alias("ss"))
    asked = asked.withColumn("salt", F.explode(F.array(*map(F.lit, range(SALTS)))))
    met = asked.join(held.withColumn("salt", F.expr(f"cast(pmod(xxhash64(class_id), {SALTS}) as int)")), ["v", "salt"])
    places = met.select("query_class", "class_id", F.explode("ss").alias("s"), "ts").select("query_class", "class_id", "s", F.explode("ts").alias("t"))
    votes = places.groupBy("query_class", "class_id", (F.col("t") - F.col("s")).alias("offset")).agg(F.count("*").alias("votes"))
    best = votes.groupBy("query_class", "class_id").agg(F.max(F.struct("votes", (-F.abs("offset")).alias("near"), (-F.col("offset")).alias("first"))).alias("b"))
    best = best.select("query_class", "class_id", F.col("b.votes").alias("votes"), (-F.col("b.first")).alias("offset")).where(F.col("votes") >= least_votes)
    both = best.join(reps.select(F.col("class_id").alias("query_class"), F.col("prints").alias("x")), "query_class").join(reps.select("class_id", "copies", F.col("prints").alias("y")), "class_id")
    overlap = F.expr("least(size(x) - greatest(-offset, 0), size(y) - greatest(offset, 0))")
    errors = F.expr("aggregate(zip_with(slice(x, 1 + greatest(-offset, 0), overlap), slice(y, 1 + greatest(offset, 0), overlap), (p, q) -> bit_count((p ^ q) & 4294967295L)), 0L, (s, e) -> s + e)")
    scored = both.withColumn("overlap", overlap).withColumn("bit_errors", errors)
    scored = scored.select("query_class", "class_id", "copies", "offset", "votes", "overlap", "bit_errors", (F.col("bit_errors") / (32 * F.col("overlap"))).alias("error_rate"))
    return queries.join(scored, "query_class").select("query_id", "class_id", "copies", "offset", "votes", "overlap", "bit_errors", "error_rate")


def melody(vectors: DataFrame, rate: int = 4000, note: int = 512) -> DataFrame:
    """rec_id, pcm, rate: a tone of ``note`` samples for each value of a vector, higher values higher.

    Stands for stored sound where tables have none: equal vectors sound equal, near ones alike.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = np.arange(note) / rate
        ease = np.minimum(1, np.minimum(np.arange(note), np.arange(note)[::-1]) / 32)
        for b in batches:
            out = []
            for v in b.column(1).to_pylist():
                f = 300 * 2 ** np.clip(8 * np.array([x or 0.0 for x in v or ()]), -2, 2)
                out.append((np.sin(2 * np.pi * f[:, None] * t) * ease * 24_000).astype("<i2").tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary()), pa.array([rate] * len(out), pa.int32())], names=["rec_id", "pcm", "rate"])

    return vectors.mapInArrow(run, "rec_id long, pcm binary, rate int")


def op2_audio_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").cast("long").alias("rec_id"), "embedding")
    sound = vectors.repartition(64)  # small rows, much work each
    prints = written(fingerprints(melody(sound)), "fingerprints")
    return align(prints, F.col("rec_id") % 20 == 0)


QUERIES = {"op2_audio_fingerprint": op2_audio_fingerprint}
ORACLES: dict[str, str] = {}
