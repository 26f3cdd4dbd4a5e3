"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

score = sigmoid(b + sum w_i x_i + 1/2 sum_f [(sum v_if x_i)^2 - sum v_if^2 x_i^2]): pairwise interactions in time linear in the
features. A text's distinct words are hashed to buckets with counts scaled to length one; statistics
of its structure and numeric metadata are cut into ranges, a feature each.

The machine is fitted on the driver from a bounded sample of labelled rows (``SAMPLE_ROWS``, chosen by a
hash of the id); every row is scored, whole text, in vectorised batches.

Defined results: null text is empty; empty texts get a score from their statistics; null metadata is a
range of its own; without two labels to learn from every score is the share of label 1 (0.5 without any);
no rows give no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import words as W
from .host_rules import measure
from .language_id import held_out

WORD_BUCKETS = 1 << 17
SAMPLE_ROWS = 10_000
RANKS = 8
LEVELS = 16
STATISTICS = ("words", "word length", "symbols", "repeats", "duplicate lines", "line length", "upper case", "digits", "punctuation", "stops", "distinct")
_UPPER, _DIGIT, _PUNCT, _STOP = (np.zeros(256, bool) for _ in range(4))
_UPPER[65:91] = _DIGIT[48:58] = True
_PUNCT[list(b"!\"'()*+,-/:;=?@[]^_`{}~#$%&|<>\\")] = True
_STOP[ord(".")] = True


def _ratio(a, b):
    return a / np.maximum(b, 1)


def features(col: pa.Array, metadata: list[pa.Array] = ()) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, feature, value), rows ascending; a row's features are distinct."""
    data, off = W.column_bytes(col)
    rows = len(off) - 1
    m = measure(col)
    lower = W.LOWER[data]
    s, e, first = W.spans(lower, off)
    bucket = (W.mix(W.span_hashes(lower, s, e)) >> W.U(47)).astype(np.int64)
    key = np.sort(W.document_of(first) * WORD_BUCKETS + bucket)
    new = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
    count = np.diff(np.append(new, len(key))).astype(np.float64)
    row, feature = np.divmod(key[new], WORD_BUCKETS)
    norm = np.sqrt(np.bincount(row, count * count, minlength=rows)) if rows else np.zeros(0)
    value = count / norm[row] if len(row) else count

    def share(which: np.ndarray) -> np.ndarray:
        return _ratio(np.diff(np.searchsorted(np.flatnonzero(which[data]), off)), np.diff(off))

    n = m["n_words"]
    distinct = np.bincount(row, minlength=rows)
    levels = [
        np.log2(n + 1), _ratio(m["word_chars"], n), 20 * np.sqrt(_ratio(m["n_symbols"], n)), 10 * _ratio(m["n_repeat_words"], n), 10 * _ratio(m["n_dup_lines"], m["n_lines"]), np.log2(_ratio(m["word_chars"], m["n_lines"]) + 1),
        60 * share(_UPPER), 60 * share(_DIGIT), 60 * share(_PUNCT), 200 * share(_STOP), 15 * _ratio(distinct, n),
    ]
    for x in metadata:
        v = x.to_numpy(zero_copy_only=False).astype(float)
        levels.append(np.where(np.isnan(v), LEVELS - 1, np.log2(np.maximum(np.nan_to_num(v), 0) + 1)))
    r = [row, *[np.arange(rows)] * len(levels)]
    f = [feature, *(WORD_BUCKETS + k * LEVELS + np.clip(v, 0, LEVELS - 1).astype(np.int64) for k, v in enumerate(levels))]
    v = [value, *[np.full(rows, 0.5)] * len(levels)]
    r, f, v = map(np.concatenate, (r, f, v))
    order = np.argsort(r, kind="stable")
    return r[order], f[order], v[order]


class FactorisationMachine:
    def __init__(self, size: int, ranks: int = RANKS, seed: int = 7):
        self.b, self.w = 0.0, np.zeros(size, np.float32)
        self.v = np.random.default_rng(seed).normal(0, 0.02, (size, ranks)).astype(np.float32)

    def logits(self, row: np.ndarray, feature: np.ndarray, value: np.ndarray, rows: int) -> np.ndarray:
        out = np.full(rows, self.b)
        if len(row):
            begin = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]]))
            xv = self.v[feature] * value[:, None].astype(np.float32)
            one = np.add.reduceat(xv, begin, axis=0)
            pair = 0.5 * ((one * one).sum(axis=1) - np.add.reduceat((xv * xv).sum(axis=1), begin))
            out[row[begin]] += np.add.reduceat(self.w[feature] * value, begin) + pair
        return out

    def fit(self, row: np.ndarray, feature: np.ndarray, value: np.ndarray, label: np.ndarray, epochs: int = 8, batch: int = 128, rate: float = 0.1, decay: float = 1e-5, seed: int = 7) -> None:
        """Adaptive gradient steps on the log loss. Rows ascend from 0 without a gap."""
        begin = np.searchsorted(row, np.arange(len(label) + 1))
        gw, gv, gb = np.full(len(self.w), 1e-6, np.float32), np.full(self.v.shape, 1e-6, np.float32), 1e-6
        p = label.mean()
        self.b = float(np.log((p + 1e-3) / (1 - p + 1e-3)))
        rng = np.random.default_rng(seed)
        for _ in range(epochs):
            order = rng.permutation(len(label))
            for k in range(0, len(order), batch):
                take = order[k : k + batch]
                at = np.concatenate([np.arange(begin[i], begin[i + 1]) for i in take])
                r = np.repeat(np.arange(len(take)), begin[take + 1] - begin[take])
                f, x = feature[at], value[at].astype(np.float32)
                starts = np.flatnonzero(np.concatenate([[True], r[1:] != r[:-1]]))
                xv = self.v[f] * x[:, None]
                one = np.add.reduceat(xv, starts, axis=0)
                z = self.b + np.add.reduceat(self.w[f] * x, starts) + 0.5 * ((one * one).sum(axis=1) - np.add.reduceat((xv * xv).sum(axis=1), starts))
                g = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - label[take]).astype(np.float32) / len(take)
                uf, inv = np.unique(f, return_inverse=True)
                dw = np.bincount(inv, g[r] * x, minlength=len(uf)).astype(np.float32) + decay * self.w[uf]
                each = (g[r] * x)[:, None] * (one[r] - xv)
                dv = np.stack([np.bincount(inv, each[:, c], minlength=len(uf)) for c in range(each.shape[1])], axis=1).astype(np.float32) + decay * self.v[uf]
                gw[uf] += dw * dw
                gv[uf] += dv * dv
                gb += float(g.sum()) ** 2
                self.w[uf] -= rate * dw / np.sqrt(gw[uf])
                self.v[uf] -= 0.3 * rate * dv / np.sqrt(gv[uf])
                self.b -= rate * float(g.sum()) / np.sqrt(gb)


def train(docs: DataFrame, labels: DataFrame, metadata: tuple[str, ...] = (), rows: int = SAMPLE_ROWS) -> FactorisationMachine:
    """docs: doc_id, text, metadata; labels: doc_id, label (0 or 1). At most ``rows`` of the labels are used."""
    chosen = labels.where("label IS NOT NULL").orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    sample = docs.join(F.broadcast(chosen), "doc_id").select("label", "text", *metadata)

    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in W.bites(b, 1):
                r, f, v = features(part.column(1), part.columns[2:])
                cut = np.searchsorted(r, np.arange(part.num_rows + 1))
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array([f[x:y].astype("<i4").tobytes() for x, y in zip(cut[:-1], cut[1:])], pa.binary()), pa.array([v[x:y].astype("<f4").tobytes() for x, y in zip(cut[:-1], cut[1:])], pa.binary())], names=["label", "f", "v"])

    got = sample.mapInArrow(W.trimmed(extract), "label long, f binary, v binary").collect()
    got.sort(key=lambda r: (r["f"], r["v"], r["label"]))  # the same steps whatever the partitions
    label = np.array([r["label"] for r in got], np.float64)
    machine = FactorisationMachine(WORD_BUCKETS + LEVELS * (len(STATISTICS) + len(metadata)))
    if len(set(label)) == 2:
        f = np.frombuffer(b"".join(r["f"] for r in got), "<i4").astype(np.int64)
        v = np.frombuffer(b"".join(r["v"] for r in got), "<f4")
        machine.fit(np.repeat(np.arange(len(got)), [len(r["f"]) // 4 for r in got]), f, v, label)
    else:
        p = float(np.clip(label.mean(), 1e-3, 1 - 1e-3)) if len(label) else 0.5
        machine.v[:] = 0
        machine.b = float(np.log(p / (1 - p)))
    return machine


def scored(docs: DataFrame, machine: FactorisationMachine, metadata: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, score of every row."""
    kind = dict(docs.dtypes)["doc_id"]
    shared = docs.sparkSession.sparkContext.broadcast(machine)  # WORD_BUCKETS * (RANKS + 1) floats, whatever the data

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            for part in W.bites(b, 1):
                z = m.logits(*features(part.column(1), part.columns[2:]), part.num_rows)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(1 / (1 + np.exp(-np.clip(z, -30, 30))), pa.float64())], names=["doc_id", "score"])

    return docs.select("doc_id", "text", *metadata).mapInArrow(W.trimmed(run), f"doc_id {kind}, score double")


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "n_chars")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(~held_out()).select("doc_id", F.col("quality").alias("label"))
    machine = train(docs, labels, ("n_chars",))
    out = scored(docs, machine, ("n_chars",))
    return out.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


QUERIES = {"op8_quality_classifier": op8_quality_classifier}
ORACLES: dict[str, str] = {}
