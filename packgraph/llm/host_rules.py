"""Host-level quality rules: rule failures by host, shrunk with an empirical beta prior.

Each document is measured once (whole text, vectorised over Arrow batches); hosts are
aggregated from the small table of measures, so no text is shuffled. A third of all rows under
one host costs nothing: counts are combined before the shuffle.

Defined results: null text has no words and fails; null host is a host of its own that only
the prior judges; duplicate rows are judged each on its own; extra columns are kept, also those
named like ours (ours then get a leading underscore inside); no rows give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import words as W
from .common import fresh, written

SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


#: Up to so many bad hosts (a few MB of names) are broadcast; more are joined by a shuffle.
BROADCAST_HOSTS = 100_000


@dataclass(frozen=True)
class HostRules:
    """Thresholds. A document fails a rule by its own measures; a host is judged by its documents."""

    min_words: int = 50
    max_repeat_percent: int = 50
    max_symbol_percent: int = 10
    max_dup_line_percent: int = 30
    min_word_chars: int = 2
    max_word_chars: int = 15
    #: A host's documents go when its shrunken failure rate reaches this.
    max_host_rate: float = 0.5

    def base_failed(self) -> Column:
        return (F.col("n_words") < self.min_words) | (100 * F.col("n_repeat_words") > self.max_repeat_percent * F.col("n_words"))

    def failed(self) -> Column:
        n = F.col("n_words")
        return self.base_failed() | (100 * F.col("n_symbols") > self.max_symbol_percent * F.col("word_chars")) | (F.col("word_chars") < self.min_word_chars * n) | (F.col("word_chars") > self.max_word_chars * n) | (100 * F.col("n_dup_lines") > self.max_dup_line_percent * F.greatest(F.col("n_lines"), F.lit(1)))


def measure(col: pa.Array) -> dict[str, np.ndarray]:
    """The measures of each text of a batch."""
    data, off = W.column_bytes(col)
    s, e, first = W.spans(data, off)
    full = np.flatnonzero(np.diff(off))
    chars = np.zeros(len(off) - 1, np.int64)
    if len(full):
        chars[full] = np.add.reduceat(~W.SEPARATORS[data] & ((data & 0xC0) != 0x80), off[full], dtype=np.int64)
    at = np.flatnonzero(SYMBOLS[data])
    symbols = np.diff(np.searchsorted(at, off))

    ls, le, lfirst = W.spans(data, off, W.NEWLINE)
    worded = np.searchsorted(s, le) > np.searchsorted(s, ls)
    lh, ldoc = W.span_hashes(data, ls, le), W.document_of(lfirst)
    lh, ldoc = lh[worded], ldoc[worded]
    order = np.lexsort((lh, ldoc))
    again = (lh[order][1:] == lh[order][:-1]) & (ldoc[order][1:] == ldoc[order][:-1])
    dup = np.bincount(ldoc[order][1:][again], minlength=len(off) - 1) if len(order) else np.zeros(len(off) - 1, np.int64)
    lines = np.bincount(ldoc, minlength=len(off) - 1) if len(ldoc) else np.zeros(len(off) - 1, np.int64)

    wh = W.span_hashes(data, s, e)
    three = W.windows(wh, 3)
    cover = np.zeros(len(wh), bool)
    if len(three):
        ok = np.flatnonzero(W.inside_one(first, 3))
        doc = W.document_of(first)[ok].astype(np.uint64)
        twice = np.zeros(len(three), bool)
        twice[ok] = W.repeated(W.joined(three[ok], doc))
        for d in range(3):
            cover[d : d + len(three)] |= twice
    return {"n_words": np.diff(first), "word_chars": chars, "n_symbols": symbols, "n_dup_lines": dup, "n_repeat_words": W.per_document(cover, first), "n_lines": lines}


def measured(docs: DataFrame, text: str, keep: dict[str, str]) -> DataFrame:
    """keep: columns of ``docs`` that go along, by their new names; then the measures."""
    kinds = dict(docs.dtypes)
    picked = docs.select(F.col(f"`{text}`").alias("text"), *(F.col(f"`{c}`").alias(n) for c, n in keep.items()))
    names = [*keep.values(), *MEASURES, "n_lines"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x for b in batches for x in W.bites(b, 0)):
            m = measure(b.column(0))
            yield pa.RecordBatch.from_arrays([*b.columns[1:], *(pa.array(m[k], pa.int64()) for k in names[len(keep) :])], names=names)

    schema = ", ".join([*(f"{n} {kinds[c]}" for c, n in keep.items()), *(f"{k} long" for k in names[len(keep) :])])
    return picked.mapInArrow(W.trimmed(run), schema)


def beta_prior(hosts: DataFrame) -> tuple[float, float]:
    """(alpha, beta) by the method of moments over hosts' (n, f); sums of three numbers reach the driver.

    Between-host variance is the observed one less what sampling alone gives; without any,
    the prior is as heavy as the cap, so that every host is shrunk to the common rate.
    """
    got = hosts.agg(
        F.sum("n").alias("n"), F.sum("f").alias("f"), F.count("*").alias("h"), F.sum(F.col("f") * F.col("f") / F.col("n")).alias("s"), F.sum(F.col("n") * F.col("n")).alias("q"),
    ).first()
    n, f, h = float(got["n"] or 0), float(got["f"] or 0), got["h"]
    if not n:
        return 1.0, 1.0
    m = (f + 0.5) / (n + 1)
    within = m * (1 - m)
    spread = float(got["s"]) - f * f / n  # weighted sum of squares between hosts
    scale = n - float(got["q"]) / n
    between = (spread - (h - 1) * within) / scale if scale > 0 else 0.0
    weight = min(max(within / between - 1, 1.0), 1000.0) if between > 0 else 1000.0
    return m * weight, (1 - m) * weight


def judged(measures: DataFrame, rules: HostRules = HostRules(), host: str = "host") -> DataFrame:
    """Adds base_failed, host_rate and kept to a (written) table of measures."""
    flagged = measures.withColumn("base_failed", rules.base_failed()).withColumn("_failed", rules.failed())
    hosts = flagged.groupBy(host).agg(F.count("*").alias("n"), F.sum(F.col("_failed").cast("long")).alias("f"))
    alpha, beta = beta_prior(hosts)
    rate = ((F.col("f") + F.lit(alpha)) / (F.col("n") + F.lit(alpha + beta)))
    verdict = hosts.where(F.col(host).isNotNull()).select(F.col(host).alias("_host"), rate.alias("host_rate"))
    out = flagged.join(verdict, flagged[host] == verdict["_host"], "left")
    rate = F.coalesce("host_rate", F.lit(alpha / (alpha + beta)))
    return out.withColumn("host_rate", rate).withColumn("kept", ~F.col("base_failed") & (F.col("host_rate") < rules.max_host_rate)).drop("_host", "_failed")


def host_quality(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", host: str = "source", rules: HostRules = HostRules()) -> DataFrame:
    """One row per row of ``docs``: doc_id, host, the measures, base_failed, host_rate, kept."""
    return judged(written(measured(docs, text, {doc_id: "doc_id", host: "host"}), "measures"), rules)


def filter_hosts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", host: str = "source", rules: HostRules = HostRules()) -> DataFrame:
    """The rows of ``docs`` that are kept, with all their columns.

    The verdict is taken row by row in the same pass that reads the text, not joined by id,
    so repeated and null ids keep their own verdicts and no text is shuffled unless the
    hosts' verdicts are too large to broadcast.
    """
    verdicts = judged(written(measured(docs, text, {host: "host"}), "measures"), rules)
    (name,) = fresh(docs, "_host")
    bad = verdicts.where(F.col("host_rate") >= rules.max_host_rate).select(F.col("host").alias(name)).distinct()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x for b in batches for x in W.bites(b, b.schema.get_field_index(text))):
            m = measure(b.column(b.schema.get_field_index(text)))
            ok = (m["n_words"] >= rules.min_words) & (100 * m["n_repeat_words"] <= rules.max_repeat_percent * m["n_words"])
            yield b.filter(pa.array(ok))

    good = docs.mapInArrow(W.trimmed(run), docs.schema)
    many = bad.count()
    if not many:
        return good
    return good.join(F.broadcast(bad) if many <= BROADCAST_HOSTS else bad, F.col(f"`{host}`").eqNullSafe(F.col(name)), "left_anti")


def op9_host_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return host_quality(docs).select("doc_id", *MEASURES, "base_failed", "kept", F.round("host_rate", 6).alias("host_rate"))


QUERIES = {"op9_host_rules": op9_host_rules}
_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_FAILED = "base_failed OR 100 * n_symbols > 10 * word_chars OR word_chars < 2 * n_words OR word_chars > 15 * n_words OR 100 * n_dup_lines > 30 * greatest(n_lines, 1)"
ORACLES = {
    "op9_host_rules": f"""WITH d AS (SELECT doc_id, source, coalesce(text, '') AS text, {_WORDS} AS ws FROM documents),
b AS (SELECT doc_id, source, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars, CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols FROM d),
ln AS (SELECT doc_id, count(*) AS n_lines, count(*) - count(DISTINCT line) AS n_dup_lines FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM d) q WHERE regexp_matches(line, '[^\\x20\\x09-\\x0D]') GROUP BY doc_id),
wd AS (SELECT doc_id, unnest(ws) AS w, unnest(range(1, len(ws) + 1)) AS i FROM d),
w3 AS (SELECT doc_id, i, w || chr(10) || lead(w, 1) OVER p || chr(10) || lead(w, 2) OVER p AS g FROM wd WINDOW p AS (PARTITION BY doc_id ORDER BY i)),
rp AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM w3 WHERE g IS NOT NULL) q WHERE c > 1),
rw AS (SELECT doc_id, count(DISTINCT i) AS n_repeat_words FROM (SELECT doc_id, i FROM rp UNION ALL SELECT doc_id, i + 1 FROM rp UNION ALL SELECT doc_id, i + 2 FROM rp) q GROUP BY doc_id),
m AS (SELECT b.*, coalesce(n_lines, 0) AS n_lines, coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words FROM b LEFT JOIN ln USING (doc_id) LEFT JOIN rw USING (doc_id)),
j AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m),
h AS (SELECT source, CAST(count(*) AS DOUBLE) AS n, CAST(sum(CASE WHEN {_FAILED} THEN 1 ELSE 0 END) AS DOUBLE) AS f FROM j GROUP BY source),
t AS (SELECT sum(n) AS n, sum(f) AS f, count(*) AS k, sum(f * f / n) AS s, sum(n * n) AS q, (sum(f) + 0.5) / (sum(n) + 1) AS r FROM h),
v AS (SELECT r, r * (1 - r) AS inside, CASE WHEN n - q / n > 0 THEN (s - f * f / n - (k - 1) * r * (1 - r)) / (n - q / n) ELSE 0 END AS between FROM t),
a AS (SELECT r, CASE WHEN between > 0 THEN least(greatest(inside / between - 1, 1), 1000) ELSE 1000 END AS weight FROM v)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND coalesce((h.f + r * weight) / (h.n + weight), r) < 0.5 AS kept, round(coalesce((h.f + r * weight) / (h.n + weight), r), 6) AS host_rate
FROM j LEFT JOIN h ON h.source = j.source, a"""
}
