"""Language identification by segmentation-marginalised unigrams.

Each language has a probability for every piece of a fixed public vocabulary. A word's likelihood is the sum, over
all ways to cut it into pieces, of the products of their probabilities (forward algorithm);
a text's is the product over its words. Probabilities are fitted by expectation
maximisation over the same segmentations on a bounded sample of labelled rows.

Words are scored once for each worker's table of known words, all languages and a batch of new words
at a time; a text is a sum of rows of that table.

Defined results: ``und`` with score 0 where the text is null or has no letter, or nothing could be learned; rows are
judged one by one, so repeated rows agree; no rows give no rows; extra columns are ignored.
"""

from __future__ import annotations

import re
import sys
from collections import Counter
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: A run of letters, of at most this many characters at a time (longer ones are scored in parts).
LONGEST = 24
#: Numbers that are neither letters nor decimal digits (superscripts, fractions, Roman numerals), which \\w holds too.
_NUMBERS = "".join(c for c in map(chr, range(sys.maxunicode + 1)) if c.isalnum() and not c.isalpha() and not c.isdecimal())
_WORD = re.compile(rf"[^\W\d_{_NUMBERS}]{{1,{LONGEST}}}")
#: The same where a text has none of those numbers: a class of so many characters is searched one by one.
_PLAIN = re.compile(rf"[^\W\d_]{{1,{LONGEST}}}")
_NUMBER_SET = frozenset(_NUMBERS)
MARK = "▁"
ROWS_PER_LANGUAGE = 400
KNOWN_WORDS = 600_000
PART = 20_000


def letters(text: str | None) -> list[str]:
    """The text's words in lower case, for training and prediction alike."""
    if not text:
        return []
    low = text.lower()
    return (_PLAIN if low.isascii() or _NUMBER_SET.isdisjoint(low) else _WORD).findall(low)


def vocabulary(path: str) -> list[str]:
    """Pieces of a sentencepiece model that are text: no control, unknown or byte pieces."""
    import sentencepiece

    m = sentencepiece.SentencePieceProcessor(model_file=path)
    return [m.id_to_piece(i) for i in range(m.get_piece_size()) if not (m.is_control(i) or m.is_unknown(i) or m.is_byte(i))]


def beginnings(pieces: dict[str, int]) -> dict[str, int]:
    """The number of each piece, and -1 for what only begins some."""
    out = {p[:k]: -1 for p in pieces for k in range(1, len(p))}
    return out | pieces


class Lattice:
    """All segmentations of a batch of words: edges (word, from, to, piece), ordered by their end. ``begun``: the pieces' ``beginnings``; from each place
    a word is followed while some piece goes on."""

    def __init__(self, words: list[str], pieces: dict[str, int], longest: int, begun: dict[str, int] | None = None):
        if begun is None:
            begun = beginnings({p: k for p, k in pieces.items() if len(p) <= longest})
        count, i_, j_, p_ = [], [], [], []
        unknown, find = len(pieces), begun.get
        add_i, add_j, add_p = i_.append, j_.append, p_.append
        for word in words:
            s = MARK + word
            n, had = len(s) + 1, len(p_)
            for i in range(n - 1):
                p = find(s[i])
                add_i(i), add_j(i + 1), add_p(unknown if p is None or p < 0 else p)
                if p is None:
                    continue
                for j in range(i + 2, n):
                    p = find(s[i:j])
                    if p is None:
                        break
                    if p >= 0:
                        add_i(i), add_j(j), add_p(p)
            count.append(len(p_) - had)
        j = np.array(j_, np.int64)
        order = np.argsort(j, kind="stable")
        at = np.repeat(np.arange(len(words)), count)
        self.word, self.i, self.j, self.piece = (np.array(x, np.int64)[order] for x in (at, i_, j_, p_))
        self.length = np.array([len(w) + 1 for w in words], np.int64)
        self.cuts = np.searchsorted(self.j, np.arange(1, (self.length.max(initial=0)) + 2))

    def forward(self, prob: np.ndarray) -> np.ndarray:
        """prob: pieces (and last the unknown character) by languages. Sums over segmentations up to each place."""
        alpha = np.zeros((len(self.cuts), len(self.length), prob.shape[1]))
        alpha[0] = 1
        for j in range(1, len(self.cuts)):
            e = slice(self.cuts[j - 1], self.cuts[j])
            w = self.word[e]
            if len(w):
                begin = np.flatnonzero(np.concatenate([[True], w[1:] != w[:-1]]))
                alpha[j, w[begin]] = np.add.reduceat(alpha[self.i[e], w] * prob[self.piece[e]], begin, axis=0)
        return alpha

    def likelihood(self, prob: np.ndarray) -> np.ndarray:
        return self.forward(prob)[self.length, np.arange(len(self.length))]

    def expected(self, prob: np.ndarray, weight: np.ndarray) -> np.ndarray:
        """Expected uses of each piece in words that occur ``weight`` (words by languages) times."""
        alpha = self.forward(prob)
        total = alpha[self.length, np.arange(len(self.length))]
        beta = np.zeros_like(alpha)
        beta[self.length, np.arange(len(self.length))] = 1
        for j in range(len(self.cuts) - 1, 0, -1):
            e = slice(self.cuts[j - 1], self.cuts[j])
            w = self.word[e]
            np.add.at(beta, (self.i[e], w), beta[j, w] * prob[self.piece[e]])
        use = alpha[self.i, self.word] * prob[self.piece] * beta[self.j, self.word] * (weight / np.maximum(total, 1e-300))[self.word]
        out = np.zeros_like(prob)
        np.add.at(out, self.piece, use)
        return out


class Model:
    """Piece probabilities by language."""

    def __init__(self, languages: list[str], prior: np.ndarray, pieces: list[str], prob: np.ndarray):
        self.languages, self.prior, self.prob = languages, prior, prob
        self.pieces = {p: k for k, p in enumerate(pieces)}
        self.longest = max(map(len, pieces), default=1)

    @cached_property
    def begun(self) -> dict[str, int]:
        return beginnings(self.pieces)

    def log_likelihood(self, words: list[str]) -> np.ndarray:
        return np.log(np.maximum(Lattice(words, self.pieces, self.longest, self.begun).likelihood(self.prob), 1e-300))


def fit(counts: list[tuple[str, str, int]], shares: dict[str, int], pieces: list[str], rounds: int = 4, floor: float = 1e-7, shared: float = 1e-3) -> Model | None:
    """counts: (language, word, occurrences); shares: documents by language."""
    languages = sorted({c[0] for c in counts})
    if not languages:
        return None
    words = sorted({c[1] for c in counts})
    row, col = {w: k for k, w in enumerate(words)}, {x: k for k, x in enumerate(languages)}
    weight = np.zeros((len(words), len(languages)))
    for language, word, n in counts:
        weight[row[word], col[language]] += n
    index = {p: k for k, p in enumerate(pieces)}
    longest, begun = max(map(len, pieces)), beginnings(index)
    order = sorted(range(len(words)), key=lambda k: len(words[k]))  # words of one length together: tables of a part are as wide as its longest
    parts = [order[i : i + PART] for i in range(0, len(order), PART)]
    lattices = [Lattice([words[k] for k in part], index, longest, begun) for part in parts]
    weights = [weight[part] for part in parts]
    use = np.zeros((len(pieces) + 1, len(languages)))
    for x, w in zip(lattices, weights):
        np.add.at(use, x.piece, w[x.word])  # to begin with: every piece wherever it fits
    for _ in range(rounds + 1):
        prob = use / np.maximum(use.sum(axis=0), 1e-300)
        prob = (1 - shared) * prob + shared * prob.mean(axis=1, keepdims=True) + floor
        prob[-1] = np.minimum(prob[-1], floor)
        prob /= prob.sum(axis=0)
        if _ < rounds:
            use = sum(x.expected(prob, w) for x, w in zip(lattices, weights))
    seen = np.flatnonzero(use[:-1].sum(axis=1) > 0)  # others differ in no language and only cost lookups; single characters stay
    keep = sorted({*seen.tolist(), *(index[p] for p in pieces if len(p) == 1)})
    prior = np.log(np.array([shares.get(x, 0) + 1.0 for x in languages]) / sum(shares.get(x, 0) + 1 for x in languages))
    return Model(languages, prior, [pieces[k] for k in keep], prob[[*keep, len(pieces)]])


class _Table(dict):
    """Number of each known word; new ones are noted."""

    def __init__(self):
        self.new = []

    def __missing__(self, word: str) -> int:
        self[word] = n = len(self)
        self.new.append(word)
        return n


class Scorer:
    def __init__(self, model: Model, known: int = KNOWN_WORDS):
        self.model, self.known = model, known
        self._reset()

    def _reset(self) -> None:
        self.table, self.rows = _Table(), np.zeros((0, len(self.model.languages)), np.float32)
        self.filled = 0

    def __call__(self, texts: list[str | None]) -> list[tuple[str, float]]:
        out = []
        for i in range(0, len(texts), 256):
            if len(self.table) > self.known:
                self._reset()
            found = [letters(t) for t in texts[i : i + 256]]
            number = self.table.__getitem__
            rows = [list(map(number, w)) for w in found]
            if self.table.new:
                need = len(self.table)
                if need > len(self.rows):
                    self.rows = np.concatenate([self.rows, np.zeros((max(need, 2 * len(self.rows)) - len(self.rows), self.rows.shape[1]), np.float32)])
                for k in range(0, len(self.table.new), 20_000):
                    part = self.table.new[k : k + 20_000]
                    self.rows[self.filled : self.filled + len(part)] = self.model.log_likelihood(part)
                    self.filled += len(part)
                self.table.new = []
            for r in rows:
                if not r:
                    out.append(("und", 0.0))
                    continue
                logit = self.rows[np.array(r)].sum(axis=0, dtype=np.float64) + self.model.prior
                k = int(np.argmax(logit))
                out.append((self.model.languages[k], float(1 / np.exp(logit - logit[k]).sum())))
        return out


def held_out(doc_id: str = "doc_id"):
    """Rows no label is learned from: crc32 of the id as text, modulo 4, is 2."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def sample(labelled: DataFrame, most: int) -> tuple[DataFrame, dict[str, int]]:
    """(at most ``most`` rows a language, those of the smallest hashes of doc_id; rows a language).

    Hashes above a bound that leaves about twice as many go first, so that no language is sorted whole in one task.
    """
    shares = {r["lang"]: r["count"] for r in labelled.groupBy("lang").count().collect()}  # a row a language
    if not shares:
        return labelled, shares
    share = F.create_map(*[F.lit(x) for k, n in shares.items() for x in (k, min(1.0, (2 * most + 100) / n))])
    place = F.xxhash64("doc_id") / F.lit(2.0**64) + 0.5
    few = labelled.withColumn("_place", place).where(F.col("_place") <= F.element_at(share, F.col("lang")))
    order = Window.partitionBy("lang").orderBy("_place", "doc_id", F.xxhash64("text"))
    return few.withColumn("_k", F.row_number().over(order)).where(F.col("_k") <= most).select("lang", "text"), shares


def train(docs: DataFrame, vocabulary_path: str, rows_per_language: int = ROWS_PER_LANGUAGE) -> Model | None:
    """Fits on (doc_id, text, lang): all words of at most ``rows_per_language`` rows a language, chosen by a hash of
    the id. Languages' shares come from all rows."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "lang", "text")
    chosen, shares = sample(labelled, rows_per_language)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lang, text in zip(b.column(0).to_pylist(), b.column(1)):
                c = Counter(letters(text.as_py()))
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(c), pa.string()), pa.array(list(c), pa.string()), pa.array(list(c.values()), pa.int64())], names=["lang", "word", "n"])

    counted = chosen.mapInArrow(count, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    counts = [(r["lang"], r["word"], r["n"]) for r in counted.collect()]  # the words of a bounded sample
    return fit(counts, shares, vocabulary(vocabulary_path))


def identify(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, lang_pred, score for every row, from the text alone."""
    kind = dict(docs.dtypes)["doc_id"]
    shared = docs.sparkSession.sparkContext.broadcast(model)  # pieces by languages: bounded by the vocabulary

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = Scorer(shared.value) if shared.value else lambda texts: [("und", 0.0)] * len(texts)
        for b in batches:
            got = [x for i in range(0, b.num_rows, 512) for x in score(b.column(1).slice(i, 512).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x for x, _ in got], pa.string()), pa.array([x for _, x in got], pa.float64())], names=["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, lang_pred string, score double")


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as P

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    model = train(docs.where(~held_out()), P.path("piece_bpe_32k.model"))
    return identify(docs, model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


QUERIES = {"op4_language_id": op4_language_id}
ORACLES: dict[str, str] = {}
