"""Language identification, the classifier and fingerprints: identities, held-out accuracy and brute force."""

import itertools

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest

from packgraph.core.store import written
from packgraph.llm.audio_fingerprint import FILTERS, WIDEST, align, chroma, classes, fingerprint, fingerprints, melody
from packgraph.llm.language_id import Lattice, fit, held_out, identify, op4_language_id, train, vocabulary
from packgraph.llm.quality_classifier import FactorisationMachine, features, op8_quality_classifier, scored
from packgraph.llm.quality_classifier import train as train_quality

SF = "/root/testdata/sf0.01"


def segmentations(s, pieces):
    if not s:
        yield []
    for k in range(1, len(s) + 1):
        if s[:k] in pieces or k == 1:
            for rest in segmentations(s[k:], pieces):
                yield [s[:k], *rest]


def test_forward_sums_all_segmentations():
    pieces = {p: k for k, p in enumerate(["▁", "▁a", "a", "b", "ab", "ba", "aba", "▁ab"])}
    prob = np.random.default_rng(1).random((len(pieces) + 1, 2))
    words = ["abab", "a", "bca", "ccc"]
    got = Lattice(words, pieces, 3).likelihood(prob)
    for word, row in zip(words, got):
        want = sum(np.prod([prob[pieces.get(p, len(pieces))] for p in s], axis=0) for s in segmentations("▁" + word, pieces))
        assert np.allclose(row, want)
    weight = np.ones((4, 2))
    use = Lattice(words, pieces, 3).expected(prob, weight)
    want = np.zeros_like(prob)
    for word in words:
        all_ = [(s, np.prod([prob[pieces.get(p, len(pieces))] for p in s], axis=0)) for s in segmentations("▁" + word, pieces)]
        total = sum(p for _, p in all_)
        for s, p in all_:
            for x in s:
                want[pieces.get(x, len(pieces))] += p / total
    assert np.allclose(use, want)


def test_language_id_on_held_out_rows(spark):
    lang = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "lang").collect()}
    out = [r for r in op4_language_id(spark, SF).collect() if r["held_out"]]
    assert sum(r["lang_pred"] == lang[r["doc_id"]] for r in out) >= 0.98 * len(out)
    assert all(0 <= r["score"] <= 1 for r in out)


def test_language_id_edges(spark):
    rows = [(1, "the cat and the dog", "en"), (2, "der Hund und die Katze", "de"), (3, None, "en"), (4, "", "de"), (5, "12 34 ?!", None), (6, "x" * 3000, None), (7, "und der", None), (7, "und der", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = train(docs, public_tokenizers.path("piece_bpe_32k.model"))
    got = [(r["doc_id"], r["lang_pred"], r["score"]) for r in identify(docs, model).orderBy("doc_id").collect()]
    assert [x[1] for x in got if x[0] in (3, 4, 5)] == ["und"] * 3
    assert [x[1] for x in got if x[0] == 7] == ["de", "de"] and got[0][1] == "en"
    assert train(docs.where("lang = 'xx'"), public_tokenizers.path("piece_bpe_32k.model")) is None
    assert {r["lang_pred"] for r in identify(docs, None).collect()} == {"und"}
    assert identify(docs.limit(0), model).count() == 0
    assert fit([], {}, vocabulary(public_tokenizers.path("piece_bpe_32k.model"))[:10]) is None


def test_factorisation_identity():
    m = FactorisationMachine(12, 3)
    rng = np.random.default_rng(2)
    m.w[:], m.v[:], m.b = rng.normal(size=12), rng.normal(size=(12, 3)), 0.3
    f, x = np.array([1, 4, 7, 9]), np.array([0.5, 1.0, -2.0, 0.25])
    pair = sum(m.v[f[i]] @ m.v[f[j]] * x[i] * x[j] for i, j in itertools.combinations(range(4), 2))
    assert abs(m.logits(np.zeros(4, int), f, x, 2)[0] - (0.3 + m.w[f] @ x + pair)) < 1e-4
    assert m.logits(np.zeros(4, int), f, x, 2)[1] == 0.3


def test_quality_on_held_out_rows(spark):
    label = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    out = [r for r in op8_quality_classifier(spark, SF).collect() if r["held_out"] and r["doc_id"] in label]
    assert sum(r["predicted"] == label[r["doc_id"]] for r in out) >= 0.95 * len(out)
    assert all(r["predicted"] == int(r["score"] >= 0.7) for r in out)


def test_quality_edges(spark):
    docs = spark.createDataFrame([(1, "good words here", 10), (2, None, None), (3, "", 0), (3, "", 0)], "doc_id long, text string, n_chars long")
    labels = spark.createDataFrame([(1, 1), (2, None)], "doc_id long, label int")
    m = train_quality(docs, labels, ("n_chars",))
    got = [r["score"] for r in scored(docs, m, ("n_chars",)).collect()]
    assert len(got) == 4 and all(0 <= s <= 1 for s in got)
    assert abs(scored(docs, train_quality(docs, labels.limit(0))).first()["score"] - 0.5) < 1e-9
    r, f, v = features(pa.array(["a b a", None, ""]))
    assert (np.diff(r) >= 0).all() and len({*zip(r.tolist(), f.tolist())}) == len(r)


def test_chroma_finds_the_pitch():
    t = np.arange(8000) / 8000
    for semitone in range(12):
        image = chroma(np.sin(2 * np.pi * 440 * 2 ** (semitone / 12) * t), 8000)
        assert (image.argmax(axis=1) == semitone).mean() > 0.9
    assert chroma(np.zeros(8000), 8000).max() == 0 and len(chroma(np.zeros(3), 8000)) == 0


def test_integral_image_equals_sums():
    image = np.random.default_rng(3).random((40, 12))
    got = fingerprint(image)
    assert len(got) == 40 - WIDEST + 1 and len(FILTERS) == 16
    assert len(set(got.tolist())) > 20
    assert fingerprint(image)[5:].tolist() == fingerprint(image[5:]).tolist()


def test_alignment(spark):
    rng = np.random.default_rng(4)
    rate = 4000

    def tone(notes):
        t = np.arange(512) / rate
        return np.concatenate([np.sin(2 * np.pi * 300 * 2**x * t) for x in notes])

    tunes = [rng.uniform(-1.5, 1.5, 60) for _ in range(6)]
    rows = [(k, tone(x)) for k, x in enumerate(tunes)]
    rows += [(20, tone(tunes[2][10:])), (40, tone(tunes[3]) + rng.normal(0, 0.02, 60 * 512)), (60, tone(tunes[4])), (61, tone(tunes[4])), (80, np.zeros(4)), (100, None)]
    data = [(k, None if x is None else (x * 9000).astype("<i2").tobytes(), rate) for k, x in rows]
    prints = fingerprints(spark.createDataFrame(data, "rec_id long, pcm binary, rate int"))
    out = align(prints, "rec_id % 20 = 0").collect()
    best = {}
    for r in out:
        if r["class_id"] != r["query_id"]:
            best[r["query_id"]] = max(best.get(r["query_id"], (0,)), (r["votes"], r["class_id"], r["offset"], r["error_rate"]))
    assert best[20][1:3] == (2, 10) and best[20][3] < 0.05
    assert best[40][1:3] == (3, 0) and best[40][3] < 0.2
    own = [r for r in out if r["query_id"] == 60 and r["error_rate"] == 0]
    assert [(r["class_id"], r["copies"], r["offset"]) for r in own] == [(4, 3, 0)]
    assert not [r for r in out if r["query_id"] in (80, 100)]
    # brute force over all pairs of classes
    c = {r["class_id"]: np.array(r["prints"], np.int64) & 0xFFFFFFFF for r in classes(prints).collect()}
    for r in out:
        q = {20: 20, 40: 40, 60: 4, 0: 0}[r["query_id"]]
        x, y, o = c[q], c[r["class_id"]], r["offset"]
        n = min(len(x) - max(-o, 0), len(y) - max(o, 0))
        a, b = x[max(-o, 0) :][:n], y[max(o, 0) :][:n]
        assert r["overlap"] == n and r["bit_errors"] == sum(int(i ^ j).bit_count() for i, j in zip(a.tolist(), b.tolist()))
        assert r["votes"] == max(sum(1 for s, i in enumerate(x) for t, j in enumerate(y) if i == j and t - s == d) for d in {t - s for s, i in enumerate(x) for t, j in enumerate(y) if i == j})


def test_melody_and_empty(spark):
    v = spark.createDataFrame([(1, [0.1] * 64), (2, None)], "rec_id long, embedding array<float>")
    assert [len(r["pcm"]) for r in melody(v).orderBy("rec_id").collect()] == [64 * 512 * 2, 0]
    assert align(fingerprints(melody(v.limit(0))), "rec_id % 20 = 0").count() == 0


def test_common_integers_vote(spark):
    """Recordings that share three single integers at one offset match, also when very many hold these integers."""
    rows = [(20 * k, [10_000 * k + j if j % 4 else 7 + j for j in range(12)]) for k in range(1, 101)]
    out = align(written(spark.createDataFrame(rows, "rec_id long, prints array<int>"), "prints"), "rec_id = 20").collect()
    assert {(r["class_id"], r["offset"], r["votes"]) for r in out if r["class_id"] != 20} == {(20 * k, 0, 3) for k in range(2, 101)}


def test_words_and_segmentations_cost_what_they_must():
    """Numbers that are no letters part words as before, and a place is left when no piece goes on."""
    from packgraph.llm import language_id as L

    texts = ["x²y Ⅷ ab_c9d éa" * 3, "plain ascii words_and 12 more", "größe ½ maß", "z" * 60, "", "𐄇a b"]
    for text in texts:
        assert L.letters(text) == L._WORD.findall(text.lower())
    assert L.letters("größe ohne zahlen") == ["größe", "ohne", "zahlen"]

    class Counted(dict):
        asked = 0

        def get(self, key):
            Counted.asked += 1
            return super().get(key)

    pieces = {p: k for k, p in enumerate(["a", "ab", "abc", "b", "c", "xyz"])}
    lattice = L.Lattice(["abcabc" * 3 + "q" * 20], pieces, 20, Counted(L.beginnings(pieces)))
    assert set(zip(lattice.i[:6].tolist(), lattice.j[:6].tolist())) == {(0, 1), (1, 2), (1, 3), (2, 3), (1, 4), (3, 4)}
    assert Counted.asked < 120
