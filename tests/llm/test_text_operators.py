"""Operators on texts against brute force, on a small fixture with nulls, empty and long texts, ties and repeats."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from packgraph.llm.byte_bpe import decode_documents, encode_documents, load_ranks, words
from packgraph.llm import line_dedup
from packgraph.llm.common import components, tables
from packgraph.llm.host_rules import HostRules, filter_hosts, host_quality
from packgraph.llm.line_dedup import _apart, dedup_lines
from packgraph.llm.ngram_join import SignatureTree, folded, jaccard_components, need, traverse
from packgraph.llm.packing import column_generation, knapsack, pack_documents, plan
from packgraph.llm.substring_dedup import COVER, PERIOD, remove_substrings, substring_report
from packgraph.llm.token_file import read_token_file, vbyte_decode, vbyte_encode, write_token_file

WORD = re.compile(rb"[^\x20\x09-\x0D]+")
TOKENIZER = public_tokenizers.path("word_bpe_49k.json")
RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
rng = np.random.default_rng(5)
VOCABULARY = ["".join(rng.choice(list("abcdeéßñ"), rng.integers(1, 7))) for _ in range(400)]


def prose(n: int) -> str:
    w = rng.choice(VOCABULARY, n).tolist()
    return "".join(x + ("\n" if rng.random() < 0.05 else " ") for x in w)


BASE, PASSAGE = [prose(int(n)) for n in rng.integers(5, 300, 40)], prose(60)
TEXTS: list = [*BASE, BASE[0], BASE[0], BASE[1].upper(), None, "", "  \n\t ", "one", "one two three", " ".join(["x"] * 5000), "a" * 30_000, "tab\tvt\x0bnb sp \x1c fs"]
TEXTS += [prose(50) + PASSAGE + prose(50) for _ in range(6)]
for k in range(2, 12):  # near copies
    w = BASE[k].split(" ")
    for c in range(3):
        v = list(w)
        v[int(rng.integers(len(v)))] = f"edit{k}{c}"
        TEXTS.append(" ".join(v))
IDS = list(range(100, 100 + len(TEXTS)))


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", "h%d" % (i % 3) if i % 7 else None, -1, "kept") for i, t in zip(IDS, TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, _host int, n string").repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, source string")



def split(t):
    return WORD.findall((t or "").encode())


def test_vbyte():
    v = np.array([0, 255, 256, 65535, 65536, 2**24 - 1, 2**24, 2**32 - 1, 7], np.uint32)
    control, data = vbyte_encode(v)
    assert len(control) == 3 and len(data) == 1 + 1 + 2 + 2 + 3 + 3 + 4 + 4 + 1
    assert vbyte_decode(control, data, len(v)).tolist() == v.tolist()


def test_token_file(spark, docs, none, tmp_path):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(TOKENIZER)
    write_token_file(docs, str(tmp_path / "f"), TOKENIZER, 1)
    at = 0
    got = {r["doc_id"]: r for r in read_token_file(spark, str(tmp_path / "f")).collect()}
    for i, text in zip(IDS, TEXTS):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 1]
        r = got[i]
        assert (r["start"], r["n_tokens"], np.frombuffer(r["ids"], "<u4").tolist()) == (at, len(ids), ids)
        at += len(ids)
    write_token_file(none, str(tmp_path / "e"), TOKENIZER, 1)
    assert read_token_file(spark, str(tmp_path / "e"), digest=True).count() == 0


def test_byte_bpe(spark, docs, none):
    import tiktoken

    e = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=load_ranks(RANKS), special_tokens={})
    out = encode_documents(docs, RANKS, public_tokenizers.PATTERN, stable=False)
    got = {r["doc_id"]: r["ids"] for r in out.collect()}
    for i, text in zip(IDS, TEXTS):
        assert got[i] == (None if text is None else e.encode_ordinary(text))
    assert {r["doc_id"]: r["text"] for r in decode_documents(out, RANKS, public_tokenizers.PATTERN).collect()} == dict(zip(IDS, TEXTS))
    assert encode_documents(none, RANKS, public_tokenizers.PATTERN, digest=True).count() == 0
    for text in ("", " ", "a  b", " a", "a ", "a\n b", "x \n\n y", "  a  ", "  a"):
        w = words(text)
        assert sum((e.encode_ordinary(x if k == 0 else " " + x) for k, x in enumerate(w)), []) == e.encode_ordinary(text)


def test_host_rules(docs, none):
    got = {r["doc_id"]: r for r in host_quality(docs).collect()}
    for i, text in zip(IDS, TEXTS):
        w = split(text)
        c, hit = Counter(zip(w, w[1:], w[2:])), set()
        for k, z in enumerate(zip(w, w[1:], w[2:])):
            if c[z] > 1:
                hit |= {k, k + 1, k + 2}
        seen, dup = set(), 0
        for line in (text or "").split("\n"):
            if WORD.search(line.encode()):
                dup += line in seen
                seen.add(line)
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(len(x.decode()) for x in w), dup, len(hit))
        assert r["base_failed"] == (len(w) < 50 or 100 * len(hit) > 50 * len(w))
        assert not (r["kept"] and r["base_failed"])
    kept = filter_hosts(docs)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(i for i, r in got.items() if r["kept"])
    assert host_quality(none).count() == 0 and filter_hosts(none).count() == 0


def test_bad_host_goes(spark):
    good, junk = " ".join(f"w{k}" for k in range(60)), "| # |"
    rows = [(k, good, "fine") for k in range(200)] + [(1000 + k, junk if k % 10 else good, "bad") for k in range(100)] + [(2000, junk, "small"), (2001, good, "small")]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string")
    kept = {r["doc_id"] for r in host_quality(d, rules=HostRules()).where("kept").collect()}
    assert kept == {*range(200), 2001}


def jaccard_truth(k, percent):
    sets = []
    for t in TEXTS:
        w = split((t or "").translate({c: c + 32 for c in range(65, 91)}))
        sets.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set()))
    root = list(range(len(sets)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(sets)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return [(len(s), IDS[find(k)]) for k, s in enumerate(sets)]


@pytest.mark.parametrize("k,percent", [(4, 85), (5, 80)])
def test_ngram_join(docs, none, k, percent):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_components(docs, k, percent).collect()}
    assert [got[i] for i in IDS] == jaccard_truth(k, percent)


def test_ngram_join_of_nothing(none):
    assert jaccard_components(none).count() == 0


def test_signature_tree_loses_no_link():
    sets = [set(rng.integers(0, 400, rng.integers(20, 60)).tolist()) for _ in range(30)]
    sets += [(s - set(list(s)[:2])) | {1000 + k} for k, s in enumerate(sets)] * 3
    n = np.array([len(s) for s in sets])
    bits = []
    for s in sets:
        b = np.zeros(128, np.uint8)
        b[[x * 2654435761 % 128 for x in s]] = 1
        bits.append(np.packbits(b, bitorder="little").tobytes())
    order = np.argsort(n, kind="stable")
    tree = SignatureTree(n[order], folded([bits[k] for k in order], 16), np.arange(len(sets)))
    found = {frozenset((order[a], order[b])) for p, q in traverse(tree, tree, 80, True) for a, b in zip(p, q)}
    want = {frozenset((a, b)) for a in range(len(sets)) for b in range(a) if len(sets[a] & sets[b]) >= need(n[a], n[b], 80)}
    assert want <= found
    assert len(found) < len(sets) * (len(sets) - 1) / 4


def test_cover_aligns_all_starts():
    assert {(a - b) % PERIOD for a in COVER for b in COVER} == set(range(PERIOD))


def test_substring_dedup(docs, none):
    got = {r["doc_id"]: r for r in substring_report(docs).collect()}
    c = Counter(tuple(w[k : k + 35]) for w in map(split, TEXTS) for k in range(len(w) - 34))
    for i, text in zip(IDS, TEXTS):
        w = split(text)
        gone = [False] * len(w)
        for k in range(len(w) - 34):
            if c[tuple(w[k : k + 35])] > 1:
                gone[k : k + 35] = [True] * 35
        kept = b" ".join(x for x, g in zip(w, gone) if not g)
        r = got[i]
        assert (r["n_words"], r["n_removed"], r["kept_sha256"]) == (len(w), sum(gone), hashlib.sha256(kept).hexdigest())
        assert sum(s["end"] - s["start"] for s in r["spans"]) == sum(gone)
    out = remove_substrings(docs)
    assert out.columns == docs.columns
    texts = {r["doc_id"]: r["text"] for r in out.collect()}
    for i, text in zip(IDS, TEXTS):
        assert texts[i] == text if not got[i]["n_removed"] else hashlib.sha256(texts[i].encode()).hexdigest() == got[i]["kept_sha256"]
    assert substring_report(none).count() == 0 and remove_substrings(none).count() == 0


def line_set(line):
    return {line[k : k + 12] for k in range(max(1, len(line) - 11))}


def test_line_dedup(spark, docs, none):
    out = dedup_lines(docs)
    assert out.columns == [*docs.columns, "removed_lines"]
    got = {r["doc_id"]: (r["text"], r["removed_lines"]) for r in out.collect()}
    first, where = {}, defaultdict(list)
    for i, text in zip(IDS, TEXTS):
        for p, line in enumerate((text or "").split("\n")):
            if re.search(r"\S", line, re.A):
                first.setdefault(line, (i, p))
                where[line].append((i, p))
    sets, root = {x: line_set(x) for x in first}, {x: x for x in first}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    names = sorted(first, key=first.get)
    for a, x in enumerate(names):
        for y in names[:a]:
            both = len(sets[x] & sets[y])
            if both and both >= 0.8 * (len(sets[x]) + len(sets[y]) - both):
                u, v = find(x), find(y)
                root[max(u, v, key=first.get)] = min(u, v, key=first.get)
    gone = defaultdict(list)
    for line, places in where.items():
        for i, p in places:
            if (i, p) != first[find(line)]:
                gone[i].append(p)
    wrong = sum(sorted(gone[i]) != got[i][1] for i in IDS)
    assert wrong <= 2  # banding may miss a link
    for i, text in zip(IDS, TEXTS):
        left = None if text is None else "\n".join(x for p, x in enumerate(text.split("\n")) if p not in got[i][1])
        assert got[i][0] == left
    assert dedup_lines(none).count() == 0
    plan_text = out._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow", plan_text)


def test_line_dedup_of_stars(spark):
    """Variants alike to one original and not to each other, more than are compared with one another."""
    rng = np.random.default_rng(8)
    rows = []
    for s in range(3):
        base = ["".join(rng.choice(list("abcdefgh"), 6)) for _ in range(34)]
        rows += [" ".join(base)]
        for k in range(150):
            v = list(base)
            v[k % 34] = f"{s}v{k:04d}"
            rows.append(" ".join(v))
    docs = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string").repartition(3)
    kept = {r["doc_id"] for r in dedup_lines(docs).collect() if not r["removed_lines"]}
    sets = [line_set(x) for x in rows]
    centre = [k // 151 * 151 for k in range(len(rows))]
    linked = [len(sets[k] & sets[c]) >= 0.8 * len(sets[k] | sets[c]) for k, c in enumerate(centre)]
    assert sum(linked) > 400
    assert kept == {k for k in range(len(rows)) if k == centre[k] or not linked[k] and not any(len(sets[k] & sets[o]) >= 0.8 * len(sets[k] | sets[o]) for o in range(len(rows)) if o != k)}


def test_line_dedup_of_many_variants(spark):
    """Variants of a line that is not there: those with own words in too many places are joined with nothing, and no similar pair is lost."""
    rng = np.random.default_rng(9)
    base = ["".join(rng.choice(list("abcdefgh"), 6)) for _ in range(60)]
    lines = []
    for k in range(240):
        v = list(base)
        for place in rng.choice(np.arange(1, 59, 3), 4 if k % 8 else 1, replace=False):
            v[place] = f"v{k:03d}{place:02d}"
        lines.append(" ".join(v))
    texts = spark.createDataFrame([((k, k), x) for k, x in enumerate(lines)], "id struct<h1: bigint, h2: bigint>, line string")
    alone = spark.createDataFrame([], "id struct<h1: bigint, h2: bigint>, root struct<h1: bigint, h2: bigint>")
    got = {(r["a"]["h1"], r["b"]["h1"]) for r in _apart(texts, alone, 0.8).collect()}
    sets = [line_set(x) for x in lines]
    similar = {(a, b) for b in range(len(lines)) for a in range(b) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])}
    assert len(similar) >= 435 and similar <= got and len(got) < 3 * len(similar)


def test_line_dedup_leaves_small_plans_and_tables(spark):
    """The table that orders shingles doesn't fill plan descriptions, and what nothing reads any more is removed."""
    texts = spark.range(9000).selectExpr("struct(id as h1, id as h2) as id", "concat('line number ', id) as line")
    alone = spark.createDataFrame([], "id struct<h1: bigint, h2: bigint>, root struct<h1: bigint, h2: bigint>")
    assert len(_apart(texts, alone, 0.8)._jdf.queryExecution().analyzed().toString()) < 1_000_000
    before = set(tables())
    ordered = " ".join(f"word{k * k}" for k in range(40))
    docs = spark.createDataFrame([(k, f"{ordered} and {k}\n{ordered}") for k in range(80)], "doc_id long, text string")
    dedup_lines(docs)
    left = {path.rsplit("/", 1)[1].split("-")[1] for path in tables() if path not in before}
    assert "gone" in left and not left & {"lines", "held", "candidates", "texts", "groups", "pairs", "apart", "sets", "prefixes"}


def test_line_dedup_creates_few_files(spark, monkeypatch):
    """Its many small shuffles are not written as a file a partition; the session's setting is as before afterwards, and common lines go as others do."""
    key, seen = "spark.sql.shuffle.partitions", []
    monkeypatch.setattr(line_dedup, "written", lambda df, name, f=line_dedup.written: seen.append(int(spark.conf.get(key))) or f(df, name))
    docs = spark.createDataFrame([(k, f"number {k * 7919} of all\nthe same line everywhere") for k in range(60)], "doc_id long, text string")
    was = spark.conf.get(key)
    try:
        spark.conf.set(key, "200")
        out = dedup_lines(docs)
        assert spark.conf.get(key) == "200" and seen and min(seen) > 200
        spark.conf.set(key, "4")
        seen.clear()
        few = dedup_lines(docs)
        assert set(seen) == {4}
    finally:
        spark.conf.set(key, was)
    for found in (out, few):
        assert {r["doc_id"]: r["removed_lines"] for r in found.collect()} == {k: [1] if k else [] for k in range(60)}


def test_line_dedup_of_ends_and_short_lines(spark):
    apart = ["The measured temperature was 21.5", "The measured temperature was 37.0", "number 100000000000001 here", "number 100000000000002 here", "kürz", "kurz"]
    near = [("abcdefghijklmnopqrstu", "bcdefghijklmnopqrstu"), ("a b c d e f g h i j k", "b c d e f g h i j k"), ("zyxwvutsrqponmlkjihgfedcb", "yxwvutsrqponmlkjihgfedcb")]
    once = "again and again we say " * 12 + "to the one who does not want to hear of it at all"
    near.append((once, "But " + once))
    lines = [*apart, *(x for p in near for x in p)]
    docs = spark.createDataFrame([(k, x) for k, x in enumerate(lines)], "doc_id long, text string")
    gone = {r["doc_id"] for r in dedup_lines(docs).collect() if r["removed_lines"]}
    assert gone == {len(apart) + 2 * k + 1 for k in range(len(near))}


def test_line_dedup_of_edges(spark):
    lines = ["Invoice for the customer with number 4711", "Invoice for the customer with number 0815", "=" * 100, "=" * 300, None, "", "kürz", "kürz"]
    rows = [(k, x, "s") for k, x in enumerate(lines)] + [(None, "kürz", "s"), (7, "kürz", "s"), (8, "one\ntwo", "s"), (8, "two\none", "s")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, removed_lines string")
    out = dedup_lines(docs)
    assert out.columns == ["doc_id", "text", "removed_lines", "_removed_lines"]
    got = Counter((r["doc_id"], r["text"], tuple(r["_removed_lines"])) for r in out.collect())
    want = [(0, lines[0], ()), (1, lines[1], ()), (2, lines[2], ()), (3, "", (0,)), (4, None, ()), (5, "", ()), (6, "kürz", ()), (7, "", (0,)), (7, "", (0,)), (None, "kürz", ()), (8, "one", (1,)), (8, "two", (1,))]
    assert got == Counter(want)


def test_line_dedup_recall(spark):
    """All similar pairs of the lines of sf0.01, by an index of all runs of 12 characters, against the operator's components."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    rows = sorted((r["doc_id"], r["text"] or "") for r in docs.collect())
    first = {}
    for i, text in rows:
        for p, line in enumerate(text.split("\n")):
            if re.search(r"\S", line, re.A):
                first.setdefault(line, (i, p))
    lines = sorted(first, key=first.get)
    often = Counter(x for line in lines for x in line_set(line))
    held, links, root = defaultdict(list), 0, list(range(len(lines)))

    def find(x):
        while root[x] != x:
            root[x] = x = root[root[x]]
        return x

    sets = {}
    for k in sorted(range(len(lines)), key=lambda k: len(line_set(lines[k]))):
        s = sets[k] = line_set(lines[k])
        rare = sorted(s, key=lambda x: (often[x], x))[: len(s) - -(-4 * len(s) // 5) + 1]
        for o in {o for x in rare for o in held[x]}:
            both = len(s & sets[o])
            if both * 10 >= 8 * (len(s) + len(sets[o]) - both):
                links += 1
                a, b = sorted((find(k), find(o)))
                root[b] = a
        for x in rare:
            held[x].append(k)
    gone = {(r["doc_id"], p) for r in dedup_lines(docs).collect() for p in r["removed_lines"]}
    number = {x: k for k, x in enumerate(lines)}
    want = {(i, p) for i, text in rows for p, line in enumerate(text.split("\n")) if line in first and (i, p) != first[lines[find(number[line])]]}
    assert links > 50 and gone <= want and len(gone) >= 0.99 * len(want)


def test_knapsack_and_plan():
    sizes = np.array([3, 5, 7])
    value, count = knapsack(sizes, np.array([3.0, 5.5, 8.0]), 12)
    assert abs(value - 13.5) < 1e-9 and count.tolist() == [0, 1, 1]
    demand = rng.integers(1, 50, 40)
    sizes = np.sort(rng.choice(np.arange(1, 257), 40, replace=False))
    left = demand.copy()
    used = 0
    for times, pattern in plan(sizes, demand, 256):
        assert sum(sizes[i] * k for i, k in pattern.items()) <= 256
        used += times
        for i, k in pattern.items():
            left[i] -= times * k
    assert not left.any()
    bound = column_generation(sizes, demand.astype(float), 256)[1].sum()
    assert bound * 0.998 <= used <= bound + len(sizes)


def test_packing(docs, none):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(TOKENIZER)
    ids = {i: np.array([*t.encode(x or "", add_special_tokens=False).ids, 1], "<u4") for i, x in zip(IDS, TEXTS)}
    rows = pack_documents(docs, TOKENIZER).collect()
    docs_, seqs = defaultdict(list), defaultdict(list)
    for r in rows:
        x = ids[r["doc_id"]]
        assert r["doc_tokens"] == len(x) and r["ids_crc32"] == zlib.crc32(x[r["start"] : r["start"] + r["length"]].tobytes())
        docs_[r["doc_id"]].append((r["start"], r["length"]))
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
    for i, x in ids.items():
        at = 0
        for start, n in sorted(docs_[i]):
            assert start == at
            at += n
        assert at == len(x)
    for pieces in seqs.values():
        at = 0
        for offset, n in sorted(pieces):
            assert offset == at
            at += n
        assert at <= 2048
    assert sorted(seqs) == list(range(len(seqs)))
    assert pack_documents(none, TOKENIZER).count() == 0


def test_components(spark):
    edges = [(k, k + 1) for k in range(0, 60)] + [(100, 200), (300, 200), (300, 400)] + [(500, 500 + k) for k in range(1, 30)]
    got = {r["id"]: r["root"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(61), 0), **dict.fromkeys((100, 200, 300, 400), 100), **dict.fromkeys(range(500, 530), 500)}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
