"""Corpus operators against brute force, on small tables with nulls, ties, repeats and clashing columns."""

import base64
import bz2
import collections
import gzip
import hashlib
import lzma
import os
import random
import re
import urllib.parse
import zlib

import numpy as np
import pytest
import zstandard
from pyspark.sql import functions as F

from pathlift.llm import pieces as pc
from pathlift.llm.ann_forest import nearest
from pathlift.llm.components import connected
from pathlift.llm.frames import Workspace, held_out
from pathlift.llm.language_id import fit_language_model, identify_language
from pathlift.llm.mixing import mix
from pathlift.llm.ngram_join import similar_groups
from pathlift.llm.quality_rules import judge
from pathlift.llm.secret_scan import base_spans, redact, scan, scan_secrets
from pathlift.llm.substring_dedup import remove_repeats
from pathlift.llm.toxicity import fit_toxicity, indexed, score_toxicity, train, words_of
from pathlift.llm.warc import read_warc, write_warc

WORD = re.compile(r"[^\x20\x09-\x0D]+")
MODEL = os.environ.get("PATHLIFT_PIECE_MODEL", "/opt/tokenizers/piece_bpe_32k.model")


def sentence(rng, n, vocabulary=300):
    return " ".join(f"w{rng.randrange(vocabulary)}" for _ in range(n))


def corpus(seed=1):
    """(id, text) with exact and near copies, shared passages, empty, null and repeated rows."""
    rng = random.Random(seed)
    rows = [(i, sentence(rng, rng.choice((3, 8, 40, 120)))) for i in range(60)]
    passage = sentence(rng, 30)
    for i in range(60, 90):
        base = rows[rng.randrange(60)][1].split()
        for _ in range(rng.choice((0, 0, 1, 2, 6))):
            base[rng.randrange(len(base))] = f"x{rng.randrange(999)}"
        rows.append((i, " ".join(base)))
    rows += [(i, f"{sentence(rng, 10)} {passage}\n\t{sentence(rng, 10)}") for i in range(90, 100)]
    rows += [(100, ""), (101, None), (102, "   \n "), (103, "One two"), (104, "one TWO"), (5, rows[5][1]), (None, passage), (105, "é à ü " * 40)]
    return rows


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


# --- n-gram join -------------------------------------------------------------------


def shingles(text, k):
    low = (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    w = WORD.findall(low)
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def groups_of(rows, k, percent):
    sets = [(i, shingles(t, k)) for i, t in rows]
    parent = {i: i for i, _ in sets if i is not None}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for n, (a, x) in enumerate(sets):
        for b, y in sets[:n]:
            if a is not None and b is not None and x and y and 100 * len(x & y) >= percent * len(x | y):
                low, high = sorted((find(a), find(b)))
                parent[high] = low
    return sorted(((i, len(s), None if i is None else find(i)) for i, s in sets), key=str)


@pytest.mark.parametrize(("k", "percent"), [(4, 85), (5, 80)])
def test_join_finds_the_groups_of_brute_force(spark, k, percent):
    rows = corpus()
    df = frame(spark, rows).withColumn("component_id", F.lit("clash")).withColumn("n", F.lit(1))
    got = sorted((tuple(r) for r in similar_groups(df, words=k, percent=percent).select("doc_id", "n_shingles", "component_id").collect()), key=str)
    assert got == groups_of(rows, k, percent)


def test_join_of_a_hot_group_in_blocks(spark):
    rng = random.Random(4)
    base = sentence(rng, 60, 5000).split()
    rows = []
    for i in range(70):
        own = list(base)
        for _ in range(rng.choice((1, 2, 3, 4))):
            own[rng.randrange(60)] = f"y{i}_{rng.randrange(99)}"
        rows.append((i, " ".join(own)))
    for rounds, hot in ((0, 10), (0, 10**9), (3, 10)):
        got = sorted((tuple(r) for r in similar_groups(frame(spark, rows), words=4, percent=85, rounds=rounds, pairs_per_node=0, hot_pairs=hot).collect()), key=str)
        assert got == groups_of(rows, 4, 85)


@pytest.mark.parametrize(("rounds", "hot"), [(0, 10**9), (0, 1), (4, 10_000)])
def test_join_keeps_contained_pairs_and_pairs_of_unequal_demands(spark, rounds, hot):
    rng = random.Random(11)
    shared = sentence(rng, 24, 5000)
    rows = []
    for i in range(40):  # a text and the same text with words added, at the threshold: 40 of 50 shingles
        long = sentence(rng, 54, 10**6)
        rows += [(2 * i, " ".join(long.split()[:44])), (2 * i + 1, long)]
    for i in range(40, 70):  # one side has a frequent passage more
        own = sentence(rng, 100, 10**6)
        rows += [(2 * i, own), (2 * i + 1, f"{own} {shared}" if i % 2 else f"{shared} {own}")]
    got = sorted((tuple(r) for r in similar_groups(frame(spark, rows), words=5, percent=80, rounds=rounds, pairs_per_node=0, hot_pairs=hot).collect()), key=str)
    assert got == groups_of(rows, 5, 80)


def test_join_of_nothing(spark):
    assert similar_groups(frame(spark, [])).count() == 0


def test_components(spark):
    edges = [(1, 2), (2, 3), (3, 4), (4, 5), (9, 8), (8, 7), (7, 7), (20, 21)]
    out = {r["node"]: r["root"] for r in connected(spark.createDataFrame(edges, "a long, b long"), Workspace(spark, "t")).collect()}
    assert len({out[i] for i in range(1, 6)}) == 1 and out[7] == out[8] == out[9] and out[20] == out[21] and len(set(out.values())) == 3


# --- substring dedup ------------------------------------------------------------------


def repeats(rows, window):
    first = {}
    words = [(i, WORD.findall(t or "")) for i, t in rows]
    for i, w in words:
        for k in range(len(w) - window + 1):
            g = tuple(w[k : k + window])
            if i is not None:
                first[g] = min(first.get(g, i), i)
    out = []
    for i, w in words:
        gone = {k + j for k in range(len(w) - window + 1) if i is not None and first[tuple(w[k : k + window])] < i for j in range(window)}
        out.append((i, len(w), len(gone), hashlib.sha256(" ".join(x for k, x in enumerate(w) if k not in gone).encode()).hexdigest()))
    return sorted(out, key=str)


def test_dedup_removes_what_brute_force_removes(spark):
    rows = corpus(2) + [(200, " ".join(["again"] * 40)), (201, " ".join(["again"] * 20)), (7, "another text of the same id " * 5)]
    got = sorted((tuple(r) for r in remove_repeats(frame(spark, rows).withColumn("n_words", F.lit(0))).select("doc_id", "n_words", "n_removed", "kept_sha256").collect()), key=str)
    assert got == repeats(rows, 13)


def test_dedup_of_nothing_and_with_text(spark):
    assert remove_repeats(frame(spark, [])).count() == 0
    text = " ".join(f"a{i}" for i in range(20))
    out = {r["doc_id"]: r for r in remove_repeats(frame(spark, [(1, text), (2, f"b {text} c")]), with_text=True).collect()}
    assert out[2]["kept_text"] == "b c" and [tuple(s) for s in out[2]["repeats"]] == [(1, 21)] and out[1]["kept_text"] == text


# --- secrets ------------------------------------------------------------------------------

SECRET = 'password = "abcdefgh12345678"'


@pytest.mark.parametrize(
    "wrapped",
    [
        urllib.parse.quote(SECRET), "".join(f"\\u{ord(c):04x}" for c in SECRET), base64.b64encode(SECRET.encode()).decode(), base64.b64encode(gzip.compress(SECRET.encode())).decode(), base64.b64encode(zlib.compress(SECRET.encode())).decode(),
        base64.b64encode(bz2.compress(SECRET.encode())).decode(), base64.b64encode(urllib.parse.quote(SECRET).encode()).decode(), base64.b64encode(base64.b64encode(SECRET.encode())).decode(), base64.urlsafe_b64encode(zlib.compress(gzip.compress(SECRET.encode()))).decode().rstrip("="),
    ],
)
def test_secrets_in_nested_layers(wrapped):
    text = f"before {wrapped} after"
    base, found = scan(text)
    assert base == [] and found
    a, b, kind = found[0]
    assert kind == "assign" and 7 <= a < b <= 7 + len(wrapped)


def _packed(raw, times=1):
    for _ in range(times):
        raw = gzip.compress(raw)
    return raw


@pytest.mark.parametrize(
    "wrapped",
    [
        *[base64.b64encode(f"{c}{SECRET}{c}".encode()).decode() for c in ("\xa0", "\ufeff", "\u200b", "\f", "\0")], base64.b64encode(b"\xff" + SECRET.encode() + b"\xe2\x82").decode(),
        base64.b64encode(_packed(b"\xff\0" + SECRET.encode())).decode(), base64.b64encode(_packed(b"\xff" + base64.b64encode(SECRET.encode()))).decode(), base64.b64encode(_packed(SECRET.encode(), 12)).decode(),
        base64.b64encode(_packed(b"first member ") + _packed(SECRET.encode())).decode(), base64.b64encode(_packed(SECRET.encode()[:14]) + _packed(SECRET.encode()[14:])).decode(), base64.b64encode(bz2.compress(b"one ") + bz2.compress(SECRET.encode())).decode(),
        base64.b64encode(lzma.compress(b"one ") + lzma.compress(SECRET.encode())).decode(), base64.b64encode(zstandard.compress(b"one ") + zstandard.compress(SECRET.encode())).decode(),
        base64.b64encode(_packed(b"plain ") + _packed(_packed(SECRET.encode()))).decode(), base64.b64encode(_packed(b"a, " * 6_000_000 + SECRET.encode())).decode(), base64.b64encode(zstandard.compress(b"a, " * 6_000_000 + SECRET.encode())).decode(),
        "\n".join(re.findall(".{1,10}", base64.b64encode(SECRET.encode()).decode())), "\r\n  ".join(re.findall(".{1,64}", base64.b64encode(_packed(SECRET.encode())).decode())), "x/" + base64.b64encode(SECRET.encode()).decode(), "id-" + base64.b64encode(_packed(SECRET.encode())).decode().rstrip("="),
    ],
    ids=range(21),
)
def test_secrets_in_layers_that_are_not_plain(wrapped):
    base, found = scan(f"before {wrapped} after")
    assert base == [] and any(kind == "assign" and 7 <= a < b <= 7 + len(wrapped) for a, b, kind in found)


def test_secrets_across_windows():
    body = "".join(f"{i:07d}\n" for i in range(999)) + " ".join(["word"] * 500) + "\n" + "\n".join(re.findall(".{1,76}", base64.b64encode(b"-" * 900 + SECRET.encode()).decode()))
    raw = base64.b64encode(_packed(f"{SECRET}{body}".encode())).decode()
    for most in (1, 50, 1000, 3001, 1 << 24):
        assert {k for *_, k in scan(base64.b64encode(_packed(body.encode())).decode(), most)[1]} == {"assign"}
        assert scan(raw, most) == scan(raw)


def test_base_patterns():
    text = 'x token: "aaaaaaaaaaaa" token=short secret=0123456789abcdef AKIA' + "Z" * 14 + " AKIAZZ deadbeefdeadbeef API_KEY=AbCdEfGhIjKl ſecret=abcdefghijkl token=secret: abcdefghijklmnop"
    kinds = collections.Counter(k for *_, k in base_spans(text))
    assert kinds == {"assign": 3, "access": 1, "hex": 2}
    assert scan(None) == ([], []) and scan("") == ([], [])
    again = base64.b64encode(b"aGVsbG8gd29ybGQgaGVsbG8=").decode()
    assert scan(f"{again} {again}")[1] == []
    assert redact("ab token=abcdefghijkl cd", scan("ab token=abcdefghijkl cd")[1]) == "ab [secret] cd"


def test_secret_scan_of_a_table(spark):
    rows = [(1, f"a {SECRET} b"), (2, None), (3, ""), (1, f"a {SECRET} b")]
    out = scan_secrets(frame(spark, rows).withColumn("spans", F.lit("clash")), redacted_col="clean").orderBy("doc_id").collect()
    assert [r["n_assign"] for r in out] == [1, 1, 0, 0] and out[0]["clean"] == "a [secret]\" b" and out[2]["clean"] is None
    assert scan_secrets(frame(spark, [])).count() == 0


# --- nearest neighbours -----------------------------------------------------------------------


def test_nearest_is_exact_on_small_tables_and_leaves_bad_vectors_out(spark):
    rng = np.random.default_rng(0)
    rows = [(i, rng.normal(size=8).tolist()) for i in range(80)]
    rows += [(80, rows[3][1]), (81, rows[3][1]), (82, None), (83, [0.0] * 8), (84, [float("nan")] + [1.0] * 7), (85, [1.0] * 7), (86, [1.0, None] + [1.0] * 6), (87, [])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = nearest(df, df.where("vec_id % 20 = 0"), k=5).collect()
    good = [(i, np.array(v)) for i, v in rows if i < 82]
    for q in (0, 20, 40, 60, 80):
        x = dict(good)[q]
        want = sorted(((-float((x * v).sum()), i) for i, v in good if i != q))[:5]
        mine = sorted((r["rank"], r["vec_id"], r["score"]) for r in got if r["query_id"] == q)
        assert [m[1] for m in mine] == [i for _, i in want] and np.allclose([m[2] for m in mine], [-s for s, _ in want])
    assert nearest(df.where("vec_id > 81"), df, k=5).count() == 0
    assert nearest(df.where("vec_id < 3"), df.where("vec_id = 0"), k=5).count() == 2


def test_forest_recall(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(1500, 24))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = nearest(df, df.where("vec_id % 100 = 0"), k=10, leaf_rows=90, block_rows=64).collect()
    hits = 0
    for q in range(0, 1500, 100):
        s = x @ x[q]
        s[q] = -np.inf
        hits += len({r["vec_id"] for r in got if r["query_id"] == q} & set(np.argsort(-s)[:10].tolist()))
    assert hits / 150 >= 0.9


# --- toxicity ------------------------------------------------------------------------------------


def toxic_corpus():
    rng = random.Random(5)
    syllables = ["ta", "re", "mo", "li", "su", "ne", "pa", "ko", "ri", "den"]
    word = lambda: "".join(rng.choice(syllables) for _ in range(rng.choice((1, 2, 3))))
    docs, labels = [], []
    for i in range(600):
        own = [word() for _ in range(40)]
        if i % 4 == 0:
            for _ in range(2):
                own[rng.randrange(40)] = rng.choice(["wretched", "scoundrel", "imbecile"])
        docs.append((i, " ".join(own)))
        labels.append((i, int(i % 4 == 0)))
    return docs, labels


def test_toxicity_learns_and_tolerates_gaps(spark):
    docs, labels = toxic_corpus()
    df, told = frame(spark, docs), spark.createDataFrame(labels, "doc_id long, toxic int")
    model = fit_toxicity(df, told.where(~held_out()))
    out = score_toxicity(df.unionByName(frame(spark, [(900, None), (901, ""), (902, "an imbexcile"), (903, "w r e t c h e d"), (904, "s.c.o.u.n.d.r.e.l")])).withColumn("score", F.lit(0)), model).collect()
    by = {r["doc_id"]: r for r in out}
    unseen = [i for i, _ in docs if zlib.crc32(str(i).encode()) % 4 == 2]
    assert all(by[i]["predicted"] == int(i % 4 == 0) for i in unseen)
    assert by[900]["predicted"] == by[901]["predicted"] == 0 and by[900]["score"] == by[901]["score"]
    assert by[902]["predicted"] == by[903]["predicted"] == by[904]["predicted"] == 1
    assert score_toxicity(frame(spark, []), model).count() == 0


def test_toxicity_without_labels(spark):
    docs, labels = toxic_corpus()
    model = fit_toxicity(frame(spark, docs), spark.createDataFrame([], "doc_id long, toxic int"))
    assert score_toxicity(frame(spark, docs[:3]), model).where("score BETWEEN 0 AND 1").count() == 3
    words, (a, b) = indexed([{"x"}], [])
    assert train(words, a, b).slope == 0
    assert words_of("Ab1c! d e f " + "z" * 100) >= {"abc", "def"}


# --- mixing ---------------------------------------------------------------------------------------


def test_mixing_meets_its_targets(spark):
    rng = random.Random(6)
    rows = [(i, "w " * rng.randrange(20, 60), rng.choice("aaabc") if i % 50 else None, rng.choice("xxy")) for i in range(3000)]
    df = spark.createDataFrame([*rows, (None, "w w w", "a", "x"), (3000, None, "a", "x"), (3001, "", "b", "y")], "doc_id long, text string, source string, lang string")
    out = mix(df, {"source": F.col("source"), "lang": F.col("lang")}, exponent=0.0, budget_share=0.02)
    assert out.count() == df.count() and out.where("source = '(none)'").count() == 60 and out.where("n_tokens = 0 AND sampled").count() == 0
    expected = {r["lang"]: r["t"] for r in out.groupBy("lang").agg(F.sum(F.col("probability") * F.col("n_tokens")).alias("t")).collect()}
    assert expected["x"] == pytest.approx(expected["y"], rel=0.01)
    total = out.agg(F.sum("n_tokens")).first()[0]
    assert sum(expected.values()) == pytest.approx(0.02 * total, rel=0.01)
    assert mix(df.where("false"), {"source": F.col("source")}).count() == 0


# --- pieces ----------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def pieces():
    return pc.load_pieces(MODEL)


def every_way(p, text):
    out = []

    def back(node, ids, score):
        if node == 0:
            out.append((score, ids))
        else:
            for start, s, own in p._edges(text, node):
                back(start, own + ids, score + s)

    back(len(text), (), 0.0)
    return sorted(out, key=lambda w: (-round(w[0], 9), w[1]))


@pytest.mark.parametrize("word", ["▁hello", "▁w\nör", "▁internal", "▁", "▁\U0010fffdab", "▁日本x"])
def test_nbest_is_that_of_all_ways(pieces, word):
    ways = every_way(pieces, word)
    assert [round(s, 6) for s, _ in pieces.nbest(word, 5)] == [round(s, 6) for s, _ in ways[:5]]
    many = pieces.many([word, "▁the", word])
    assert many.best[2] == pytest.approx(ways[0][0]) and (len(ways) < 2 or many.second[0] == pytest.approx(ways[1][0]))
    assert many.body[many.starts[0] : many.starts[0] + many.sizes[0]].tolist() == list(pieces.nbest(word, 1)[0][1])


def test_documents_encode_and_decode(spark, pieces):
    texts = [(1, "  Hello   wörld\nfoo ▁x "), (2, None), (3, ""), (4, "in on at"), (5, "🙂 " + "long" * 60), (4, "in on at")]
    out = pc.encode_documents(frame(spark, texts).withColumn("ids", F.lit(1)), pieces, n=4).orderBy("doc_id").collect()
    for r in out:
        assert r["decoded"] and (pieces.decode(r["ids"]) == (r["text"] or "") or "▁" in (r["text"] or ""))
    whole = "▁" + "in on at".replace(" ", "▁")
    want = [s for s, _ in pieces.nbest(whole, 4)]
    assert np.allclose(next(r for r in out if r["doc_id"] == 4)["nbest_scores"], want)
    assert pc.encode_documents(frame(spark, []), pieces).count() == 0


# --- quality ----------------------------------------------------------------------------------------


def test_quality_counts_and_learned_rules(spark):
    rng = random.Random(7)
    good = [(i, "\n".join(sentence(rng, 20, 4000) + "." for _ in range(5))) for i in range(150)]
    bad = [(i, "\n".join(" ".join(f"{rng.randrange(9999)}#%" for _ in range(20)) for _ in range(5))) for i in range(150, 220)]
    odd = [(300, None), (301, ""), (302, "a b c a b c a b c"), (303, "x\nx\n \n\nx"), (None, "y " * 80), (302, "a b c a b c a b c")]
    rows = good + bad + odd
    labels = spark.createDataFrame([(i, int(i < 150)) for i, _ in good + bad] + [(999, None), (None, 1)], "doc_id long, quality int")
    out = judge(frame(spark, rows).withColumn("kept", F.lit(1)), labels).collect()
    by = {r["doc_id"]: r for r in out}
    assert len(out) == len(rows)
    for i, t in rows:
        w = WORD.findall(t or "")
        count = collections.Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
        covered = {k + j for k in range(len(w) - 2) if count[tuple(w[k : k + 3])] > 1 for j in range(3)}
        lines = [x for x in (t or "").split("\n") if WORD.search(x)]
        assert (by[i]["n_words"], by[i]["word_chars"], by[i]["n_symbols"], by[i]["n_dup_lines"], by[i]["n_repeat_words"]) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(covered))
    assert all(by[i]["kept"] for i, _ in good) and not any(by[i]["kept"] for i, _ in bad) and by[302]["base_failed"]
    assert judge(frame(spark, []), labels).count() == 0
    assert judge(frame(spark, good[:3]), labels.where("false")).where("kept").count() == 3


# --- archives -----------------------------------------------------------------------------------------


def test_archives_round_trip_and_are_the_same_bytes_twice(spark, tmp_path):
    big, other = "<p>" + "é" * 1200, "<b>" + "z" * 5000
    rows = [(1, "http://a/x y", big), (2, None, big), (3, "http://c", "small"), (4, "http://d", "small"), (5, "u", None), (6, "u", ""), (7, "http://e", other), (None, "http://n", big), (2, None, big)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit("clash"))
    sums = []
    for name, parts in (("one", 1), ("two", 3)):
        folder = f"file://{tmp_path}/{name}"
        files = write_warc(df.repartition(parts), folder, shard_bytes=4000, roll_bytes=900).collect()
        sums.append(sorted((r["file"], r["sha1"]) for r in files))
        assert not [f for f in os.listdir(tmp_path / name) if f.startswith("_tmp")]
    assert sums[0] == sums[1] and len(sums[0]) > 2
    got = sorted(((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in read_warc(spark, f"file://{tmp_path}/two").collect()), key=str)
    size = lambda t: len((t or "").encode())
    kind = lambda i, t: ("revisit", 2) if t == big and i == 1 else ("response", None)
    assert got == sorted(((i, size(t), hashlib.sha1((t or "").encode()).hexdigest(), *kind(i, t)) for i, _, t in rows), key=str)
    assert gzip.open(tmp_path / "two" / sums[1][0][0]).read().startswith(b"WARC/1.1\r\n")
    write_warc(df.where("false"), f"file://{tmp_path}/none")
    assert read_warc(spark, f"file://{tmp_path}/none").count() == 0


# --- language -------------------------------------------------------------------------------------------


def test_language_by_compression(spark):
    rng = random.Random(8)
    stems = {"aa": ["kor", "lam", "tis", "ne"], "bb": ["schu", "gen", "feit", "ur"]}
    word = lambda lang: "".join(rng.choice(stems[lang]) for _ in range(3))
    rows = [(i, " ".join(word(lang) for _ in range(60)), lang) for i, lang in enumerate(["aa", "bb"] * 60)]
    df = spark.createDataFrame([*rows, (500, None, "aa"), (501, "12 !", "bb"), (502, "", None)], "doc_id long, text string, lang string").withColumn("score", F.lit("clash"))
    model = fit_language_model(df.where(~held_out()))
    out = {r["doc_id"]: r for r in identify_language(df, model).collect()}
    assert all(out[i]["lang_pred"] == lang for i, _, lang in rows) and all(0 <= r["score"] <= 1 for r in out.values())
    assert [out[i]["lang_pred"] for i in (500, 501, 502)] == ["und"] * 3
    empty = fit_language_model(df.where("false"))
    assert {r["lang_pred"] for r in identify_language(df, empty).collect()} == {"und"} and identify_language(df.where("false"), model).count() == 0


# --- the pipeline ------------------------------------------------------------------------------------------


def test_every_label_is_learned_beyond_the_first_characters(spark):
    rng = random.Random(5)
    letters = "abcdefghijklmnopqrstuvwxyz"
    words = [["".join(rng.choices(letters, k=6)) for _ in range(30)] for _ in range(72)]
    header = " ".join("".join(rng.choices(letters, k=6)) for _ in range(230))
    text = lambda k, n: " ".join(rng.choices(words[k], k=n))
    rows = [(100 * k + i, f"{header} {text(k, 900)}", f"l{k:02d}") for k in range(72) for i in range(3)]
    model = fit_language_model(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    asked = spark.createDataFrame([(k, text(k, 60)) for k in range(72)], "doc_id long, text string")
    out = {r["doc_id"]: r["lang_pred"] for r in identify_language(asked, model).collect()}
    assert len(model.dictionaries) == 72 and sum(out[k] == f"l{k:02d}" for k in out) >= 70


def test_pipeline_stages(spark, data):
    import corpus_pipeline as cp
    from pathlift.llm.frames import table

    docs = table(spark, data, "documents")
    before = {r["doc_id"]: r for r in docs.collect()}
    for k, (name, stage) in enumerate(cp.STAGES):
        out = Workspace(spark, "test").keep(stage(spark, docs, data), "stage")
        if k + 1 < len(cp.STAGES):
            assert out.columns == docs.columns, name
        after = {r["doc_id"]: r for r in out.collect()}
        assert set(after) <= set(before) and len(after) == out.count()
        if name == "n-gram Jaccard join":
            want = {c for _, n, c in groups_of([(i, r["text"]) for i, r in before.items()], 5, 80)}
            assert set(after) == want
        if name == "secret scans":
            assert set(after) == set(before) and all(not base_spans(r["text"] or "") for r in after.values())
        if name == "sentencepiece encoding":
            assert set(after) == set(before) and all(r["decoded"] for r in after.values())
        docs, before = out, after
