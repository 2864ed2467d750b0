"""Every corpus operator on nulls, empty and very long texts, ties, repeats, clashing columns and empty tables."""

import collections
import hashlib
import itertools
import pathlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_corpus import MODEL, SECRET, corpus, every_way, frame, groups_of, repeats, sentence, toxic_corpus

from pathlift.llm import mixing, substring_dedup, warc
from pathlift.llm import pieces as pc
from pathlift.llm.ann_forest import nearest, opened_share, usable
from pathlift.llm.frames import Workspace, fresh, held_out, table
from pathlift.llm.language_id import fit_language_model, identify_language, normalised
from pathlift.llm.mixing import mix, plan_mixture, rake
from pathlift.llm.ngram_join import _common, similar_groups
from pathlift.llm.quality_rules import FEATURES, features, judge, learn_rules, text_statistics
from pathlift.llm.recall_report import brute_force, recall
from pathlift.llm.secret_scan import scan, scan_secrets
from pathlift.llm.substring_dedup import remove_repeats
from pathlift.llm.toxicity import fit_toxicity, score_toxicity
from pathlift.llm.warc import read_warc, shard_bounds, write_warc

CLASHES = ("n", "w", "l", "h", "g", "s", "p", "t", "node", "root", "token", "kept", "score", "predicted", "words", "whole", "lines", "spans", "ids", "decoded", "redacted", "stratum_source", "__source", "sampled", "probability", "rank", "label")


def odd_rows():
    """(id, text): null, empty, blank, very long, repeated and tied rows."""
    rng = random.Random(3)
    long = sentence(rng, 30_000, 2000)
    plain = [(i, sentence(rng, 60, 900)) for i in range(6)]
    return [*plain, (10, None), (11, ""), (12, " \n\t "), (13, long), (14, f"{long} more"), (15, "one"), (2, plain[2][1]), (16, plain[2][1]), (None, plain[1][1]), (None, None), (17, "x" * 200_000)]


def clashing(df):
    for c in CLASHES:
        df = df.withColumn(c, F.lit(None).cast("string"))
    return df


def test_fresh_names(spark):
    df = spark.createDataFrame([(1, 2)], "A int, a_1 int")
    assert fresh(df, "a", "b", "a") == ["a_2", "b", "a_3"]


# --- nearest neighbours ---------------------------------------------------------------


def test_nearest_with_clashes_repeats_and_ties(spark):
    rng = np.random.default_rng(2)
    same = rng.normal(size=6).tolist()
    rows = [(i, same if i % 3 == 0 else rng.normal(size=6).tolist()) for i in range(400)] + [(7, same), (None, same)]
    df = clashing(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    got = nearest(df, df.where("vec_id IN (0, 1, 399)"), k=8, leaf_rows=20, open_scale=10.0, open_power=1.0).collect()
    points = collections.defaultdict(list)
    for i, v in rows:
        if i is not None:
            points[i].append(np.array(v))
    for q in (0, 1, 399):
        best = sorted((-max(float((v * points[q][0]).sum()) for v in vs), i) for i, vs in points.items() if i != q)[:8]
        assert [r["vec_id"] for r in sorted((r for r in got if r["query_id"] == q), key=lambda r: r["rank"])] == [i for _, i in best]
    assert nearest(df.where("false"), df).count() == 0 and nearest(df, df.where("false")).count() == 0


def test_one_rule_opens_leaves_at_every_size(spark, data):
    """The share that is opened falls with the rows, and recall at 20 stays over 0.9 on the given vectors."""
    shares = [opened_share(n, 1.85, 0.886) for n in (30, 500, 2000, 50_000, 10**6, 10**9)]
    assert shares[0] == 1 and shares == sorted(shares, reverse=True) and shares[-1] < 0.2
    df = table(spark, data, "embeddings").select("vec_id", "embedding")
    queries = df.where("vec_id % 20 = 0")
    mean, _ = recall(nearest(df, queries), brute_force(usable(df, "vec_id", "embedding"), usable(queries, "vec_id", "embedding")))
    assert 0.9 <= mean < 1


def test_copies_do_not_use_up_the_budget(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(3000, 16))
    x[::3] = x[0]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    queries = df.where("vec_id % 100 = 1 AND vec_id % 3 > 0")
    mean, least = recall(nearest(df, queries, k=10), brute_force(usable(df, "vec_id", "embedding"), usable(queries, "vec_id", "embedding"), 10))
    assert mean >= 0.9 and least >= 0.5


def test_forest_keeps_every_vector_once(spark):
    """What is written follows the rows, not the trees nor the leaves that queries open; crowds of copies hide no other id."""
    rng = np.random.default_rng(6)
    x = rng.normal(size=(3000, 64)).astype(np.float32)
    x[:60] = x[0]
    ids = [5] * 30 + list(range(30, 3000))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in zip(ids, x, strict=True)], "vec_id long, embedding array<float>")
    root = pathlib.Path(spark.conf.get("spark.checkpoint.dir").removeprefix("file://"))
    before = set(root.glob("forest-*"))
    got = nearest(df, df.where("vec_id % 20 = 0"), k=20, open_scale=10.0, open_power=1.0, block_rows=500, block_queries=40).collect()
    written = sum(f.stat().st_size for folder in set(root.glob("forest-*")) - before for f in folder.rglob("*.parquet"))
    assert 0 < written < 1.5 * x.nbytes
    exact = x.astype(np.float64)
    for q in (40, 60, 2980):
        best: dict = {}
        for i, score in zip(ids, (exact * exact[q]).sum(axis=1).tolist(), strict=True):
            best[i] = max(score, best.get(i, -np.inf))
        best.pop(q)
        want = sorted(best, key=lambda i: (-best[i], i))[:20]
        assert [r["vec_id"] for r in sorted((r for r in got if r["query_id"] == q), key=lambda r: r["rank"])] == want


# --- toxicity -------------------------------------------------------------------------------


def test_toxicity_of_odd_rows(spark):
    docs, told = toxic_corpus()
    docs = [(1000 + i, t) for i, t in docs]
    labels = spark.createDataFrame([*[(1000 + i, y) for i, y in told], (1001, 0), (None, 1), (1003, None), (999, 1)], "doc_id long, toxic int")
    model = fit_toxicity(clashing(frame(spark, docs + odd_rows()[6:])), labels)
    out = score_toxicity(clashing(frame(spark, [*odd_rows(), (50, f"{docs[1][1]} {odd_rows()[9][1]} scoundrel"), (51, docs[1][1])])), model).collect()
    assert len(out) == len(odd_rows()) + 2 and all(0 <= r["score"] <= 1 for r in out)
    by = {r["doc_id"]: r["predicted"] for r in out}
    assert by[50] == 1 and by[51] == by[10] == by[11] == by[12] == by[None] == 0 and len({r["score"] for r in out if r["doc_id"] == 2}) == 1


def test_toxicity_separates_held_out_documents(spark):
    """Area under the curve on the documents whose labels taught nothing."""
    folder = "/root/testdata/sf0.1"
    docs, labels = table(spark, folder, "documents").select("doc_id", "text"), table(spark, folder, "labels").select("doc_id", "toxic").where("toxic IS NOT NULL")
    model = fit_toxicity(docs, labels.where(~held_out()))
    asked = labels.where(held_out()).join(docs, "doc_id")
    rows = [(r["score"], r["toxic"]) for r in score_toxicity(asked, model).collect()]
    bad, fine = [s for s, y in rows if y], [s for s, y in rows if not y]
    area = np.mean([(b > f) + 0.5 * (b == f) for b, f in itertools.product(bad, fine)])
    assert len(bad) > 20 and area >= 0.9


# --- n-gram join --------------------------------------------------------------------------------


def test_join_of_odd_rows(spark):
    rows = odd_rows()
    got = sorted((tuple(r) for r in similar_groups(clashing(frame(spark, rows)), words=5, percent=80).collect()), key=str)
    assert got == groups_of(rows, 5, 80)


@pytest.mark.parametrize("seed", [1])
def test_join_with_hot_passages_and_mixed_sizes(spark, seed):
    """Passages that many documents hold, sizes from 1 to 400 shingles, near copies around the threshold."""
    rng = random.Random(seed)
    hot = [sentence(rng, 20, 10**6) for _ in range(2)]
    rows = []
    for _ in range(60):
        size = rng.choice((1, 3, 8, 25, 60, 150, 400))
        own = sentence(rng, size, 10**6).split()
        for _ in range(rng.choice((0, 1, 2))):
            own[rng.randrange(len(own)) : 0] = rng.choice(hot).split()
        rows.append((len(rows), " ".join(own)))
        for _ in range(rng.choice((0, 1, 2))):
            copy = list(own)
            for _ in range(rng.choice((1, 1, 2, max(1, len(own) // 40)))):
                k = rng.randrange(len(copy))
                copy[k : k + rng.choice((0, 1))] = [f"z{rng.randrange(10**6)}"] * rng.choice((0, 1))
            rows.append((len(rows), " ".join(copy)))
    rows += [(1000 + i, f"{hot[0]} a{i} b{i} c{i}") for i in range(30)] + [(2000, f"{hot[0]} p q r"), (2001, f"X{hot[0]} p q r")]
    for rounds, heat in ((0, 1), (4, 10_000)):
        got = sorted((tuple(r) for r in similar_groups(frame(spark, rows), words=4, percent=85, rounds=rounds, pairs_per_node=0, hot_pairs=heat).collect()), key=str)
        assert got == groups_of(rows, 4, 85)


def test_common_counts_in_steps():
    rng = np.random.default_rng(0)
    lists = [[np.unique(rng.integers(0, 60, rng.integers(1, 20))) for _ in range(n)] for n in (7, 5)]
    flat = [(np.concatenate(s), np.array([len(x) for x in s])) for s in lists]
    want = [[len(np.intersect1d(a, b)) for b in lists[1]] for a in lists[0]]
    assert _common(*flat[0], *flat[1], step=7).tolist() == want


# --- substring dedup ----------------------------------------------------------------------------------


def test_dedup_of_odd_rows(spark):
    rows = odd_rows()
    got = sorted((tuple(r) for r in remove_repeats(clashing(frame(spark, rows))).collect()), key=str)
    assert got == repeats(rows, 13)


def test_dedup_with_hot_anchors_dealt_out(spark, monkeypatch):
    monkeypatch.setattr(substring_dedup, "HOT_ROWS", 3)
    rows = corpus(5) + [(300 + i, sentence(random.Random(7), 40)) for i in range(20)]
    got = sorted((tuple(r) for r in remove_repeats(frame(spark, rows)).collect()), key=str)
    assert got == repeats(rows, 13)


# --- secrets ----------------------------------------------------------------------------------------------


def matched_by_hand(text):
    """(start, end, kind) of the base patterns, read character by character."""
    out, value = [], set("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_.=-")
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text)
    at = 0
    while at < len(text):
        end = None
        for word in ("password", "passwd", "secret", "token", "api_key", "apikey"):
            if low.startswith(word, at):
                k = at + len(word)
                k += text[k : k + 1] in ("'", '"') and text[k : k + 1] != ""
                while text[k : k + 1] == " ":
                    k += 1
                if text[k : k + 1] in ("=", ":") and text[k : k + 1]:
                    k += 1
                    while text[k : k + 1] == " ":
                        k += 1
                    k += text[k : k + 1] in ("'", '"') and text[k : k + 1] != ""
                    stop = k
                    while stop < len(text) and text[stop] in value:
                        stop += 1
                    if stop > k:
                        end = stop
                        if stop - k >= 12:
                            out.append((at, stop, "assign"))
                        break
        at = end if end else at + 1
    for kind, head, letters, least in (("access", "AKIA", set("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789"), 18), ("hex", "", set("0123456789abcdef"), 16)):
        at = 0
        while at < len(text):
            stop = at + len(head) if text.startswith(head, at) else at
            if stop > at or not head:
                body = stop
                while stop < len(text) and text[stop] in letters:
                    stop += 1
                if stop > body:
                    if stop - at >= least:
                        out.append((at, stop, kind))
                    at = stop
                    continue
            at += 1
    return sorted(out, key=lambda s: (s[0], ("assign", "access", "hex").index(s[2])))


def test_base_secrets_by_hand():
    rng = random.Random(12)
    parts = ["password", "Passwd", "TOKEN", "api_key", "apikey", "secret", "=", ":", " ", '"', "'", "AKIA", "ABCD1234EFGH5678", "deadbeef", "0123456789abcdef", "xyz+/_.", "é", "\n", "ſ", "K", "-", "==", "AKIAAKIA"]
    for _ in range(2000):
        text = "".join(rng.choice(parts) for _ in range(rng.randrange(1, 14)))
        assert scan(text)[0] == matched_by_hand(text), text


def test_secrets_of_odd_rows(spark):
    rows = [*odd_rows(), (60, f"{odd_rows()[9][1]} {SECRET} {SECRET}")]
    out = scan_secrets(clashing(frame(spark, rows)), redacted_col="text").collect()
    assert len(out) == len(rows) and [r["n_assign"] for r in out if r["doc_id"] == 60] == [2]
    assert all((r["text"] is None) == (r["doc_id"] in (10, None) and r["text"] is None) for r in out)
    assert "redacted" in out[0].asDict()


# --- mixing -------------------------------------------------------------------------------------------------


def test_mixing_keeps_columns_and_converges(spark, monkeypatch):
    df = clashing(frame(spark, odd_rows())).withColumn("source", F.lit("a")).withColumn("lang", F.when(F.col("doc_id") > 3, "x")).withColumn("__kept", F.lit(7))
    out = mix(df, {"source": F.col("source"), "lang": F.col("lang")}, budget_share=1.0)
    assert set(df.columns) | {"n_tokens"} == set(out.columns)
    rows = out.collect()
    assert len(rows) == len(odd_rows()) and all(r["__kept"] == 7 for r in rows) and all(r["sampled"] and r["probability"] == 1 for r in rows)
    cells = spark.createDataFrame([("a", "x", 100), ("a", "y", 50), ("b", "x", 10), ("b", "y", 500), ("c", "y", 3), ("d", "x", 0)], "source string, lang string, tokens long")
    shares = lambda **v: spark.createDataFrame(list(v.items()), "value string, share double")
    targets = {"source": shares(a=0.5, b=0.3, c=0.2, absent=0.7), "lang": shares(x=0.25, y=0.75)}
    raked = rake(cells, ["source", "lang"], targets, Workspace(spark, "t"), tolerance=1e-7)
    assert raked.gap <= 1e-7
    weight = raked.cells.toPandas()
    assert np.allclose(weight.groupby("source")["weight"].sum()[["a", "b", "c"]], [0.5, 0.3, 0.2], atol=1e-6) and np.allclose(weight.groupby("lang")["weight"].sum(), [0.25, 0.75], atol=1e-6)
    # brute force: the same factors by plain loops
    w = {(s, g): float(t) for s, g, t in cells.where("tokens > 0").collect()}
    for _ in range(500):
        for axis, goal in ((0, {"a": 0.5, "b": 0.3, "c": 0.2}), (1, {"x": 0.25, "y": 0.75})):
            now = collections.Counter()
            for key, v in w.items():
                now[key[axis]] += v
            w = {key: v * goal[key[axis]] / now[key[axis]] for key, v in w.items()}
    assert all(abs(r.weight - w[r.source, r.lang]) < 1e-5 for r in weight.itertuples())
    monkeypatch.setattr(mixing, "LITERAL_VALUES", 2)  # one stratum as a literal map, the other as a table
    other = rake(cells, ["source", "lang"], targets, Workspace(spark, "t"), tolerance=1e-3).cells.toPandas()
    assert all(abs(r.weight - w[r.source, r.lang]) < 1e-2 for r in other.itertuples())
    impossible = rake(cells, ["source", "lang"], {"source": shares(c=1.0), "lang": shares(x=1.0)}, Workspace(spark, "t"), most_passes=5)
    assert impossible.passes == 5 and impossible.gap > 0.1


def test_mixture_report(spark):
    counted = spark.createDataFrame([("a", 60), ("a", 40), ("b", 10)], "source string, n_tokens long")
    plan = plan_mixture(counted, ["source"], Workspace(spark, "t"), exponent=0.0, budget_share=0.1)
    report = {r["value"]: r for r in plan.report().collect()}
    assert plan.gap <= 1e-13 and report["a"]["share"] == pytest.approx(0.5) and report["b"]["drawn_share"] == pytest.approx(0.5) and report["a"]["tokens"] == 100


# --- pieces ------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def pieces():
    return pc.load_pieces(MODEL)


@pytest.mark.parametrize("text", ["in on at", "a b", "the the", "aaaa -- aaaa", "no é x", "internal of"])
def test_nbest_ids_of_texts_are_those_of_all_ways(spark, pieces, text):
    """All segmentations of a text of several words, against the n best that come back."""
    marked = "▁" + text.replace(" ", "▁")
    words = ["▁" + w for w in text.split(" ")]
    alone = [every_way(pieces, w) for w in words]
    ways = sorted(((round(sum(s for s, _ in way), 9), tuple(itertools.chain.from_iterable(i for _, i in way))) for way in itertools.product(*[a[:9] for a in alone])), key=lambda w: -w[0])
    row = pc.encode_documents(frame(spark, [(1, text)]), pieces, n=6).first()
    got = list(zip((round(s, 9) for s in row["nbest_scores"]), map(tuple, row["nbest_ids"]), strict=True))
    assert np.allclose([s for s, _ in got], [s for s, _ in ways[: len(got)]]) and len(got) == min(6, len(ways))
    assert len({i for _, i in got}) == len(got) and all(any(abs(s - t) < 1e-6 and i == j for t, j in ways) for s, i in got)
    assert tuple(row["ids"]) == got[0][1] and all(pieces.decode(i) == text for _, i in got)
    assert np.allclose([s for s, _ in got], [s for s, _ in pieces.nbest(marked, 6)])
    assert row["nbest_digests"] == [hashlib.sha1(np.array(i, dtype=np.int32).tobytes()).hexdigest() for _, i in got]


def test_encoding_of_odd_rows_and_back(spark, pieces):
    rows = [*odd_rows(), (70, "tabs\tand\nlines ▁ mark \U0001f642")]
    df = clashing(frame(spark, rows)).drop("ids")
    out = pc.encode_documents(df, pieces, n=3)
    back = pc.decode_documents(out.withColumnRenamed("text", "before").select("doc_id", "before", "ids", "nbest_ids", "decoded"), pieces).collect()
    assert len(back) == len(rows) and all(r["decoded"] and r["text"] == (r["before"] or "") for r in back)
    assert pc.encode_documents(df.where("false"), pieces).count() == 0 and pc.decode_documents(out.where("false"), pieces).count() == 0
    assert all(not r["nbest_ids"] and not r["ids"] for r in back if not r["before"])


# --- quality ---------------------------------------------------------------------------------------------------------


def test_judging_odd_rows(spark):
    labels = spark.createDataFrame([(i, i % 2) for i in range(20)] + [(None, 0), (1, None), (1, 1)], "doc_id long, quality int").withColumn("id", F.lit(1)).withColumn("bad", F.lit(1))
    out = judge(clashing(frame(spark, odd_rows())), labels.select("doc_id", "quality")).collect()
    assert len(out) == len(odd_rows())
    by = {r["doc_id"]: r for r in out}
    assert by[13]["n_words"] == 30_000 and by[17]["n_words"] == 1 and all(by[i]["base_failed"] and not by[i]["kept"] for i in (10, 11, 12, 15, 17))
    stats = text_statistics(clashing(frame(spark, odd_rows())))
    assert set(clashing(frame(spark, [])).columns) <= set(stats.columns)


def test_first_rule_is_the_best_of_all_literals(spark):
    """The literal that grows the first rule, against trying every feature and cut."""
    rng = random.Random(4)
    rows = [(i, " ".join(("#%" if rng.random() < (0.5 if i % 3 == 0 else 0.02) else "") + f"w{rng.randrange(500)}" for _ in range(80))) for i in range(300)]
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(300)], "doc_id long, quality int")
    stats = text_statistics(frame(spark, rows)).drop("text")
    rules = learn_rules(stats, labels, most_rules=1, most_literals=1, bins=16)
    told = stats.select("doc_id", (F.pmod(F.xxhash64("doc_id"), F.lit(3)) == 2).alias("prune"), *[c.alias(n) for n, c in features().items()]).toPandas()
    told["bad"] = told["doc_id"] % 3 == 0
    cuts = {f: sorted(set(stats.select(features()[f].alias("x")).agg(F.percentile_approx("x", [k / 16 for k in range(1, 16)], 2000)).first()[0])) for f in FEATURES}
    part = told[~told["prune"]]
    p0, n0 = part["bad"].sum(), (~part["bad"]).sum()
    score = {}
    for f in FEATURES:
        for cut, above in itertools.product(cuts[f], (False, True)):
            hit = part[part[f] > cut] if above else part[part[f] <= cut]
            p, n = hit["bad"].sum(), (~hit["bad"]).sum()
            score[f, above, cut] = p * (np.log2((p + 1e-9) / (p + n + 1e-9)) - np.log2((p0 + 1e-9) / (p0 + n0 + 1e-9))) if p >= 5 else 0
    (literal,), kept = rules.rules[0]
    assert not kept and score[literal.feature, literal.above, literal.threshold] == pytest.approx(max(score.values()))


# --- archives --------------------------------------------------------------------------------------------------------------


def test_one_far_id_does_not_fill_a_shard(spark, tmp_path):
    rows = [(i, f"http://h/{i}", "x" * 2000) for i in range(500)] + [(2**60, "http://far", "y" * 2000), (None, None, None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    out = write_warc(df, f"file://{tmp_path}/far", shard_bytes=26_000, roll_bytes=1 << 20)
    records = [r["records"] for r in out.collect()]
    assert sum(records) == 502 and len(records) > 25 and max(records) < 60
    with pytest.raises(FileExistsError):
        write_warc(df, f"file://{tmp_path}/far")


def test_one_id_of_a_third_of_all_rows_is_spread(spark, tmp_path):
    rows = [(5 if i % 3 == 0 else i, "u", f"{i} " * 500) for i in range(600)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    out = write_warc(clashing(df), f"file://{tmp_path}/hot", shard_bytes=40_000, roll_bytes=1 << 20).collect()
    assert max(r["records"] for r in out) < 100 and sum(r["records"] for r in out) == 600
    assert read_warc(spark, f"file://{tmp_path}/hot").where("page_id = 5").count() == 201


def test_a_repeated_attempt_leaves_the_same_file(tmp_path):
    from pyarrow import fs as pafs

    class Refusing:
        """A store whose move does not overwrite."""

        def __init__(self):
            self.own = pafs.LocalFileSystem()

        def __getattr__(self, name):
            return getattr(self.own, name)

        def move(self, a, b):
            if self.own.get_file_info(b).type != pafs.FileType.NotFound:
                raise OSError("exists")
            self.own.move(a, b)

    for _ in range(2):
        roller = warc._Roller(Refusing(), str(tmp_path), 3, 50)
        for k in range(4):
            roller.add(b"record %d " % k * 20)
        roller.close()
        names = [d[0] for d in roller.done]
    assert sorted(p.name for p in tmp_path.iterdir()) == sorted(names) and len(names) > 1


def test_shards_follow_bytes(spark):
    facts = spark.createDataFrame([(i, "u", hashlib.sha1(b"%d" % i).hexdigest(), 10_000 if i < 100 else 100) for i in range(1100)], "page_id long, url string, digest string, n long")
    bounds = shard_bounds(facts, 60_000)
    ids = [int.from_bytes(b[1:9], "big") - 2**63 for b in bounds]
    sizes = [sum(10_600 if k < 100 else 700 for k in range(a, b)) for a, b in itertools.pairwise([0, *ids, 1100])]
    assert len(sizes) > 20 and max(sizes) < 3 * 60_000
    assert len(shard_bounds(facts.where("false"), 1000)) == 0


# --- language ----------------------------------------------------------------------------------------------------------------------


def test_letters_are_of_category_l(spark):
    assert normalised("½ ² 12 _ ٣ Ⅷ ①") == b"" and normalised("Ab½c é") == " ab c é ".encode() and normalised("क्‍ष").strip()
    docs = [(i, "ein zwei drei vier " * 9 if i % 2 else "one two three four " * 9, "de" if i % 2 else "en") for i in range(40)]
    model = fit_language_model(spark.createDataFrame(docs, "doc_id long, text string, lang string"))
    out = {r["doc_id"]: r for r in identify_language(clashing(frame(spark, [*odd_rows(), (80, "½ ² 12"), (81, "vier drei " * 50_000)])), model).collect()}
    assert out[80]["lang_pred"] == out[10]["lang_pred"] == out[11]["lang_pred"] == out[12]["lang_pred"] == "und" and out[81]["lang_pred"] == "de"


def test_language_of_held_out_documents(spark):
    """Accuracy on documents that taught nothing, and every size against plain compression."""
    docs = table(spark, "/root/testdata/sf0.1", "documents").select("doc_id", "text", "lang")
    model = fit_language_model(docs.where(~held_out()))
    asked = docs.where(held_out() & F.col("lang").isNotNull() & (F.length("text") > 200))
    rows = identify_language(asked, model).collect()
    assert len(rows) > 1000 and np.mean([r["lang_pred"] == r["lang"] for r in rows]) >= 0.95
    compressors = model.compressors()
    for r in rows[:60]:
        body = normalised(r["text"])
        sizes = sorted((sum(len(z.compress(body[k : k + model.block_bytes])) for k in range(0, len(body), model.block_bytes)), lang) for lang, z in compressors)
        assert r["lang_pred"] == sizes[0][1]


# --- the pipeline ------------------------------------------------------------------------------------------------------------------------


def test_pipeline_stages_on_odd_rows(spark, data):
    import corpus_pipeline as cp

    rows = [(i, t, None if k % 3 else "en", None if k % 2 else "s", len(t) if t else None) for k, (i, t) in enumerate(odd_rows())]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for k, (name, stage) in enumerate(cp.STAGES):
        assert stage(spark, docs.where("false"), data).count() == 0, name
        out = stage(spark, clashing(docs), data)
        if k + 1 < len(cp.STAGES):
            assert out.columns == docs.columns, name
        got = out.collect()
        ids = collections.Counter(r["doc_id"] for r in got)
        if name == "n-gram Jaccard join":
            want = {c for i, _, c in groups_of(odd_rows(), 5, 80) if i is not None}
            assert set(ids) == {*want, None} and all(n == 1 for i, n in ids.items() if i is not None) and ids[None] == 2
        elif name in ("toxicity", "secret scans", "sentencepiece encoding"):
            assert ids == collections.Counter(i for i, _ in odd_rows())
        else:
            assert {10, 11, 12} <= set(ids)


def test_checksum_of_held_out_rows(spark):
    rows = spark.createDataFrame([(i,) for i in [*range(200), -5, None]], "doc_id long")
    got = {r["doc_id"]: r["h"] for r in rows.select("doc_id", held_out().alias("h")).collect()}
    assert all(h == (i is not None and zlib.crc32(str(i).encode()) % 4 == 2) for i, h in got.items())
    assert re.fullmatch(r"\w+", "x")
