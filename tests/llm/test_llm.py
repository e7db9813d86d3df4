"""Each document operator on small cases: nulls, empty and long texts, ties and repeated rows, empty tables, clashing columns."""

from __future__ import annotations

import hashlib
import math
import re
import time
import zlib
from collections import Counter

import numpy as np
import pytest
from conftest import same
from pyspark.sql import functions as F

from kinetic.llm import arrow_files, fingerprint, html_text, mixing, ngram_join, packing, quality, queries, toxicity
from kinetic.llm.common import fresh_path
from kinetic.llm.exact_dedup import exact_dedup
from kinetic.llm.tokens import Encoder, crc32, default_tokenizer, encoder
from kinetic.llm.url_filter import Rule, ShiftAnd, judge_urls

DOCS = "doc_id long, text string, lang string, source string, n_chars long, fingerprint string, kept boolean, score double, rule string, sequence_id long"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), "x", True, 0.5, "r", 9) for i, t, s in rows], DOCS)


ODD = [(5, "the cat sat on the mat today", "a"), (3, "the cat  sat on the mat\ttoday", "a"), (2, None, "b"), (1, "", "b"), (9, " \n", None), (7, "x" * 50_000, "a"), (7, "x" * 50_000, "a"), (None, "no id here", "a")]


@pytest.fixture(scope="module")
def odd(spark):
    return docs(spark, ODD)


@pytest.fixture(scope="module")
def none(spark):
    return docs(spark, [])


# exact dedup


def test_exact_dedup(odd, none):
    got = {(r["doc_id"], r["text_sha256"]): r for r in exact_dedup(odd).collect()}
    cat = hashlib.sha256(b"thecatsatonthemattoday").hexdigest()
    assert got[(5, cat)]["keep_id"] == got[(3, cat)]["keep_id"] == 3  # more characters in the original
    empty = hashlib.sha256(b"").hexdigest()
    assert {got[(i, empty)]["keep_id"] for i in (1, 2, 9)} == {9} and got[(1, empty)]["group_size"] == 3
    rows = exact_dedup(odd).collect()
    assert len(rows) == len(ODD) and sum(r["doc_id"] == 7 and r["kept"] for r in rows) == 2
    assert [r["kept"] for r in rows if r["doc_id"] is None] == [True]
    assert exact_dedup(none).count() == 0


def test_exact_dedup_equals_sql(spark, sf, duck):
    same(queries.op3_exact_dedup(spark, sf), duck, queries.oracle_sql()["op3_exact_dedup"])


def test_hot_text_is_dealt_over_salts(spark):
    hot = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit("same text").alias("text"))
    assert {(r["keep_id"], r["group_size"]) for r in exact_dedup(hot).collect()} == {(0, 4000)}


# fingerprints


def test_fingerprints(odd, none):
    rows = fingerprint.neighbour_fingerprints(odd, rows_per_range=2).collect()
    assert len(rows) == len(ODD)
    order = sorted(ODD, key=lambda r: (-(r[0] if r[0] is not None else -(2**63)), r[1] or ""))
    texts = [t or "" for _, t, _ in order]
    want = Counter((d, hashlib.sha256(fingerprint.edited(t, n).encode()).hexdigest()) for (d, _, _), t, n in zip(order, texts, texts[1:] + texts[:1], strict=True))
    assert Counter((r["doc_id"], r["edited_sha256"]) for r in rows) == want
    assert all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in rows)
    assert fingerprint.neighbour_fingerprints(none).count() == 0
    assert fingerprint.with_fingerprints(odd).where("fingerprint = 'x'").count() == 0


def test_fingerprints_of_equal_and_edited_texts():
    rng = np.random.default_rng(1)
    a = " ".join(f"w{i}" for i in rng.integers(0, 500, 400))
    b = " ".join(f"w{i}" for i in rng.integers(0, 500, 400))
    x, y, z = fingerprint.digests([a.encode(), fingerprint.edited(a, b).encode(), b"\x01\x02\x03" * 300])
    assert fingerprint.likeness([x], [x])[0] == 1 and fingerprint.likeness([x], [y])[0] > fingerprint.likeness([x], [z])[0]
    assert fingerprint.differences([x], [z])[0] <= fingerprint.WORST
    assert fingerprint.digests([a.encode()]) == [x]


def test_bucket_counts_by_hand():
    got = fingerprint.bucket_counts([b"abcd", b"", b"ab", b"abcd"])
    assert got.sum(1).tolist() == [4, 0, 0, 4] and (got[0] == got[3]).all()


# tokens, files, packing

HARD = ["", " ", "a  b", " a b ", "\n a", "a \nb", "<|endoftext|> x", "a <|endoftext|> b", "a b<|endoftext|>c d", "<|endoftext", "it's 's", "　c d", "\x1c a", "a\n\n b", "ñandú çéà. größe,", "²³ a½ x_y %%% a,b", "日本語 テスト", "🙂 ok"]


def test_ids_equal_the_library():
    from tokenizers import Tokenizer

    e, plain = Encoder(default_tokenizer(), most=3), Tokenizer.from_file(default_tokenizer())
    want = [x.ids for x in plain.encode_batch(HARD, add_special_tokens=False)]
    for _ in range(2):
        assert [x[:-1].tolist() for x in e.documents(HARD)] == want
    assert e.documents([None])[0].tolist() == [2]


def test_new_pieces_go_to_the_library_together():
    from tokenizers import Tokenizer

    plain, asked = Tokenizer.from_file(default_tokenizer()), []

    class Counted:
        def __init__(self, model):
            self.model = model

        def encode_batch_fast(self, texts, **how):
            asked.extend(texts)
            return self.model.encode_batch_fast(texts, **how)

    e = Encoder(default_tokenizer())
    e.documents(["one two.\nThree", "two.\nThree"])
    assert not any("\n" in p[1:] for p in e.kept)  # what begins a line is kept once, whatever is before it
    e.bare = Counted(e.bare)
    texts = [" ".join(f"w\u00f6rd{chr(97 + i % 26) * (i % 7)}x{i}{j},\nNext{j}." for i in range(50)) for j in range(20)]
    assert [x[:-1].tolist() for x in e.documents(texts)] == [x.ids for x in plain.encode_batch(texts, add_special_tokens=False)]
    assert len(asked) <= 10  # for 1,000 words and 20 that begin a line


def test_line_ends_and_merges_that_cross_the_word_pattern(tmp_path):
    import json

    from tokenizers import Tokenizer

    signs = ["a", "B", "\n", "\n\n", " ", ".", "'s", "\u00e9", "\u00f7", "\u2014", "1"]
    texts = [x + y + z + w for x in signs for y in signs for z in signs for w in signs]
    plain = Tokenizer.from_file(default_tokenizer())
    assert [x[:-1].tolist() for x in Encoder(default_tokenizer()).documents(texts)] == [x.ids for x in plain.encode_batch(texts, add_special_tokens=False)]
    # a merge of a letter with a full stop: only the word pattern keeps them apart
    spec = json.loads(plain.to_str())
    spec["model"]["merges"].insert(0, ["a", "."])
    spec["model"]["vocab"]["a."] = 50257
    other = tmp_path / "other.json"
    other.write_text(json.dumps(spec))
    assert [x[:-1].tolist() for x in Encoder(str(other)).documents(texts)] == [x.ids for x in Tokenizer.from_file(str(other)).encode_batch(texts, add_special_tokens=False)]
    assert not Encoder(str(other)).cuts


def brute(rows):
    return {i: x for (i, _, _), x in zip(rows, encoder(default_tokenizer()).documents([t for _, t, _ in rows]), strict=True)}


def test_token_files(spark, odd, none):
    rows = arrow_files.token_files_round_trip(odd).collect()
    ids = brute(ODD)
    assert len(rows) == len(ODD) and all(r["ids_crc32"] == crc32(ids[r["doc_id"]]) and r["n_tokens"] == len(ids[r["doc_id"]]) for r in rows)
    starts = sorted((r["start"], r["n_tokens"]) for r in rows)
    assert starts[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(starts, starts[1:], strict=False))
    by = [r["doc_id"] for r in sorted(rows, key=lambda r: r["start"])]
    assert by[0] is None and by[1:] == sorted(by[1:])
    assert arrow_files.token_files_round_trip(none).count() == 0


def test_repeated_ids_share_no_shard(spark):
    rows = [(None if i % 3 else i, f"text number {i}", "a") for i in range(90)]
    df = docs(spark, rows).repartition(4)
    shards = arrow_files.write_token_files(df, fresh_path(spark, "test"), docs_per_shard=10)
    assert max(r["n_docs"] for r in shards.collect()) < 30
    got = sorted(arrow_files.read_token_files(shards).collect(), key=lambda r: r["start"])
    ids = Counter((i, crc32(x)) for (i, _, _), x in zip(rows, encoder(default_tokenizer()).documents([t for _, t, _ in rows]), strict=True))
    assert Counter((r["doc_id"], r["ids_crc32"]) for r in got) == ids
    assert [r["doc_id"] for r in got] == sorted((r["doc_id"] for r in got), key=lambda i: (i is not None, i))
    assert all(a["start"] + a["n_tokens"] == b["start"] for a, b in zip(got, got[1:], strict=False))


def test_sequences_of_a_file(spark, odd):
    shard = arrow_files.write_token_files(odd, fresh_path(spark, "test"), length=8).first()
    with arrow_files.SequenceFile(shard["ids"]) as f:
        n, flat = shard["n_tokens"], []
        for i in range(math.ceil(n / 8)):
            ids, mask = f.sequence(i)
            assert len(ids) == len(mask) == 8
            flat += ids[mask].tolist()
        assert len(flat) == n and f.tokens(0, n).tolist() == flat


def test_packing(odd, none):
    rows = packing.pack_documents(odd, capacity=64).collect()
    ids = brute(ODD)
    check_packing(rows, 64)
    assert sum(r["length"] for r in rows) == sum(len(ids[i]) for i, _, _ in ODD)
    assert all(crc32(ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]) == r["ids_crc32"] for r in rows)
    assert packing.pack_documents(none).count() == 0


def check_packing(rows, capacity):
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for places in by.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def test_groups_exchange_what_does_not_fill(spark):
    rng = np.random.default_rng(5)
    sizes = [int(s) for s in rng.integers(1, 100, 3000)]
    pieces = spark.createDataFrame([(i, 0, 0, s, 0) for i, s in enumerate(sizes)], "doc_id long, piece int, start long, length long, ids_crc32 long")
    rows = packing.pack(pieces, capacity=100, group_pieces=300).collect()
    used = check_packing(rows, 100)
    assert sorted(r["doc_id"] for r in rows) == list(range(3000))
    low = packing.lower_bound(np.array(sizes), 100)
    assert low <= used <= 1.02 * low  # groups of 300 pieces lose about a sequence each to best fit on its own
    proof = packing.certificate(spark.createDataFrame(rows), 100).first()
    assert (proof["sequences"], proof["bound"], proof["gap"]) == (used, low, used - low)
    assert all(1 <= r["group_bound"] <= r["group_sequences"] for r in rows)


def test_equal_pieces_are_dealt_apart(spark):
    pieces = spark.range(4000).select(F.lit(None).cast("long").alias("doc_id"), F.lit(0).alias("piece"), F.lit(0).cast("long").alias("start"), F.lit(40).cast("long").alias("length"), F.lit(0).cast("long").alias("ids_crc32"))
    rows = packing.pack(pieces, capacity=100, group_pieces=500).collect()
    assert len(rows) == 4000 and check_packing(rows, 100) == 2000 and max(r["group_sequences"] for r in rows) < 500


def test_packing_a_gap_anew_is_never_worse():
    rng = np.random.default_rng(1)
    for _ in range(60):
        sizes = rng.integers(20, 60, 40)
        place, offset, used, bound = packing.certified_fit(sizes, 100)
        plain = len(packing.best_fit(sizes, 100)[2])
        assert bound <= len(used) <= plain and (np.bincount(place, sizes) == used).all() and used.max() <= 100
        for b in range(len(used)):
            inside = np.flatnonzero(place == b)
            inside = inside[np.argsort(offset[inside])]
            assert (offset[inside] == np.cumsum(sizes[inside]) - sizes[inside]).all()


def test_lower_bounds():
    assert packing.lower_bound(np.array([60] * 5), 100) == 5  # no two fit
    assert packing.lower_bound(np.array([34] * 6), 100) == 3
    assert packing.lower_bound(np.array([], int), 100) == 0
    rng = np.random.default_rng(2)
    for _ in range(50):
        s = rng.integers(1, 21, 9)
        assert math.ceil(s.sum() / 20) <= packing.lower_bound(s, 20) <= optimum(sorted(map(int, s), reverse=True), 20)


def optimum(sizes, capacity):
    best = [len(sizes)]

    def go(i, bins):
        if len(bins) >= best[0]:
            return
        if i == len(sizes):
            best[0] = len(bins)
            return
        for k in range(len(bins)):
            if bins[k] + sizes[i] <= capacity and bins[k] not in bins[:k]:
                go(i + 1, [*bins[:k], bins[k] + sizes[i], *bins[k + 1 :]])
        go(i + 1, [*bins, sizes[i]])

    go(0, [])
    return best[0]


# n-gram join


def grams(text):
    w = (text or "").lower().split()
    k = min(5, len(w))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if w else set()


def brute_links(rows):
    sets = [(i, grams(t)) for i, t in rows]
    links, parent = Counter(), {i: i for i, _ in sets}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a, (i, x) in enumerate(sets):
        for j, y in sets[:a]:
            if x and y and len(x & y) >= 0.8 * len(x | y):
                links[i] += 1
                links[j] += 1
                p, q = root(i), root(j)
                parent[max(p, q)] = min(p, q)
    return {i: (root(i), links[i]) for i, _ in sets}


def families(seed=4):
    rng = np.random.default_rng(seed)
    rows, n = [], 0
    for size in (1, 2, 3, 40, 1, 1, 5):
        base = [f"w{x}" for x in rng.integers(0, 5000, 120)]
        for _ in range(size):
            words = list(base)
            for at in rng.integers(0, 120, 2):
                words[at] = f"v{rng.integers(0, 5000)}"
            rows.append((n, " ".join(words)))
            n += 1
    rows += [(n, rows[0][1]), (n + 1, rows[0][1]), (n + 2, ""), (n + 3, None), (n + 4, "two words"), (n + 5, "Two  words")]
    return rows


def test_ngram_join_equals_brute_force(spark, monkeypatch):
    rows = families()
    df = spark.createDataFrame([(i, t, 0) for i, t in rows], "doc_id long, text string, class_id int")
    want = brute_links(rows)
    for block in (512, 8):
        monkeypatch.setattr(ngram_join, "BLOCK_CLASSES", block)
        got = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in ngram_join.ngram_join(df).collect()}
        assert got == want


def test_ngram_join_odd(odd, none):
    rows = ngram_join.ngram_join(odd).collect()
    assert len(rows) == len(ODD) and {r["class_id"] for r in rows if r["doc_id"] in (3, 5)} == {3}
    assert {r["n_links"] for r in rows if r["doc_id"] in (1, 2, 9)} == {0}
    assert ngram_join.ngram_join(none).count() == 0


def test_bands_reach_the_recall():
    b = ngram_join.bands_for()
    assert 1 - (1 - 0.8**5) ** b >= 0.9999 > 1 - (1 - 0.8**5) ** (b - 1)


# mixing


def test_weights_are_exact():
    assert mixing.exact_weights({"a": 0.3, "b": 0.1, "c": 0}) == {"a": 3, "b": 1, "c": 0}
    assert mixing.exact_weights({"a": 1e-4, "b": 1}) == {"a": 1, "b": 10000}
    with pytest.raises(ValueError):
        mixing.exact_weights({"a": -1.0})


def test_no_weight_no_turn_and_clashing_names(spark):
    names = ["s", "id", "h", "row", "rank", "part", "_total", "mix_note", "mix_slot", "p_s"]
    rows = [(i, "abz"[i % 3], *range(len(names))) for i in range(60)]
    df = spark.createDataFrame(rows, ["doc_id", "source", *names])
    got = mixing.mix_sources(df, {"a": 0.75, "b": 0.25, "z": 0}, block=2)
    assert [c for c in got.columns if not c.startswith("mix_")] == ["doc_id", "source", *[n for n in names if not n.startswith("mix_")]] and "mix_note" in got.columns
    got = got.collect()
    assert len(got) == 60 and all((r["mix_slot"] is None) == (r["source"] == "z") and r["rank"] == 4 and r["mix_note"] == 7 for r in got)
    assert mixing.in_mixed_order(df, {"a": 0.75, "b": 0.25, "z": 0}, block=2).columns == df.columns
    with pytest.raises(ValueError):
        mixing.mix_sources(df, {"a": 1.0000001, "b": 1.0, "z": 1.0})


def test_no_drift_from_target_weights(spark):
    sizes = {"a": 9000, "b": 300, "c": 20_000}
    df = spark.createDataFrame([(i, s) for s, n in sizes.items() for i in range(n)], "doc_id long, source string")
    weights = {"a": 0.317, "b": 0.011, "c": 0.672}
    rows = mixing.mix_sources(df, weights, block=4).select("mix_slot", "mix_source").distinct().orderBy("mix_slot").collect()
    left, seen = {s: -(-n // 4) for s, n in sizes.items()}, Counter()
    for t, r in enumerate(rows, 1):
        seen[r["mix_source"]] += 1
        assert all(abs(seen[s] - w * t) < 1 for s, w in weights.items())
        if any(seen[s] == n for s, n in left.items()):
            break
    assert t > 6000


def test_pfair_periods():
    for weights in ({"a": 5, "b": 3, "c": 2}, {"a": 1}, {"a": 7, "b": 7, "c": 1, "d": 20}):
        order, total = mixing.period(weights), sum(weights.values())
        seen = Counter()
        for t, s in enumerate(order, 1):
            seen[s] += 1
            assert all(abs(seen[x] - w * t / total) < 1 for x, w in weights.items())
        assert seen == weights


def test_mixing(spark, odd, none):
    rows = mixing.mix_sources(odd, block=2).collect()
    assert sorted(str(r["doc_id"]) for r in rows) == sorted(str(i) for i, _, _ in ODD) and "fingerprint" in rows[0].asDict()
    assert len({r["mix_position"] for r in rows}) == len(rows)
    assert all(r["mix_release"] <= r["mix_slot"] < r["mix_deadline"] for r in rows)
    assert mixing.mix_sources(none).count() == 0
    assert mixing.in_mixed_order(odd).columns == odd.columns


def test_mix_keeps_to_the_weights(spark):
    df = spark.range(6000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "hot").when(F.col("id") % 3 == 1, "b").otherwise("c").alias("source"))
    rows = mixing.mix_sources(df, {"hot": 6, "b": 3, "c": 1}, block=10).select("mix_slot", "mix_source").distinct().orderBy("mix_slot").collect()
    assert [r["mix_slot"] for r in rows] == list(range(600))
    seen = Counter()
    for t, r in enumerate(rows[:300], 1):
        seen[r["mix_source"]] += 1
        assert all(abs(seen[s] - w * t / 10) < 1 for s, w in (("hot", 6), ("b", 3), ("c", 1)))


# URL filters


def test_urls_equal_sql(spark, sf, duck):
    same(queries.op6_url_filters(spark, sf), duck, queries.oracle_sql()["op6_url_filters"])


def test_urls_by_hand(spark):
    urls = [None, "", "no scheme/en/", "http://Example.COM/en/71", "http://com/en/", "http://xcom/en/", "https://a.b.example.net/de/8?x", "http://a.net/de/8#t", "http://example.org", "http://a.com?/en/", "ftp://x.org/es/" + "y" * 5000]
    df = spark.createDataFrame([(i, u, "h") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = [(r["host"], r["rule"], r["verdict"]) for r in judge_urls(df, queries.URL_RULES).orderBy("page_id").collect()]
    assert got == [
        ("", None, "allow"), ("", None, "allow"), ("", None, "allow"), ("example.com", "example.com/en/7", "allow"), ("com", "com/en/", "block"), ("xcom", None, "allow"), ("a.b.example.net", "example.net/de/8", "block"),
        ("a.net", "net/de/", "allow"), ("example.org", None, "allow"), ("a.com", None, "allow"), ("x.org", "org/es/", "block"),
    ]
    assert judge_urls(df.limit(0), queries.URL_RULES).count() == 0 and judge_urls(df, []).where("verdict = 'allow'").count() == len(urls)


def test_long_urls_take_time_in_proportion():
    machine = ShiftAnd([Rule("com", "/a*z", "block"), *[Rule(f"h{i}.net", "/", "block") for i in range(40)]])
    start = time.process_time()
    got = machine.run([("com", "/en/")] * 3000 + [("com", "/a" + "y" * 1_000_000 + "z"), ("h7.net", "/" + "é" * 300_000)])
    assert not got[:3000].any() and np.flatnonzero(got[3000]).tolist() == [0] and np.flatnonzero(got[3001]).tolist() == [8]
    assert time.process_time() - start < 8


def test_globs_equal_regex():
    rules = [Rule("ex*.com", "/a?c", "block"), Rule("b.org", "/*z", "block"), Rule("*", "/q", "block")] + [Rule(f"h{i}.net", f"/p{i}", "block") for i in range(30)]
    hosts, paths = ["ex.com", "www.exam.com", "b.org", "ab.org", "h7.net", "q"], ["/abc", "/ac", "/aéc", "/a🙂c", "/aacz", "/q", "/p7x", "", "/zz"]
    cases = [(h, p) for h in hosts for p in paths]
    got = ShiftAnd(rules).run(cases)

    def pattern(glob):
        return "".join(".*" if c == "*" else "." if c == "?" else re.escape(c) for c in glob)

    for (h, p), fits in zip(cases, got, strict=True):
        assert [bool(re.fullmatch(r"(.*\.)?" + pattern(r.host), h) and re.match(pattern(r.path), p)) for r in rules] == fits.tolist()


# quality and toxicity


def auc(scores, labels):
    s, y = np.array(scores), np.array(labels)
    return np.mean([(a > b) + 0.5 * (a == b) for a in s[y == 1] for b in s[y == 0]])


def labelled(spark, n=400):
    rng = np.random.default_rng(8)
    words = [f"{a}{b}{c}" for a in ("ta", "ro", "mi", "se") for b in ("lo", "na", "ru", "ki") for c in ("", "s", "m", "n")]
    rows, labels = [], []
    for i in range(n):
        text = [str(w) for w in rng.choice(words, 80)]
        toxic, good = i % 4 == 0, i % 3 != 0
        if toxic:
            text[10:14] = rng.choice(["vilegrub", "vilegrubs", "vilegrubber"], 4)
        if not good:
            text = [w.upper() + "!!" for w in text]
        rows.append((i, " ".join(text), "a"))
        labels.append((i, int(good), int(toxic)))
    return docs(spark, rows), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_classifiers_on_held_out_rows(spark):
    df, labels = labelled(spark)
    truth = {r["doc_id"]: r for r in labels.collect()}
    for got, column, cut in ((quality.quality_scores(df, labels), "quality", 0.3), (toxicity.toxicity_scores(df, labels), "toxic", 0.5)):
        rows = got.collect()
        assert len(rows) == 400 and all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) and r["predicted"] == int(r["score"] >= cut) for r in rows)
        held = [r for r in rows if r["held_out"]]
        assert auc([r["score"] for r in held], [truth[r["doc_id"]][column] for r in held]) > 0.95


def test_labels_of_held_out_rows_do_not_count(spark):
    df, labels = labelled(spark, 200)
    turned = labels.withColumn("quality", F.when(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = ({r["doc_id"]: r["score"] for r in quality.quality_scores(df, x).collect()} for x in (labels, turned))
    assert a == b


def test_classifiers_odd(spark, odd, none):
    no = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    one = spark.createDataFrame([(5, 1, 1), (3, None, None), (None, 1, 0)], "doc_id long, quality int, toxic int")
    for fn in (quality.quality_scores, toxicity.toxicity_scores):
        for labels in (no, one):
            rows = fn(odd, labels).collect()
            assert len(rows) == len(ODD) and all(0 <= r["score"] <= 1 for r in rows)
        assert fn(none, no).count() == 0


def test_rare_and_toxic_only_histories_count(spark):
    rows = [("vilegrub here", 1), *[(f"plain words w{i} vile", 0) for i in range(30)], *[(f"other t{i} here", 1) for i in range(40)]]
    got = {r["gram"]: r["ratio"] for r in toxicity.log_ratios(spark.createDataFrame(rows, "text string, y int")).collect()}
    assert got["\x02vileg"] > 0  # a history that one toxic document has
    assert got["\x02vilegr"] > 0 and got["vilegrub"] > 0  # histories that no ordinary document has
    assert not any(g.startswith("\x02plai") for g in got)  # none that only ordinary ones have


def test_joined_model_scores_as_the_broadcast_one(spark, monkeypatch):
    df, labels = labelled(spark, 200)
    df = df.unionByName(docs(spark, [(None, "vilegrub, vilegrub ...", "a"), (7, "vilegrubs", "a"), (901, None, "a")]))
    found = []
    for most in (2**22, 0):
        monkeypatch.setattr(toxicity, "BROADCAST_GRAMS", most)
        found.append(sorted((str(r["doc_id"]), r["score"]) for r in toxicity.toxicity_scores(df, labels).collect()))
    assert len(found[0]) == 203 and [i for i, _ in found[0]] == [i for i, _ in found[1]]
    assert np.allclose([s for _, s in found[0]], [s for _, s in found[1]], atol=1e-6)


# HTML


def test_main_text():
    page = """<html><head><title>T</title><style>p{}</style></head><body><header><p>Site name</p></header><nav><ul><li><a href=x>Home</a></li></ul></nav><div class="cookie-notice">We use cookies</div>
    <article><h1>Head &amp; line</h1><p>First  paragraph<br>goes on.<p>Second &eacute;<script>var t="</p>"</script></p><form><input><label>Mail</label></form><aside>Read more</aside><p>ok</p></article>
    <div id="comments"><p>Nice post, really a long comment about this and that and more.</p></div><footer>&copy; me</footer></body></html>"""
    assert html_text.main_text(page) == "Head & line\n\nFirst paragraph goes on.\n\nSecond é\n\nok"
    assert html_text.main_text(None) == html_text.main_text("") == html_text.main_text("<nav><a>x</a></nav>") == ""
    assert html_text.main_text("<p>open <b>never closed") == "open never closed"


def test_wrappers_and_comments():
    page = '<div class="page has-sidebar"><main><article><h1>A</h1><p>B</p></article></main></div><section class="comments"><article class="comment"><p>Not this</p></article></section>'
    assert html_text.main_text(page) == "A\n\nB"
    page = '<article><p>B</p></article><article class="comment"><p>Not this</p></article>'
    assert html_text.main_text(page) == "B"


def test_main_text_without_an_article():
    long = "A sentence with a good many words in it that goes on for a while. " * 4
    page = f"<body><div class=menu><a>One</a> <a>Two</a></div><div><h2>Title</h2><p>{long}</p><p>Short.</p><p>{long}</p></div><div class='sidebar'><p>{long}</p></div></body>"
    assert html_text.main_text(page) == "\n\n".join(["Title", long.strip(), "Short.", long.strip()])


def test_extraction_keeps_rows(spark, sf):
    pages = spark.createDataFrame([(1, "u", None, "t"), (2, None, "<article><p>a</p></article>", "t"), (2, None, "<article><p>a</p></article>", "t")], "page_id long, url string, html string, text string")
    got = sorted((r["page_id"], r["text"], r["n_chars"]) for r in html_text.extract_main_text(pages).collect())
    assert got == [(1, "", 0), (2, "a", 1), (2, "a", 1)]
    assert html_text.extract_main_text(pages.limit(0)).count() == 0
    assert queries.op10_html_extraction(spark, sf).where("n_chars = 0").count() == 0


# pipeline


def test_pipeline_stages(spark, sf):
    import corpus_pipeline as cp

    start = spark.read.parquet(f"{sf}/documents.parquet")
    frame, seen = start, {}
    for name, stage in cp.STAGES:
        path = fresh_path(spark, "stage")
        stage(spark, frame, sf).write.parquet(path)
        frame = spark.read.parquet(path)
        seen[name] = frame
        if name != cp.STAGES[-1][0]:
            assert frame.columns == start.columns
    texts = [re.sub(r"[\x20\x09-\x0d]", "", r["text"] or "") for r in seen["exact_dedup"].collect()]
    assert len(texts) == len(set(texts)) and set(texts) == {re.sub(r"[\x20\x09-\x0d]", "", r["text"] or "") for r in seen["quality"].collect()}
    left = [(r["doc_id"], r["text"]) for r in seen["exact_dedup"].collect()]
    assert {r["doc_id"] for r in seen["near_duplicates"].collect()} == {c for c, _ in brute_links(left).values()}
    assert sorted(r["doc_id"] for r in seen["mixing"].collect()) == sorted(r["doc_id"] for r in seen["near_duplicates"].collect())
    check_packing(seen["packing"].collect(), 1024)


def test_pipeline_odd(spark, odd, none):
    import corpus_pipeline as cp

    left = {"exact_dedup": 4, "near_duplicates": 6, "mixing": 8, "packing": None}
    for name, stage in cp.STAGES[1:]:
        got = stage(spark, odd, "").collect()
        if name == "packing":
            check_packing(got, 1024)
            assert {r["doc_id"] for r in got} == {i for i, _, _ in ODD}
        else:
            assert len(got) == left[name] and list(got[0].asDict()) == odd.columns
        assert stage(spark, none, "").count() == 0


def test_exact_stage_keeps_null_ids_and_repeated_ids(spark):
    import corpus_pipeline as cp

    rows = [(None, "first text", "a"), (None, "second text", "a"), (None, "second  text", "a"), (4, "third text", "a"), (4, "fourth text", "a"), (4, "fourth  text", "b"), (6, "third  text", "a"), (6, "fifth", "a"), (-(2**63), "sixth", "a"), (None, "sixth", "a")]
    got = sorted((str(r["doc_id"]), r["text"]) for r in cp.exact(spark, docs(spark, rows), "").collect())
    assert got == sorted([("None", "first text"), ("None", "second  text"), ("4", "fourth  text"), ("6", "third  text"), ("6", "fifth"), (str(-(2**63)), "sixth")])


def test_packed_sequences_follow_the_mix(spark):
    import corpus_pipeline as cp

    text = F.concat(F.lit("some words "), F.repeat(F.lit("and more "), F.pmod(F.xxhash64("id"), F.lit(300)).cast("int")))
    df = spark.range(9000).select(F.col("id").alias("doc_id"), text.alias("text"), F.when(F.col("id") % 10 == 0, "rare").otherwise("most").alias("source"))
    rows = sorted(cp.packing(spark, df, "").collect(), key=lambda r: r["sequence_id"])
    check_packing(rows, 1024)
    assert sorted(r["doc_id"] for r in rows) == list(range(9000))
    # root weights: 30 to 90 until position 3,600
    for head in (1000, 2000, 3000):
        assert abs(sum(r["doc_id"] % 10 == 0 for r in rows[:head]) / head - 0.25) < 0.05


# rows that a single key would lose or gather


def test_join_tells_texts_of_one_id_apart(spark):
    a, b = (" ".join(f"{x}{i}" for i in range(60)) for x in "ab")
    rows = [(1, a), (1, b), (2, a + " more"), (3, b + " more"), (None, a + " other"), (None, "alone " + "in a text of its own"), (3, b + " more"), (None, None)]
    got = Counter((r["doc_id"], r["class_id"], r["n_links"]) for r in ngram_join.ngram_join(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == Counter([(1, 1, 2), (1, 1, 2), (2, 1, 2), (3, 1, 2), (3, 1, 2), (None, 1, 2), (None, None, 0), (None, None, 0)])


def test_one_of_each_class_stays(spark):
    a, b = (" ".join(f"{x}{i}" for i in range(60)) for x in "ab")
    rows = [(1, a, "x"), (1, b, "x"), (2, a + " more", "x"), (3, b + " more", "x"), (None, a + " other", "x"), (None, "alone in a text of its own", "x"), (3, b + " more", "x"), (None, None, "x"), (None, "", "x"), (7, " ", "x"), (8, "c d e f g", "x"), (8, "c d e f g", "x")]
    got = Counter((r["doc_id"], r["text"]) for r in ngram_join.one_of_each(docs(spark, rows)).collect())
    assert got == Counter([(1, a), (1, b), (None, "alone in a text of its own"), (None, None), (None, ""), (7, " "), (8, "c d e f g")])


def test_recall_of_the_bands():
    rng = np.random.default_rng(3)
    a, b = ngram_join._permutations(24 * 5)
    met = 0
    for _ in range(300):
        whole = rng.integers(0, 2**63, 110, np.int64).astype(np.uint64)
        x, y = np.unique(whole[:100]), np.unique(whole[10:])  # 90 of 110 in common: 0.82
        s, t = (ngram_join.signatures(g, a, b).reshape(24, 5) for g in (x, y))
        met += (s == t).all(1).any()
    assert met >= 0.99 * 300


def test_components_of_a_chain_and_a_star(spark):
    edges = [(i, i + 1) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 300)]
    got = {r["v"]: r["c"] for r in ngram_join.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(201)}, **{1000 + i: 1000 for i in range(300)}}


def test_quality_stage_with_clashing_names(spark):
    import corpus_pipeline as cp

    df, labels = labelled(spark, 200)
    path = fresh_path(spark, "labels")
    labels.write.parquet(f"{path}/labels.parquet")
    df = df.withColumns({"predicted": F.lit("p"), "held_out": F.lit("h"), "whole": F.lit(1), "_doc": F.lit(2)})
    got = cp.quality(spark, df, path)
    assert got.columns == df.columns
    left = {r["doc_id"] for r in got.where("predicted = 'p' AND score = 0.5").collect()}
    want = {r["doc_id"] for r in quality.quality_scores(df, labels).where("predicted = 1").collect()}
    assert left == want and 0 < len(left) < 200
    assert cp.quality(spark, docs(spark, ODD), path).count() <= len(ODD) and cp.quality(spark, df.limit(0), path).count() == 0


def test_fingerprints_of_a_repeated_id_are_many_ranges(spark):
    rows = [(None if i % 3 else i, f"text number {i}", "a") for i in range(300)]
    df = docs(spark, rows)
    bounds = fingerprint._range_bounds(df.select(F.coalesce("doc_id", F.lit(-(2**63))).alias("k"), F.xxhash64("text").alias("h")), 10)
    assert len(bounds) > 20 and bounds == sorted(set(bounds))
    got = fingerprint.neighbour_fingerprints(df, rows_per_range=10).collect()
    assert Counter(r["doc_id"] for r in got) == Counter(i for i, _, _ in rows)
    order = [t for _, t, _ in sorted(((i, t, 0) for i, t, _ in rows if i is not None), reverse=True)]
    want = {hashlib.sha256(fingerprint.edited(a, b).encode()).hexdigest() for a, b in zip(order, order[1:], strict=False)}
    assert want <= {r["edited_sha256"] for r in got}


def slow_digest(text: bytes) -> str:
    """The digest by counting, a triplet at a time."""
    counts = [0] * 256
    for k in range(len(text)):
        for (i, j), m in zip(((1, 2), (1, 3), (2, 3)), (0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D), strict=True):
            if k + j < len(text):
                h = text[k] | text[k + i] << 8 | text[k + j] << 16
                h = (h * m & 0xFFFFFFFF) ^ (h >> 7)
                counts[(h * 0x9E3779B1 & 0xFFFFFFFF) >> 24] += 1
    ranked = sorted(counts)
    q = ranked[63], ranked[127], ranked[191]
    codes = [sum(c > x for x in q) for c in counts]
    size, top = min(255, round(math.log(len(text) + 1) / math.log(1.25))), max(q[2], 1)
    body = bytes(codes[i] << 6 | codes[i + 1] << 4 | codes[i + 2] << 2 | codes[i + 3] for i in range(0, 256, 4))
    return (bytes([size, q[0] * 15 // top << 4 | q[1] * 15 // top]) + body).hex()


def test_digests_equal_counting_by_hand():
    texts = [b"", b"ab", b"abc", "naïve café".encode(), bytes(range(256)) * 3, b"x" * 5000]
    assert fingerprint.digests(texts) == [slow_digest(t) for t in texts]


def test_votes_equal_brute_force():
    rng = np.random.default_rng(6)
    counts, labels = rng.random((40, quality.TERMS)).astype(np.float32), (rng.random(40) < 0.4).astype(np.int64)
    model = quality.fit(counts, labels, 0.4, 8)
    asked = rng.random((7, quality.TERMS)).astype(np.float32)
    for x, got in zip(asked, model.score(asked), strict=True):
        v = x @ model.axes
        near = sorted(((float(v @ w) / float(np.linalg.norm(v)), y, g) for w, y, g in zip(model.vectors, labels, model.weights, strict=True)), reverse=True)[: quality.NEIGHBOURS]
        votes = [(max(s, 0) ** quality.SHARPNESS * g, y) for s, y, g in near]
        assert got == pytest.approx(sum(a * y for a, y in votes) / sum(a for a, _ in votes), rel=1e-3)
