"""The training-data operators against brute force on small fixtures with nulls, empty and long texts, ties, repeats and
clashing column names."""

from __future__ import annotations

import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from websieve.llm import components, decontamination, language_mixture, line_dedup, ngram_join, packing, secrets, token_counts, toxicity, vector_search, warc
from websieve.llm.common import Words, id_residue, slices
from websieve.llm.queries import tokenizer_file

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, key string, t string, words string"


def prose(rng: random.Random, n: int, letters: str = "abcdefg") -> str:
    return " ".join("".join(rng.choice(letters) for _ in range(rng.randint(1, 6))) for _ in range(n))


@pytest.fixture(scope="module")
def docs(spark):
    """Texts of all awkward kinds, with extra columns whose names the operators use inside."""
    rng = random.Random(5)
    base = [prose(rng, 60) for _ in range(30)]
    texts = [None, "", " ", "\n\n", "one", "Two words", "  spaced   out  ", "tab\tand\x0bfeed", "ÄÖÜ straße naïve", "日本語 テキスト", "x" * 50_000, prose(rng, 4000), "▁mark ▁▁ ▁", "<|endoftext|> and <s>", "a\x1fb c\x1cd"]
    texts += base + base[:5] + [b.replace("a", "A") for b in base[:3]] + [b + " tail" for b in base[3:9]] + [" ".join(b.split()[:30]) for b in base[9:12]]
    rows = [(i, t, "en", "s", None, "k", "t", "w") for i, t in enumerate(texts)]
    rows += [(3_000, None, None, None, None, None, None, None), rows[20], (None, "null id text with words", "en", None, 1, "k", "t", "w")]
    return spark.createDataFrame(rows, DOCS).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def test_words_of_sliced_batches():
    texts = pa.array(["Skip me", None, "A b  C", "x\ny", ""])
    words = Words(texts.slice(1), lines=True)
    spelled = [[words.distinct[int(c)].as_py() for c in words.codes[a:b]] for a, b in zip(words.bounds, words.bounds[1:])]
    assert spelled == [[""], ["A", "b", "", "C"], ["x", "\n", "y"], [""]]
    batch = pa.RecordBatch.from_arrays([pa.array(["ab", None, "c" * 10, "d"])], ["t"])
    assert [p.num_rows for p in slices(batch, 0, 4)] == [2, 1, 1]


def test_token_counts_equal_the_library(docs, empty):
    path = tokenizer_file("piece_bpe_32k.model")
    library = token_counts.SpaceCutTokenizer(path).library
    got = token_counts.count_tokens(docs, path, frequent=50).collect()
    truth = sorted((str(r.doc_id), len((r.text or "").encode()), len(library.encode(r.text or ""))) for r in docs.collect())
    assert sorted((str(r.doc_id), r.n_bytes, r.n_tokens) for r in got) == truth
    assert all(r.over_limit == (r.n_tokens > 4096) for r in got)
    assert token_counts.count_tokens(empty, path).count() == 0


def test_packing_round_trip(docs, empty):
    from tokenizers import Tokenizer

    path = tokenizer_file("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    rows = docs.where("doc_id IS NOT NULL").dropDuplicates(["doc_id"])
    ids = {r.doc_id: np.array([*library.encode(r.text or "", add_special_tokens=False).ids, 1], "<u4") for r in rows.collect()}
    pieces = packing.pack(rows, path).collect()
    covered = {}
    for p in pieces:
        own = ids[p.doc_id]
        assert p.doc_tokens == len(own) and p.ids_crc32 == zlib.crc32(own[p.start : p.start + p.length].tobytes())
        covered.setdefault(p.doc_id, []).extend(range(p.start, p.start + p.length))
    assert {k: sorted(v) for k, v in covered.items()} == {k: list(range(len(v))) for k, v in ids.items()}
    sequences = {}
    for p in pieces:
        sequences.setdefault(p.sequence_id, []).append((p.offset, p.length))
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048
    assert packing.pack(empty, path).count() == 0


def test_choose_cuts_is_optimal():
    rng = random.Random(3)
    for _ in range(30):
        steps = [rng.randint(1, 9) for _ in range(12)]
        ends, kinds = list(np.cumsum(steps)), [rng.randint(0, 2) for _ in steps]
        _, cost = packing.choose_cuts(ends, kinds, 10, 1.0, 3.0, 0.5)
        best = {-1: 0.0}
        for i, e in enumerate(ends):
            options = [best[j] + 10 - (e - (ends[j] if j >= 0 else 0)) for j in range(-1, i) if e - (ends[j] if j >= 0 else 0) <= 10]
            best[i] = min(options) + (0.0, 1.0, 3.0)[kinds[i]] + 0.5
        assert cost[-1] == pytest.approx(best[len(ends) - 1])


def brute_hits(docs, items, width=10):
    cut = lambda t: [w for w in re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOWER)) if w]
    windows = [(tuple(w[s : s + width]), i) for i, t in items for w in [cut(t)] if w for s in range(max(1, len(w) - width + 1))]
    out = {}
    for i, t in docs:
        words, hit, met = cut(t), set(), set()
        for window, item in windows:
            for s in range(len(words) - len(window) + 1):
                if tuple(words[s : s + len(window)]) == window:
                    hit.update(range(s, s + len(window)))
                    met.add(str(item))
        out[i] = (len(words), len(hit), sorted(met))
    return out


def test_decontamination_equals_brute_force(spark, docs, empty):
    texts = {r.doc_id: r.text for r in docs.collect()}
    long = [t for t in texts.values() if t and 50 < len(t.split()) < 100]
    items = [(1, long[0]), (2, " ".join(long[1].split()[5:17])), (3, "one"), (4, None), (5, "never seen anywhere zzz"), (2, "a a a"), (10, long[0].upper())]
    table = spark.createDataFrame(items, "item_id long, text string")
    index = decontamination.TestIndex(docs, table)
    got = {r.doc_id: (r.n_words, r.n_hit, r.item_ids) for r in index.report().collect()}
    assert got == brute_hits(texts.items(), items)
    assert index.report().count() == docs.count()
    shuffled = decontamination.TestIndex(docs, table, broadcast_rows=0)
    assert {r.doc_id: (r.n_words, r.n_hit, r.item_ids) for r in shuffled.report().collect()} == got
    assert decontamination.TestIndex(empty, table).report().count() == 0
    assert all(r.n_hit == 0 for r in decontamination.TestIndex(docs, table.limit(0)).report().collect())
    near = spark.createDataFrame([(1, "red x x x green blue"), (2, "green " + "y " * 30 + "red")], "doc_id long, text string")
    probe = decontamination.TestIndex(near, spark.createDataFrame([(1, "red green")], "item_id long, text string"))
    assert [r.doc_id for r in probe.proximity(8).collect()] == [1]
    assert decontamination.postings(near).where("term = 'x'").first().positions == [1, 2, 3]


def shingles(text, width=5):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def brute_components(rows):
    sets = [(i, shingles(t)) for i, t in rows]
    parent = list(range(len(sets)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(sets)):
        for b in range(a):
            x, y = sets[a][1], sets[b][1]
            if x and y and 100 * len(x & y) >= 80 * len(x | y):
                parent[find(a)] = find(b)
    least = {}
    for k, (i, _) in enumerate(sets):
        least[find(k)] = min(i, least.get(find(k), i))
    return sorted((i, len(s), least[find(k)] if s else i) for k, (i, s) in enumerate(sets))


def test_ngram_join_equals_brute_force(spark, docs, empty):
    rng = random.Random(11)
    base = [prose(rng, 80) for _ in range(4)]
    near = []
    for b in base:  # chains of edits, so that far ends are joined by others only
        words = b.split()
        for _ in range(12):
            words = list(words)
            words[rng.randrange(len(words))] = "edit%d" % rng.randrange(1000)
            near.append(" ".join(words))
    extra = spark.createDataFrame([(10_000 + i, t) for i, t in enumerate(near)], "doc_id long, text string")
    table = docs.where("doc_id IS NOT NULL").select("doc_id", "text").unionByName(extra)
    truth = brute_components([(r.doc_id, r.text) for r in table.collect()])
    for after in (0, 8):
        got = ngram_join.NearDuplicates(table, settle_after=after, broadcast_rows=10 if after else 1000).report()
        assert sorted((r.doc_id, r.n_shingles, r.component_id) for r in got.collect()) == truth
    assert ngram_join.NearDuplicates(docs).report().count() == docs.count()
    assert ngram_join.NearDuplicates(empty).report().count() == 0


def test_filters_are_safe():
    rng = np.random.default_rng(0)
    for _ in range(200):
        a = np.unique(rng.integers(0, 60, 40).astype(np.uint64))
        b = np.unique(np.concatenate([a[rng.random(len(a)) < 0.9], rng.integers(0, 60, 4).astype(np.uint64)]))
        exact = 100 * len(np.intersect1d(a, b)) >= 80 * len(np.union1d(a, b))
        assert ngram_join.similar(a, b, 80) == exact
        assert not (exact and ngram_join.far_apart(a, b, len(a) + len(b) - 2 * ngram_join.required(len(a), len(b), 80)))
    assert [ngram_join.prefix_size(n, 80) for n in (1, 4, 5, 10)] == [1, 1, 2, 3]


def test_components_of_a_long_chain(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(10, 60)] + [(100, 101), (101, 100)], "a long, b long")
    got = {r.node: r.component for r in components.components(links).collect()}
    assert got == {i: 10 for i in range(10, 61)} | {100: 100, 101: 100}


def test_line_dedup(spark, empty):
    rows = [(i, "h", f"menu\nbody {i}\n\nfooter" if i % 2 else f"menu\nbody {i}") for i in range(10)]
    rows += [(100 + i, "other", f"menu\nown {i}") for i in range(3)] + [(200, "h", None), (201, None, "menu"), (202, "h", "")]
    pages = spark.createDataFrame(rows, "page_id long, host string, text string").withColumn("line", F.lit(1)).withColumn("pages", F.lit(2))
    for limit in (100_000, 0):
        got = {r.page_id: r.text for r in line_dedup.drop_boilerplate(pages, ratio=0.3, least_pages=4, broadcast_lines=limit).collect()}
        assert got[1] == "body 1\n" and got[2] == "body 2" and got[100] == "menu\nown 0" and got[201] == "menu" and got[202] == ""
        assert got[200] is None and len(got) == len(rows)
    assert line_dedup.drop_boilerplate(empty, "doc_id", "source", "text").count() == 0


def test_toxicity(spark, empty):
    rng = random.Random(2)
    stems = ["zzkrow", "zzkren"]
    rows, labels = [], []
    for i in range(1500):
        words = prose(rng, 40).split()
        toxic = i % 5 == 0
        if toxic:
            for _ in range(3):
                words[rng.randrange(40)] = rng.choice(stems) + prose(rng, 1)
        rows.append((i, " ".join(words)))
        labels.append((i, int(toxic)))
    rows += [(5000, None), (5001, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("score", F.lit("x"))
    table = spark.createDataFrame(labels, "doc_id long, toxic int")
    residue = id_residue(F.col("doc_id"), 4)
    model = toxicity.fit(docs, table, residue != 2, residue == 3)
    got = toxicity.score(docs, model, out="p").join(table, "doc_id", "left").where((residue == 2) | F.col("toxic").isNull()).collect()
    right = [(r.p >= 0.3) == bool(r.toxic) for r in got if r.toxic is not None]
    assert np.mean(right) > 0.97 and all(0 <= r.p <= 1 for r in got)
    none = toxicity.fit(docs, table.limit(0), residue != 2, residue == 3)
    assert {r.p for r in toxicity.score(docs, none, out="p").collect()} == {0.0}
    assert toxicity.score(empty.select("doc_id", "text"), model, out="p").count() == 0


def test_kneser_ney_sums_to_one(spark):
    """Over all continuations of a context each class's probabilities add up to one (the rest is for unseen letters)."""
    rows = spark.createDataFrame([("abab abba baab abab", 1), ("bbaa abab aabb", 0)], "t string, y int")
    model = toxicity.fit_language_models(rows)
    assert model.own["count_toxic"].sum() == 20 and model.own["count_ordinary"].sum() == 15
    assert model.shared["count1"].sum() == model.shared["total1"].sum()


def test_secrets_base_patterns_and_added_spans(spark, docs, empty):
    rng = random.Random(1)
    key = "".join(rng.choice("ABCDEFGHJKLMNPQRSTUVWXYZabcdefghijkmnpqrstuvwxyz0123456789") for _ in range(40))
    texts = ['Token = "abcdef1" password: token: abcdef', "AKIA" + "A" * 16 + " AKIASHORT", "é " + "0" * 23 + " " + "0af" * 9, f"see {key} here", "cabbagefadedbagfacebadcab", None, ""]
    table = spark.createDataFrame([(90_000 + i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    corpus = docs.select("doc_id", "text").unionByName(table)
    got = {r.doc_id: [(s.kind, s.start, s.end) for s in r.spans] for r in secrets.scan(corpus, secrets.fit(corpus)).collect()}
    assert got[90_000] == [("assign", 0, 16)] and got[90_001] == [("access", 0, 20)] and ("hex", 26, 53) in got[90_002]
    assert got[90_003] == [("markov", 4, 44)] and got[90_004] == got[90_005] == got[90_006] == []
    assert secrets.scan(empty, secrets.fit(empty)).count() == 0


def test_warc_round_trip(spark, tmp_path):
    fake = "x" * 100 + "\r\n\r\nWARC/1.0\r\nWARC-Type: response\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n" + "y"
    htmls = ["<p>" + "é" * 80, "<p>" + "é" * 80, "tiny", "tiny", None, "", fake, fake + "\r\n\r\n", "WARC/1.0\r\n"]
    pages = spark.createDataFrame([(i, f"http://h/{i}", h) for i, h in enumerate(htmls)] + [(None, None, "n")], "page_id long, url string, html string").withColumn("size", F.lit("x"))
    warc.write(pages, f"file://{tmp_path}/w", records_per_file=4)
    got = {r.key: r for r in warc.read(spark, f"file://{tmp_path}/w").collect()}
    assert len(got) == len(htmls) + 1
    for i, h in enumerate(htmls):
        raw = (h or "").encode()
        assert (got[i].payload_bytes, got[i].payload_digest) == (len(raw), hashlib.sha256(raw).hexdigest())
        assert got[i].html == (None if i == 1 else h or "")
    assert (got[1].record_type, got[1].refers_to) == ("revisit", 0) and got[3].record_type == "response"
    warc.write(pages.limit(0), f"file://{tmp_path}/e")
    assert warc.read(spark, f"file://{tmp_path}/e").count() == 0


def test_pointer_jumping_follows_the_chain_only():
    assert warc.on_chain(np.array([0, 5, 9, 20]), np.array([9, 20, 20, -1])).tolist() == [True, False, True, True]
    assert warc.on_chain(np.array([3]), np.array([9])).tolist() == [False]
    assert warc.on_chain(np.array([], np.int64), np.array([], np.int64)).tolist() == []


def test_language_mixture(spark, docs, empty):
    rng = random.Random(4)
    alphabets = {"aa": "abcde", "bb": "defgh", "cc": "xyzab"}
    rows = [(i, prose(rng, 30, alphabets[lang]), lang) for i, lang in enumerate(list(alphabets) * 100)]
    train = spark.createDataFrame(rows + [(900, "no language", None), (901, None, "aa")], "doc_id long, text string, lang string")
    model = language_mixture.fit(train)
    mixed = " ".join([prose(rng, 60, "xyzab"), prose(rng, 40, "defgh")])
    test = spark.createDataFrame([(i, prose(rng, 25, a)) for i, a in enumerate(list(alphabets.values()) * 20)] + [(500, mixed), (501, None), (502, "123 ..")], "doc_id long, text string").withColumn("score", F.lit(1))
    got = {r.doc_id: r for r in language_mixture.identify(test, model).collect()}
    assert np.mean([got[i].lang_pred == list(alphabets)[i % 3] for i in range(60)]) > 0.95
    assert got[500].lang_pred == "cc" and 0.2 < got[500].shares["bb"] < 0.6
    assert (got[501].lang_pred, got[502].lang_pred, got[501].score) == ("und", "und", 0.0)
    assert language_mixture.identify(empty, model).count() == 0
    assert {r.lang_pred for r in language_mixture.identify(docs, language_mixture.fit(train.limit(0))).collect()} == {"und"}


def test_vector_search_equals_brute_force(spark):
    rng = np.random.default_rng(1)
    rows = [(i, [float(x) for x in rng.normal(size=8)]) for i in range(700)]
    rows += [(700, None), (701, [float("nan")] * 8), (702, [1.0, None] * 4), (703, [1.0, 2.0]), (704, []), (None, [1.0] * 8), (5, rows[5][1]), (706, rows[6][1])]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("shard", F.lit("x"))
    got = vector_search.top_k(table, F.col("vec_id") % 50 == 0, shard_rows=128, block_rows=5).collect()
    good = [(i, np.floor(256 * np.array(v, np.float32).astype(float))) for i, v in rows if i is not None and v and None not in v and np.isfinite(v).all()]
    truth = []
    for q, v in good:
        if q % 50 == 0:
            scores = sorted((-int(v @ w), i) for i, w in good if i != q and len(w) == len(v))[:5]
            truth += [(q, k + 1, i, -s) for k, (s, i) in enumerate(scores)]
    assert sorted((r.query_id, r.rank, r.vec_id, r.score) for r in got) == sorted(truth)
    assert vector_search.top_k(table.limit(0), F.col("vec_id") % 50 == 0).count() == 0


def test_toxicity_counts_every_learnable_text(spark):
    rng = random.Random(6)
    rows = [(i, prose(rng, 12) + (" zzkrow" if i % 4 == 0 else ""), int(i % 4 == 0)) for i in range(200)]
    residue = id_residue(F.col("doc_id"), 4)
    table = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    calibrating = {r.doc_id for r in table.where(residue == 3).collect()}
    rows = [(i, t + " qqvvx" if y and i in calibrating else t, y) for i, t, y in rows]
    table = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    models = toxicity.fit(table.select("doc_id", "text"), table.select("doc_id", "toxic"), residue != 2, residue == 3).language_models
    learnable = {r.doc_id for r in table.where(residue != 2).collect()}
    ends = [len(w) + 1 for i, t, _ in rows if i in learnable for w in t.split()]
    assert models.own["count_toxic"].sum() + models.own["count_ordinary"].sum() == sum(ends)
    grams = {("\0" * 4 + w + "\0")[k : k + 5] for i, t, _ in rows if i in learnable for w in t.split() for k in range(len(w) + 1)}
    assert len(models.keys["gram5"]) == len(grams) and models.ratios(pa.array(["qqvvx"]))[0] > 3


def test_join_verifies_classes_without_id_and_ids_of_several_texts(spark):
    rng = random.Random(8)
    words = [prose(rng, 1) + str(i) for i in range(200)]
    # 7 and 9 are linked only through the row without an id.
    ends = [" ".join(words[:186]), " ".join(words), " ".join(words[14:])]
    table = spark.createDataFrame([(7, ends[0]), (None, ends[1]), (9, ends[2])], "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in ngram_join.NearDuplicates(table, percent=90).report().collect()}
    assert got[7] == got[9] == 7
    # One id with two texts: each is verified by its own.
    one, other = [" ".join(prose(rng, 1) + str(k) for k in range(100)) for _ in range(2)]
    for order in ((one, other), (other, one)):
        table = spark.createDataFrame([(1, order[0]), (1, order[1]), (5, one + " end"), (6, other + " end")], "doc_id long, text string")
        got = {r.doc_id: r.component_id for r in ngram_join.NearDuplicates(table).report().collect()}
        assert got[5] == got[6] == 1


def test_mixture_of_more_than_three_languages(spark):
    rng = random.Random(3)
    alphabets = ["abcde", "fghij", "klmno", "pqrst", "uvwxy"]
    training = [(prose(rng, 300, a), f"l{k}") for k, a in enumerate(alphabets)]
    model = language_mixture.fit(spark.createDataFrame(training, "text string, lang string"))
    _, score, share = model.infer(pa.array([" ".join(prose(rng, 60, a) for a in alphabets), prose(rng, 60, "abcde"), " ".join(prose(rng, 60, a) for a in alphabets[:4])]), 9, 1.0)
    assert np.abs(share[0] - 0.2).max() < 0.03 and abs(score[0] - 0.2) < 0.03
    assert share[1][0] > 0.99 and np.abs(share[2][:4] - 0.25).max() < 0.03 and share[2][4] < 0.01


def test_signatures_never_rule_out_similar_sets():
    rng = np.random.default_rng(5)
    ruled_out = 0
    for k in range(300):
        a = np.unique(rng.integers(0, 1 << 63, int(rng.integers(1, 400))).astype(np.uint64) * np.uint64(2))
        other = np.unique(np.concatenate([a[rng.random(len(a)) < rng.choice([0.1, 0.85, 0.95])], rng.integers(0, 1 << 63, int(rng.integers(1, 60))).astype(np.uint64)]))
        least = ngram_join.required(len(a), len(other), 80)
        most = len(a) + len(other) - 2 * least
        apart = ngram_join.surely_different(ngram_join.signature(a), ngram_join.signature(other), most)
        assert not (apart and len(np.intersect1d(a, other)) >= least)
        ruled_out += apart
    assert ruled_out > 50
    full = np.arange(4000, dtype=np.uint64)  # all in one range, whose count stops at 255
    assert not ngram_join.surely_different(ngram_join.signature(full), ngram_join.signature(full[:3900]), 100)


def test_components_by_joins_equals_one_task(spark):
    rng = random.Random(12)
    links = spark.createDataFrame([(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(1000, 1000 + i) for i in range(1, 40)], "a long, b long")
    one = sorted(tuple(r) for r in components.components(links).collect())
    assert sorted(tuple(r) for r in components.components(links, one_task_links=0).collect()) == one


def test_decontamination_tells_rows_of_one_id_apart(spark):
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda"
    rows = [(1, "x " + item), (1, "nothing here"), (None, item + " y"), (None, None), (2, item), (2, item)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("own", F.lit(1)).withColumn("row_id", F.lit(2)).withColumn("t", F.lit("t"))
    items = spark.createDataFrame([(7, item)], "item_id long, text string")
    for limit in (500_000, 0):
        got = sorted((str(r.doc_id), r.n_words, r.n_hit, r.item_ids) for r in decontamination.TestIndex(docs, items, broadcast_rows=limit).report().collect())
        assert got == sorted([("1", 12, 11, ["7"]), ("1", 2, 0, []), ("None", 12, 11, ["7"]), ("None", 0, 0, []), ("2", 11, 11, ["7"]), ("2", 11, 11, ["7"])])


def test_decontamination_of_a_very_long_text_of_few_words(spark):
    rng = random.Random(13)
    letters = [chr(97 + i) * 2 for i in range(26)] + [chr(97 + i) * 3 for i in range(24)]
    words = [rng.choice(letters) for _ in range(200_000)]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, "aa bb")], "doc_id long, text string")
    items = spark.createDataFrame([(1, " ".join(words[150_000:150_012])), (2, " ".join(rng.choice(letters) for _ in range(30)))], "item_id long, text string")
    got = {r.doc_id: (r.n_words, r.n_hit, r.item_ids) for r in decontamination.TestIndex(docs, items).report().collect()}
    assert got == {1: (200_000, 12, ["1"]), 2: (2, 0, [])}


def test_line_dedup_of_an_id_on_two_hosts_does_not_depend_on_size(spark):
    rows = [(i, "a", f"menu\nbody {i}") for i in range(10)] + [(3, "b", "menu\nz"), (3, "b", "w\nmenu"), (None, "a", "menu\nq")]
    pages = spark.createDataFrame(rows, "page_id long, host string, text string").withColumn("gone_lines", F.lit(1)).withColumn("Gone_Host", F.lit(2)).withColumn("own", F.lit(3))
    out = []
    for limit in (100_000, 0):
        kept = line_dedup.drop_boilerplate(pages, least_pages=5, broadcast_lines=limit)
        assert kept.columns == pages.columns
        out.append(sorted((str(r.page_id), r.host, r.text) for r in kept.collect()))
    assert out[0] == out[1] and ("3", "b", "menu\nz") in out[0] and ("None", "a", "q") in out[0] and ("3", "a", "body 3") in out[0]


def test_last_round_meets_the_same_pairs_without_the_square_of_a_shared_passage(spark):
    """A passage that many texts share: the pairs that pass are those of the plain join of all entries, and where the passage is too
    little of the texts to make any of them similar, no entry meets another."""
    rng = random.Random(11)
    passage = [f"common{i}" for i in range(30)]

    def met_and_square(sizes, percent):
        rows = []
        for i in range(150):
            own = [f"w{rng.randrange(10**6)}" for _ in range(rng.choice(sizes))]
            at = rng.randrange(len(own) + 1)
            rows.append((i, " ".join(own[:at] + passage + own[at:])))
        join = ngram_join.NearDuplicates(spark.createDataFrame(rows, "doc_id long, text string"), percent=percent)
        entries = join.entries.withColumn("component", F.col("key"))
        lengths = 100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b")
        square = join._side(entries, "a").join(join._side(entries, "b"), "token").where((F.col("a") < F.col("b")) & lengths)
        met = join._met_all(entries)
        keys = [{tuple(r) for r in join._pairs(rows).select("a", "b").collect()} for rows in (met, square)]
        assert keys[0] == keys[1]
        return met.count(), square.count(), len(keys[0])

    met, square, pairs = met_and_square([1, 3, 6, 8, 10, 14, 40], 80)
    assert 0 < pairs <= met < square
    met, square, pairs = met_and_square([5, 6], 80)
    assert (met, pairs) == (0, 0) and square > 1000


def test_caches_hold_a_working_set_that_fits():
    from websieve.llm.common import BoundedCache

    cache, misses = BoundedCache(100 * 190), 0
    for _ in range(3):
        for key in (f"key{i:07}" for i in range(90)):
            if cache.get(key) is None:
                misses += 1
                cache.put(key, b"x")
    assert misses == 90 and len(cache) == 90
    for i in range(1000):
        cache.put(f"new{i:07}", b"x")
    assert 80 <= len(cache) <= 100 and cache.held == sum(180 + len(k) for k in cache) and "new0000999" in cache
    cache.put("x" * 20_000, b"y")
    assert cache.held <= 100 * 190


def test_words_are_scored_a_part_at_a_time(spark, monkeypatch):
    from websieve.llm import toxicity

    docs = spark.createDataFrame([(i, f"{'bad' if i % 2 else 'good'} word{i} thing") for i in range(40)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels, F.lit(True), F.col("doc_id") % 4 < 2).language_models
    texts, sizes, ratios = pa.array([r.text for r in docs.collect()] + ["", None]), [], toxicity.KneserNey.ratios
    whole = toxicity.features(texts, model)
    monkeypatch.setattr(toxicity, "RATIO_WORDS", 4)
    monkeypatch.setattr(toxicity.KneserNey, "ratios", lambda self, words: sizes.append(len(words)) or ratios(self, words))
    assert np.array_equal(toxicity.features(texts, model), whole) and max(sizes) == 4 and len(sizes) > 9


def test_workers_forget_other_operators():
    from websieve.llm import common

    common.loaded("one")["x"] = 1
    common.loaded("two")["y"] = 2
    common.forget_others("two")
    assert common.loaded("two") == {"y": 2} and common.loaded("one") == {}
    common.forget_others(None)
    assert common.loaded("two") == {}
