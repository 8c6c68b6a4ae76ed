"""Each operator against a plain version, and on tables with nulls, ties, repeats, clashing columns and nothing at all."""

from __future__ import annotations

import hashlib
import random
import re
import time
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from matkeep.llm import (
    chat_format,
    components,
    fertility_rules,
    hilbert_shards,
    line_runs,
    ngram_join,
    phrase_index,
    quality_net,
    sentence_pieces,
    shingling,
    toxicity_fm,
    url_filter,
)

from matkeep.llm.lookup import Lookup

from . import brute

DOC = "doc_id long, text string, lang string, source string, n_chars long, shard int, did string, n_words int, tok string"
WORDS = [a + b for a in ("ka", "lo", "mi", "ru", "te", "zo") for b in ("n", "s", "ta", "vi")]


def docs_frame(spark, rows):
    return spark.createDataFrame([(d, t, lang, "src", None, 3, "x", 1, "y") for d, t, lang in rows], DOC)


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


NASTY = [
    (None, "no id " * 12, "en"), (1, None, "en"), (2, "", None), (3, " \n\t ", "xx"), (4, "one", "en"), (4, "another text of one id", "en"),
    (5, "same text here " * 9, "de"), (5, "same text here " * 9, "de"), (6, "same text here " * 9, "de"), (7, "x" * 3000, "en"),
    (8, "Ünïcode ▁ 日本語 😀 \x00 text \\ </s>", "ja"), (9, "long words of prose " * 800, "en"),
]


@pytest.fixture(scope="module")
def nasty(spark):
    return docs_frame(spark, NASTY)


@pytest.fixture(scope="module")
def nothing(nasty):
    return nasty.limit(0)


def test_segmentation_is_the_best_one():
    pieces = sentence_pieces.Pieces(["▁", "a", "b", "c", "ab", "bc", "▁ab", "abc", "▁a"], list(range(3, 12)), [-3.0, -2.0, -2.0, -2.0, -2.5, -2.5, -3.5, -5.0, -3.0], list(range(20, 276)), 300)
    seg = sentence_pieces.Segmenter(pieces)

    def best(m):
        score = dict(zip(pieces.texts, pieces.scores, strict=True))
        top = [0.0] + [None] * len(m)
        for e in range(1, len(m) + 1):
            options = [top[e - n] + score[m[e - n : e]] for n in range(1, e + 1) if m[e - n : e] in score and top[e - n] is not None]
            if m[e - 1] not in score:
                options.append(top[e - 1] + seg.byte_score * len(m[e - 1].encode()))
            top[e] = max(options)
        return top[-1]

    rng = random.Random(1)
    for _ in range(300):
        text = "".join(rng.choice("abc dé\n") for _ in range(rng.randrange(1, 14)))
        ids = seg.encode(text)
        assert abs(seg.score_of[ids].sum() - best((" " + text).replace(" ", "▁"))) < 1e-9
        assert seg.decode(ids) == text


def test_real_vocabulary_against_a_plain_viterbi():
    pieces = sentence_pieces.load_pieces()
    seg = sentence_pieces.Segmenter(pieces)
    score = dict(zip(pieces.texts, pieces.scores, strict=True))
    assert max(pieces.scores) < 0 and len({round(x, 9) for x in pieces.scores}) > 30_000
    longest = max(map(len, score))
    for text in ("The quick brown fox jumps over the lazy dog.", "  zwei  Wörter\n\nund 日本語 \U0001f600!", "x" * 50, "aaaa bbbb\tcc"):
        m = (" " + text).replace(" ", "▁")
        top = [0.0] + [float("-inf")] * len(m)
        for e in range(1, len(m) + 1):
            top[e] = max([top[e - n] + score[m[e - n : e]] for n in range(1, min(e, longest) + 1) if m[e - n : e] in score] + ([] if m[e - 1] in seg.single else [top[e - 1] + seg.byte_score * len(m[e - 1].encode())]))
        ids = seg.encode(text)
        assert abs(seg.score_of[ids].sum() - top[-1]) < 1e-6 and seg.decode(ids) == text


def test_very_long_words_and_texts(spark):
    texts = ["q" * 300_000, "ab " * 200_000, "é" * 100_000, " " * 50_000]
    rows = sentence_pieces.encode_documents(spark, docs_frame(spark, [(i, t, "en") for i, t in enumerate(texts)])).select("doc_id", "round_trip").collect()
    assert sorted(r["doc_id"] for r in rows) == [0, 1, 2, 3] and all(r["round_trip"] for r in rows)


def test_encoding_round_trip(spark, nasty, nothing):
    rows = sentence_pieces.encode_documents(spark, nasty).collect()
    assert len(rows) == len(NASTY) and all(r["round_trip"] and r["n_ids"] == len(r["ids"]) for r in rows)
    back = sentence_pieces.decode_ids(spark, sentence_pieces.encode_documents(spark, nasty)).collect()
    assert sorted((str(r["doc_id"]), r["text"]) for r in back) == sorted((str(d), t or "") for d, t, _ in NASTY)
    assert sentence_pieces.encode_documents(spark, nothing).count() == 0


def near_copies(rng, base, share):
    w = base.split()
    for i in range(len(w)):
        if rng.random() < share:
            w[i] = rng.choice(WORDS)
    return " ".join(w)


def test_jaccard_components(spark, nasty, nothing):
    rng = random.Random(5)
    rows = [(i, prose(rng, rng.randrange(3, 60)), "en") for i in range(30)]
    base = prose(rng, 120)
    rows += [(100 + i, near_copies(rng, base, 0.015), "en") for i in range(40)]
    rows += [(200, base, "en"), (201, base.upper(), "en"), (202, base.replace(" ", "\n"), "en"), (203, "a b c", "en"), (204, "a  b c", "en")]
    for table in (rows, NASTY):
        want = brute.similar_components([(d, t) for d, t, _ in table])
        got = ngram_join.similar_components(spark, docs_frame(spark, table)).collect()
        assert len(got) == len(table)
        for r in got:
            assert r["component_id"] == want.get(r["doc_id"])
        sizes = sorted((str(d), len(brute.shingle_set(t))) for d, t, _ in table)
        assert sorted((str(r["doc_id"]), r["n_shingles"]) for r in got) == sizes
    assert ngram_join.similar_components(spark, nothing).count() == 0
    kept = ngram_join.one_of_each_group(spark, docs_frame(spark, rows))
    assert kept.columns == docs_frame(spark, rows).columns
    want = brute.similar_components([(d, t) for d, t, _ in rows])
    assert {r["doc_id"] for r in kept.collect()} == set(want.values())


def test_one_of_each_group_keeps_no_repeated_row(spark, nasty):
    kept = ngram_join.one_of_each_group(spark, nasty)
    assert kept.columns == nasty.columns
    group = brute.similar_components([(d, t) for d, t, _ in NASTY])
    want = [(None, NASTY[0][1]), *{(d, t) for d, t, _ in NASTY if d is not None and group[d] == d}]
    assert sorted((str(r["doc_id"]), str(r["text"])) for r in kept.collect()) == sorted((str(d), str(t)) for d, t in want)


def test_both_texts_of_an_id_find_their_near_copies(spark):
    rng = random.Random(15)
    x, y = prose(rng, 80), prose(rng, 90)
    close = " ".join([*y.split()[:-1], "end"])
    rows = [(3, x, "en"), (20, x, "en"), (20, y, "en"), (30, close, "en"), (40, y, "en"), (50, prose(rng, 70), "en")]
    want = brute.similar_components([(d, t) for d, t, _ in rows])
    assert want == {3: 3, 20: 3, 30: 3, 40: 3, 50: 50}
    got = ngram_join.similar_components(spark, docs_frame(spark, rows)).collect()
    assert sorted((r["doc_id"], r["component_id"]) for r in got) == sorted((d, want[d]) for d, _, _ in rows)


def test_shortened_shingles_that_coincide_lose_no_pair(spark):
    n, text = 100, " ".join(f"w{i}" for i in range(104))
    p = ngram_join.prefix_length(n)
    same = [7] * (p - 4) + [1, 2, 3, 4]  # as if all but five had one shortened value
    reps = spark.createDataFrame([(1, n, same, same), (2, n, same, same)], "doc_id long, n int, p1 array<int>, p2 array<int>")
    docs = spark.createDataFrame([(1, text), (2, text + " x")], "doc_id long, text string")
    got = ngram_join.verified(spark.createDataFrame([(1, 2)], "a long, b long"), reps, docs).collect()
    assert [tuple(r) for r in got] == [(1, 2)]


def test_leaders_and_listed_pairs_agree(spark, monkeypatch):
    rng = random.Random(6)
    base = prose(rng, 100)
    rows = [(i, near_copies(rng, base, 0.02), "en") for i in range(30)]
    want = brute.similar_components([(d, t) for d, t, _ in rows])
    monkeypatch.setattr(ngram_join, "PAIRS_PER_ROW", 0)
    monkeypatch.setattr(ngram_join, "LEADER_ROUNDS", 1)
    for name, low in (("HOT_LIST", 3), ("LONG_LIST", 4), ("SPREAD", 2)):
        monkeypatch.setattr(ngram_join, name, low)
    assert {r["doc_id"]: r["component_id"] for r in ngram_join.similar_components(spark, docs_frame(spark, rows)).collect()} == want


def test_words_and_shingles_of_a_slice_are_those_of_each_text(monkeypatch):
    rng = random.Random(21)
    bits = [" ", " ", "\n", "\t", "\x0b", "\x0c", "\r", "\x00", "\x1c", "\x85", "\xa0", "a", "A", "b", "é", "日", "z" * 8, "w" * 128, "w" * 129, "B" * 136]
    texts = [None, "", " ", "x", *("".join(rng.choice(bits) for _ in range(rng.randrange(40))) for _ in range(600))]
    for piece in (1 << 20, 7):
        monkeypatch.setattr(shingling, "PIECE_BYTES", piece)
        column = pa.array(["before", *texts]).slice(1)
        found, bounds = shingling.word_hashes(*shingling.lowered(column))
        sets, edges, _, _ = ngram_join.Shingler().sets(column)
        known = {}
        for k, text in enumerate(texts):
            words = brute.words5(text)
            assert len(words) == bounds[k + 1] - bounds[k]
            assert all(known.setdefault(w, h) == h for w, h in zip(words, found[bounds[k] : bounds[k + 1]].tolist(), strict=True))
            assert edges[k + 1] - edges[k] == len(brute.shingle_set(text)) == len(set(sets[edges[k] : edges[k + 1]].tolist()))
        assert len(set(known.values())) == len(known) > 100


def test_slots_find_what_shares_a_slot():
    keys = np.array([1, 2, 3, 1 << 40, (1 << 64) - 1, (1 << 64) - 2, 0], dtype=np.uint64)
    asked = np.array([5, 3, 0, (1 << 64) - 2, 1, (1 << 64) - 3, 1 << 40, (1 << 64) - 1], dtype=np.uint64)
    assert shingling.Slots(keys, np.arange(1, 8)).get(asked).tolist() == [0, 3, 0, 6, 1, 0, 4, 5]
    assert shingling.Slots(keys[:0], np.arange(0)).get(asked).tolist() == [0] * 8


class _Handed:
    """Stands for a frame: what is mapped over it is kept, to be called here."""

    def select(self, *columns):
        return self

    def mapInArrow(self, function, schema):  # noqa: N802
        return function


def test_signing_takes_little_more_time_than_splitting(spark):
    """In CPU seconds of this process, so that no other work counts; the least of three."""
    rng = random.Random(22)
    words = [f"{rng.choice(WORDS)}{rng.choice(WORDS)}{i}" for i in range(60_000)]
    texts = [" ".join(rng.choices(words, k=300)) for _ in range(1500)]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array(texts)], names=["doc_id", "text"])
    sign = ngram_join.signatures(spark, _Handed(), ngram_join.frequent_parts(docs_frame(spark, [(i, x, "en") for i, x in enumerate(texts[:50])])))

    def least(call):
        took = []
        for _ in range(3):
            began = time.process_time()
            call()
            took.append(time.process_time() - began)
        return min(took)

    assert least(lambda: list(sign(iter([batch])))) < 5 * least(lambda: [x.encode().lower().split() for x in texts])


def test_components(spark):
    edges = [(i, i + 1) for i in range(1, 20)] + [(30, 31), (31, 32), (40, 40), (7, 3)]
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 1 for i in range(1, 21)} | {30: 30, 31: 30, 32: 30}


def test_short_edge_lists_are_joined_in_few_jobs(spark, monkeypatch):
    rng = random.Random(8)
    edges = spark.createDataFrame([(rng.randrange(400), rng.randrange(400)) for _ in range(300)] + [(i, i + 1) for i in range(500, 600)], "a long, b long")
    spark.sparkContext.setJobGroup("short-edges", "")
    joined = components.components(edges)
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("short-edges")) <= 8
    monkeypatch.setattr(components, "ONE_TASK", 0)
    assert sorted(map(tuple, joined.collect())) == sorted(map(tuple, components.components(edges).collect()))


def test_line_dedup(spark, nasty, nothing):
    rng = random.Random(3)
    lines = [prose(rng, n) for n in (2, 3, 4, 6, 11, 14)] + ["", "  "]
    rows = [(i, "\n".join(rng.choice(lines) for _ in range(rng.randrange(1, 9))), "en") for i in range(40)] + [(50, None, "en"), (51, "", "en")]
    got = {r["doc_id"]: r["text"] for r in line_runs.dedup_lines(spark, docs_frame(spark, rows)).collect()}
    assert got == brute.line_dedup([(d, t) for d, t, _ in rows])
    out = line_runs.dedup_lines(spark, nasty)
    assert set(nasty.columns) < set(out.columns) and out.count() == len(NASTY)
    kept = [(r["doc_id"], r["text"]) for r in out.collect()]
    assert kept.count((5, NASTY[6][1])) == 2 and (6, "") in kept and (1, None) in kept
    assert line_runs.dedup_lines(spark, nothing).count() == 0


def test_chat_windows(spark):
    rng = random.Random(2)
    rows = []
    for c in range(12):
        for t in range(rng.randrange(1, 14)):
            role = "system" if t == 0 and c % 2 else rng.choice(["user", "assistant", None])
            rows.append((c if c else None, t, role, rng.choice([None, "", "</s>", "\\", "<s>[INST]x[/INST]", prose(rng, rng.randrange(1, 60))]), 9))
    rows += [(3, 0, "user", "tie", 9), (3, 0, "user", "tie", 9)]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, window int")
    windows = chat_format.chat_windows(turns, budget=120, history=40)
    got = {r["conv_id"]: r for r in chat_format.read_back(windows).collect()}
    for c in {r[0] for r in rows}:
        own = sorted((r[1], r[2] or "", r[3] or "") for r in rows if r[0] == c)
        text = "".join(f"{role}\n{t}\n" for _, role, t in own)
        loss = "".join(t for _, role, t in own if role == "assistant")
        assert got[c]["n_turns"] == len(own)
        assert got[c]["turns_sha256"] == hashlib.sha256(text.encode()).hexdigest()
        assert (got[c]["loss_chars"], got[c]["loss_sha256"]) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    for w in windows.collect():
        new = [s for s in w["segments"] if s["kind"] == "new"]
        assert new and [s["idx"] for s in w["segments"]] == sorted(s["idx"] for s in w["segments"])
        assert w["n_tokens"] <= 120 or len(new) == 1
        assert not any(s["loss"] for s in w["segments"] if s["kind"] != "new")
    assert chat_format.chat_windows(turns.limit(0)).count() == 0


def test_decontamination(spark, nasty, nothing):
    rng = random.Random(4)
    items = [(i, prose(rng, rng.randrange(1, 25))) for i in range(8)] + [(20, "..."), (21, None), (22, "Same TEXT here"), (9, "same text here"), (None, "one")]
    rows = [(i, " ".join([prose(rng, rng.randrange(0, 20)), rng.choice(items[:8])[1].upper().replace(" ", ", "), prose(rng, 5)]), "en") for i in range(25)]
    bench = spark.createDataFrame([(*x, 1) for x in items], "item_id long, text string, doc_id int")
    named = [x for x in items if x[0] is not None]
    for table in (rows, NASTY):
        got = phrase_index.decontaminate(spark, docs_frame(spark, table), bench).collect()
        want = []
        for d, t, _ in table:
            n, hit, _ = brute.contaminated(t, items)
            ids = brute.contaminated(t, named)[2]
            want.append((str(d), n, hit, len(ids), hashlib.sha256(",".join(ids).encode()).hexdigest(), hit > 0))
        assert sorted((str(r[0]), *r[1:]) for r in got) == sorted(want)
    assert phrase_index.decontaminate(spark, nothing, bench).count() == 0
    assert not any(r["contaminated"] for r in phrase_index.decontaminate(spark, nasty, bench.limit(0)).collect())
    clean = {r["doc_id"] for r in phrase_index.clean_documents(spark, docs_frame(spark, rows), bench).collect()}
    assert clean == {d for d, t, _ in rows if not brute.contaminated(t, items)[1]}


def test_proximity(spark):
    docs = docs_frame(spark, [(1, "alpha beta gamma", "en"), (2, "alpha x beta y gamma", "en"), (3, "gamma q r s t u v alpha beta", "en")])
    windows = phrase_index.phrase_windows(spark.createDataFrame([(1, "alpha beta gamma")], "item_id long, text string"))
    index = phrase_index.build_index(docs, windows.terms)
    ids = lambda slop: {r["did"] for r in phrase_index.phrase_matches(index, windows, slop).collect()}
    assert (ids(0), ids(2)) == ({1}, {1, 2})


def test_decontamination_returns_near_items(spark):
    texts = ["alpha beta gamma", "alpha x beta y gamma", "gamma q r s t u v alpha beta", None, "alpha x beta gamma delta one two"]
    docs = docs_frame(spark, [(i, t, "en") for i, t in enumerate(texts)])
    bench = spark.createDataFrame([(1, "alpha beta gamma"), (2, "delta one")], "item_id long, text string")
    got = {r["doc_id"]: r for r in phrase_index.decontaminate(spark, docs, bench, slop=2).collect()}
    assert {d: (r["n_hit"], r["n_items"], r["n_near"]) for d, r in got.items()} == {0: (3, 1, 0), 1: (0, 0, 1), 2: (0, 0, 0), 3: (0, 0, 0), 4: (2, 1, 1)}
    digest = lambda x: hashlib.sha256(x.encode()).hexdigest()
    assert got[1]["near_sha256"] == got[4]["near_sha256"] == digest("1") and got[0]["near_sha256"] == digest("")
    assert not got[1]["contaminated"] and got[4]["contaminated"]


def labelled(rng, n):
    rows = []
    for i in range(n):
        text, toxic, good = prose(rng, 40), i % 5 == 0, i % 4 != 1
        if toxic:
            text += " " + rng.choice(["grumblefool", "grumbletwit"]) + " " + prose(rng, 5)
        if not good:
            text = " ".join(w.upper() + "!!" for w in text.split())
        rows.append((i, text, int(toxic), int(good)))
    return rows


def test_classifiers(spark, nasty, nothing):
    rows = labelled(random.Random(9), 400)
    docs = docs_frame(spark, [(d, t, "en") for d, t, _, _ in rows])
    labels = spark.createDataFrame([(d, x, y) for d, _, x, y in rows] + [(None, 1, 1), (5, None, None)], "doc_id long, toxic int, quality int")
    held = lambda d, folds, at: zlib.crc32(str(d).encode()) % folds == at
    for module, column, folds, at in ((toxicity_fm, 2, 5, 0), (quality_net, 3, 4, 2)):
        model = module.fit_on(docs, labels)
        got = {r["doc_id"]: r for r in module.score_documents(spark, docs, model).collect()}
        apart = [r for r in rows if held(r[0], folds, at)]
        assert all(got[r[0]]["held_out"] == held(r[0], folds, at) and 0 <= got[r[0]]["score"] <= 1 for r in rows)
        assert sum(got[r[0]]["predicted"] == r[column] for r in apart) >= 0.95 * len(apart)
        edge = module.score_documents(spark, nasty, model).collect()
        assert len(edge) == len(NASTY) and all(0 <= r["score"] <= 1 for r in edge)
        assert module.score_documents(spark, nothing, model).count() == 0
        bare = module.fit_on(docs, labels.limit(0))
        assert module.score_documents(spark, nasty, bare).count() == len(NASTY)
    kept = quality_net.good_documents(spark, docs, quality_net.fit_on(docs, labels))
    assert kept.schema == docs.schema


def test_contexts_are_those_of_a_plain_sum(monkeypatch):
    texts = ["a b c a", "b", "", "c c b a d e f g h"]
    monkeypatch.setattr(quality_net, "STEP", 3)
    want = np.zeros((quality_net.ROWS, quality_net.DIMS))
    index = lambda w: sum(quality_net.index_vectors(np.array([h]))[0] for h in quality_net.unit_hashes(w))
    for t in texts:
        w = t.split()
        for i in range(len(w)):
            around = sum((index(w[j]) for j in range(max(0, i - 2), min(len(w), i + 3)) if j != i), np.zeros(quality_net.DIMS))
            for h in quality_net.unit_hashes(w[i]):
                want[h % quality_net.ROWS] += around
    assert np.array_equal(quality_net.context_sums(texts), want)


def test_temperature_calibrates():
    rng = np.random.default_rng(3)
    odds = rng.normal(0, 2, 20_000)
    labels = (rng.random(20_000) < 1 / (1 + np.exp(-odds))).astype(float)
    assert abs(quality_net.temperature_of(3 * odds, labels, np.ones(20_000)) - 3) < 0.3


def test_buckets_are_those_of_a_plain_count(spark):
    rows = labelled(random.Random(9), 200)
    docs = docs_frame(spark, [(d, t, "en") for d, t, _, _ in rows])
    labels = spark.createDataFrame([(d, x) for d, _, x, _ in rows], "doc_id long, toxic int")
    own = [r for r in rows if zlib.crc32(str(r[0]).encode()) % 5]
    terms = [np.unique([t for w in toxicity_fm.words_of(r[1].lower()) for t in toxicity_fm.word_terms(w)]) for r in own]
    want = toxicity_fm.associated_buckets(terms, np.array([r[2] for r in own]), toxicity_fm.KEPT)
    assert np.array_equal(toxicity_fm.fit_on(docs, labels).buckets, want)


def test_pairs_matter_to_the_factorization_machine():
    rng = random.Random(0)
    words = [toxicity_fm.word_terms(w) for w in ("alpha", "omega", "plain", "other")]
    rows, labels = [], []
    for _ in range(1200):  # toxic only if both stand there: no linear weights say so
        a, b = rng.random() < 0.5, rng.random() < 0.5
        rows.append(np.unique([t for use, w in ((a, 0), (b, 1), (rng.random() < 0.5, 2)) if use for t in words[w]] or words[3]).astype(np.int64))
        labels.append(int(a and b) if rng.random() < 0.97 else int(not (a and b)))
    fm = toxicity_fm.fit(rows, np.array(labels), {0: 900, 1: 300}, epochs=40)
    right = [int(fm.score(toxicity_fm.present(fm.buckets, r)) >= 0.5) == y for r, y in zip(rows, labels, strict=True)]
    assert np.mean(right) > 0.93 and np.abs(fm.factors).max() > 0.1


def test_fertility_counts(spark, nasty, nothing):
    rows = {(str(r["doc_id"]), r["n_words"]): r for r in fertility_rules.judge_documents(spark, nasty).collect()}
    for d, text, _ in NASTY:
        w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
        r = rows[(str(d), len(w))]
        seen = {}
        for i in range(len(w) - 4):
            seen.setdefault(tuple(w[i : i + 5]), []).append(i)
        rep = {j for at in seen.values() if len(at) > 1 for i in at for j in range(i, i + 5)}
        assert r["n_repeat_words"] == len(rep) and r["word_chars"] == sum(map(len, w))
        assert r["n_symbols"] == len(re.findall(r"[#*$%&|<>]", text or ""))
        assert r["base_failed"] == (len(w) < 10 or 100 * len(rep) > 20 * len(w))
        assert not (r["kept"] and r["base_failed"])
    assert fertility_rules.judge_documents(spark, nothing).count() == 0


def test_script_is_that_of_all_characters(spark):
    rows = [(1, " abc" * 1000, None), (2, ("д" + "a" * 19) * 200, None)]  # evenly spaced samples see spaces or д alone
    got = fertility_rules.judge_documents(spark, docs_frame(spark, rows)).collect()
    assert [r["script"] for r in got] == ["latin", "latin"]


def glob_regex(glob):
    parts = re.findall(r"\*\*|\*|\?|\\.|.", glob, flags=re.S)
    own = {"**": "(?s:.*)", "*": "[^/]*", "?": "[^/]"}
    return re.compile("".join(own.get(p) or re.escape(p[-1]) for p in parts))


def test_wildcard_automaton():
    rng = random.Random(8)
    globs = ["".join(rng.choice(["a", "b", "/", "*", "**", "?", r"\*", "."]) for _ in range(rng.randrange(1, 7))) for _ in range(60)]
    texts = ["".join(rng.choice("ab/.*") for _ in range(rng.randrange(0, 12))) for _ in range(400)]
    got = url_filter.WildcardAutomaton(globs).matches([t.encode() for t in texts])
    want = [[bool(glob_regex(g).fullmatch(t)) for g in globs] for t in texts]
    assert got.tolist() == want


def test_canonical_addresses():
    same = {
        "HTTP://me:pw@A.org:80/x/./y/../z?q=%41%2f#a.exe": "a.org/x/z?q=A%2f", "https://a.org:80": "a.org:80", "https://a.org:443/..": "a.org/", "http://a.org/a/b/..": "a.org/a/",
        "http://a.org/%7Eme/%2E%2E/b": "a.org/b", "no scheme": "", "http://a.org?x#y": "a.org?x", "http://a.org//x": "a.org//x",
    }
    assert {u: url_filter.canonical(u) for u in same} == same and url_filter.canonical(None) == ""


def test_fallback_share_is_of_bytes(spark):
    words = "plain words of prose that any vocabulary knows well enough today"
    rows = [(1, words + " 𓂀", None), (2, words, None), (3, words + " 𓂀" * 50, None), (4, "ab\nab\n\nab\n", None), (5, "x" * 200_000, None)]
    got = {r["doc_id"]: r for r in fertility_rules.judge_documents(spark, docs_frame(spark, rows)).collect()}
    n = len(words.replace(" ", ""))
    assert abs(got[1]["fallback_share"] - 4 / (n + 4)) < 1e-9 and got[2]["fallback_share"] == 0 and abs(got[3]["fallback_share"] - 200 / (n + 200)) < 1e-9
    assert got[4]["n_dup_lines"] == 2 and got[5]["n_words"] == 1 and got[5]["word_chars"] == 200_000


def test_url_verdicts(spark):
    urls = [None, "", "no scheme", "http://a.net", "http://A.Net/x", "https://example.net/en/1", "https://x.example.net/en", "http://example.com/de/a.net/", "http://notexample.com/de/", "https://b.org/fr/x?q=http://c.net/", "https://q.io/a.net/b", "https://q.io/setup.exe", "https://q.io/" + "p" * 5000]
    pages = spark.createDataFrame([(i, u, 1) for i, u in enumerate(urls)] + [(None, urls[4], 1)], "page_id long, url string, host int")
    got = {r["page_id"]: (r["host"], r["path"][:20], r["rule"], r["verdict"]) for r in url_filter.judge_urls(pages).collect()}
    assert got[0] == got[1] == got[2] == ("", "", None, "allow")
    assert got[3] == ("a.net", "", None, "allow") and got[4] == got[None] == ("a.net", "/x", "net/", "block")
    assert got[5][2:] == ("example.net/en/", "allow") and got[6][2:] == ("net/", "block")
    assert got[7][2:] == ("example.com/de/", "block") and got[8][2:] == (None, "allow") and got[9][2:] == ("org/fr/", "allow")
    assert got[10][2:] == (None, "allow") and got[11][2:] == (None, "block") and got[12][2:] == (None, "allow")
    assert url_filter.judge_urls(pages.limit(0)).count() == 0


@pytest.mark.parametrize(("axes", "bits"), [(2, 3), (3, 2)])
def test_hilbert_curve_moves_one_step_at_a_time(spark, axes, bits):
    grid = spark.range(1 << (axes * bits)).select(*[(F.shiftright("id", bits * i).bitwiseAND(F.lit((1 << bits) - 1).cast("long"))).alias(f"x{i}") for i in range(axes)])
    rows = sorted(grid.select(hilbert_shards.hilbert_index([F.col(f"x{i}") for i in range(axes)], bits).alias("h"), "*").collect())
    assert [r[0] for r in rows] == list(range(1 << (axes * bits)))
    assert all(sum(abs(a - b) for a, b in zip(p[1:], q[1:], strict=True)) == 1 for p, q in zip(rows, rows[1:], strict=False))


def test_shards(spark, nasty, nothing, tmp_path):
    rows = [(i, "t" * (i % 7), ("en", "de")[i % 2]) for i in range(100)] + NASTY
    docs = docs_frame(spark, rows)
    placed = hilbert_shards.hilbert_shards(docs)
    got = placed.collect()
    assert sorted((str(r["doc_id"]), r["size"], r["text_crc32"]) for r in got) == sorted((str(d), len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for d, t, _ in rows)
    slots = {}
    for r in got:
        slots.setdefault(r["shard"], []).append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in slots.values()) and set(slots) == set(range(16))
    assert max(map(len, slots.values())) - min(map(len, slots.values())) <= 1
    assert hilbert_shards.hilbert_shards(nothing).count() == 0
    hilbert_shards.write_shards(docs, placed, f"{tmp_path}/out")
    back = spark.read.parquet(f"{tmp_path}/out")
    assert back.count() == len(rows) and {r["own_shard"] for r in back.collect()} == {3}
    assert sorted((r["shard"], r["slot"]) for r in back.collect()) == sorted((r["shard"], r["slot"]) for r in got)
    stats = {r["shard"]: r["n_rows"] for r in hilbert_shards.shard_statistics(docs, placed).collect()}
    assert stats == {k: len(v) for k, v in slots.items()}


def plain_hilbert(axes, bits):
    """The curve by its recursion: at each bit the quadrant's number in Gray order, then the frame is turned."""
    n, x = len(axes), list(axes)
    q = 1 << (bits - 1)
    while q > 1:
        for i in range(n):
            if x[i] & q:
                x[0] ^= q - 1
            else:
                t = (x[0] ^ x[i]) & (q - 1)
                x[0] ^= t
                x[i] ^= t
        q >>= 1
    for i in range(1, n):
        x[i] ^= x[i - 1]
    t, q = 0, 1 << (bits - 1)
    while q > 1:
        if x[n - 1] & q:
            t ^= q - 1
        q >>= 1
    x = [v ^ t for v in x]
    out = 0
    for b in range(bits - 1, -1, -1):
        for v in x:
            out = out << 1 | v >> b & 1
    return out


def test_cells_and_pruning(spark):
    rng = random.Random(21)
    rows = [(i, "w " * rng.randrange(1, 60), rng.choice(["de", "en", "fr", "zz"])) for i in range(600)]
    docs = docs_frame(spark, rows).withColumn("source", F.concat(F.lit("s"), F.pmod("doc_id", F.lit(5)).cast("string")))
    grid = spark.range(512).select(*[F.shiftright("id", 3 * i).bitwiseAND(F.lit(7).cast("long")).alias(f"x{i}") for i in range(3)])
    got = grid.select("*", hilbert_shards.hilbert_index([F.col(f"x{i}") for i in range(3)], 3).alias("h")).collect()
    assert all(r["h"] == plain_hilbert([r["x0"], r["x1"], r["x2"]], 3) for r in got)
    stats = hilbert_shards.shard_statistics(docs, hilbert_shards.hilbert_shards(docs)).collect()
    for column in ("lang", "source", "size"):  # a reader that looks for one value skips files, whichever dimension it asks of
        values = ["de", "zz"] if column == "lang" else ["s0", "s4"] if column == "source" else [3, 110]
        read = [sum(r[f"min_{column}"] <= v <= r[f"max_{column}"] for r in stats) for v in values]
        assert min(read) < 16


def test_clashing_columns_and_empty_tables(spark, nasty, nothing):
    clash = nasty.selectExpr("doc_id", "text", "lang", "1 AS n_lines", "2 AS N_REMOVED", "3 AS _gone", "4 AS gone", "5 AS _did", "6 AS twice")
    out = line_runs.dedup_lines(spark, clash)
    assert out.columns == [*clash.columns, "_n_lines", "_n_removed"] and {r["n_lines"] for r in out.collect()} == {1}
    for call in (line_runs.documents_left, ngram_join.one_of_each_group):
        assert call(spark, clash).columns == clash.columns and call(spark, clash.limit(0)).count() == 0
    bench = spark.createDataFrame([(1, "another text")], "item_id long, text string")
    left = phrase_index.clean_documents(spark, clash, bench)
    assert left.columns == clash.columns and left.count() == len(NASTY) - 1
    with pytest.raises(ValueError):
        phrase_index.phrase_windows(bench, 64)


def test_a_full_lookup_keeps_words_met_again():
    asked = []
    words = Lookup(lambda w: asked.append(w) or [len(w)] * len(w), keep=10)
    words.ids(["ab", "c"])
    words.ids(["ab", *(f"n{i}" for i in range(12))])
    got = words.gather(words.ids(["ab", "c", "xyz"])).tolist()
    assert got == [2, 2, 1, 3, 3, 3]
    assert asked.count("ab") == 1 and asked.count("c") == 2


def test_short_stretches_are_segmented_as_long_ones(monkeypatch):
    rng = random.Random(5)
    segmenter = sentence_pieces.Segmenter(sentence_pieces.load_pieces())
    texts = ["".join(rng.choices("abcdeilnorst éß.#日", k=rng.randint(1, 25))) for _ in range(400)]
    short = [segmenter.segment(t) for t in texts]
    monkeypatch.setattr(sentence_pieces, "SHORT", 0)
    assert short == [segmenter.segment(t) for t in texts]
