"""The training-data operators against brute force on small fixtures, with nulls, empties, ties, copies and long texts."""

from __future__ import annotations

import html.parser
import os
import random
import re
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from factorclust.llm import chosen_path, cross_parsing, dominance_packing, edit_join, license_diagonals, onebit_ann, rendezvous, shared, suffix_decontam, token_arrow, tokens, warc_derivatives, words

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_library: dict = {}
FOLD = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def words_of(text):
    return WORD.findall((text or "").translate(FOLD))


@pytest.fixture(scope="module")
def vocab():
    return pytest.importorskip("public_tokenizers").path("byte_bpe_50k.json")


def frame(spark, texts, langs=None):
    rows = [(i, t, (langs or {}).get(i, "en"), "s", len(t or "")) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA)


def prose(n, seed=0, size=300):
    r = random.Random(seed)
    return " ".join("".join(r.choice(["ba", "ne", "ti", "ro", "su", "é"]) for _ in range(r.randint(1, 4))) for _ in range(n * size // 300))


EDGES = [None, "", "   ", "x", "A.\nB", "Ünï code space", "a " * 5000, "mit license", "MIT LICENSE mit license"]


# --- words and tokens -------------------------------------------------------------------------------------------


def test_words_match_the_pattern():
    import pyarrow as pa

    texts = [*EDGES, prose(900, size=900), "a1_b-c'd", "\x7f\x00é|z"]
    sizes = []
    for _, h, d in words.whole(pa.array(texts)):
        sizes += np.diff(d).tolist()
    assert sizes == [len(words_of(t)) for t in texts]
    one = words.hash_one([b"code", b"mit"])
    got = np.concatenate([h for _, h, _ in words.whole(pa.array(["x Code", "mit"]))])
    assert got[1] == one[0] and got[2] == one[1]


def test_long_text_is_cut_between_words():
    import pyarrow as pa

    text = "word " * 600_000
    (first, h, d), *rest = list(words.whole(pa.array([text, "tail"])))
    assert first == 0 and len(h) == 600_000 and len(set(h.tolist())) == 1 and rest[0][0] == 1


def test_token_ids_equal_the_library(vocab):
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(vocab)
    texts = [*EDGES, " a", "a ", "a  b\n c", "x\ny z", "\nabc", "a\n", "he's 9\n9 9", "<|endoftext|> x", "hello <|endoftext|> world", "a<|endoftext|>\nb  c", " <|endoftext|>", "<|endoftext| >", "w,\n\"q\" r", prose(50)] * 2
    for text, ids in zip(texts, tokens.encoder(vocab).encode_many(texts), strict=True):
        assert ids.tolist() == plain.encode(text or "", add_special_tokens=False).ids + [0]


def han(n, seed=0):
    r = random.Random(seed)
    return "".join(chr(r.randint(0x4E00, 0x9FA5)) for _ in range(n))


SPACED = st.lists(st.sampled_from([" ", "  ", "\n", "\t", "\r\n", "\u00a0", "\x00", "a", "Bc", "'s", "12", "é", "漢字", "🙂", "<|endoftext|>", "<|", "Ġ", "…", "x" * 50]), max_size=30).map("".join)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.one_of(SPACED, st.text(max_size=40).filter(lambda t: not any(0xD800 <= ord(c) < 0xE000 for c in t))), min_size=1, max_size=6))
def test_ids_of_any_texts_equal_an_untouched_library(texts):
    from tokenizers import Tokenizer

    path = pytest.importorskip("public_tokenizers").path("byte_bpe_50k.json")
    _library.setdefault(path, Tokenizer.from_file(path))
    for text, ids in zip(texts, tokens.encoder(path).encode_many(texts), strict=True):
        assert ids.tolist() == _library[path].encode(text, add_special_tokens=False).ids + [0]


def test_forgetting_words_changes_nothing(vocab, monkeypatch):
    monkeypatch.setattr(tokens, "REMEMBERED", 20)
    monkeypatch.setattr(tokens, "BATCH", 400)
    texts = [prose(80, s) for s in range(6)]
    e = tokens.Encoder(vocab)
    assert [x.tolist() for x in e.encode_many(texts)] == [x.tolist() for x in tokens.encoder(vocab).encode_many(texts)]


def test_pieces_of_more_than_65535_ids_are_whole(vocab):
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(vocab)
    r = random.Random(3)
    run = "".join(r.choices("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", k=150_000))
    texts = [run, f"a {run[::-1]} b", han(40_000), han(70_000, 1) + " y", run * 2, "a b"]
    for text, ids in zip(texts, tokens.Encoder(vocab).encode_many(texts), strict=True):
        want = plain.encode(text, add_special_tokens=False).ids + [0]
        assert ids.tolist() == want and (text == "a b" or len(want) > 65_536)


# --- shared -----------------------------------------------------------------------------------------------------


def test_gapless_numbers_and_components(spark):
    df = spark.range(1000).select((F.col("id") % 3).alias("g"), "id")
    got = shared.gapless(df, ["g"], ["id"], "k", 7).groupBy("g").agg(F.min("k").alias("lo"), F.max("k").alias("hi"), F.countDistinct("k").alias("n")).collect()
    assert all(r.lo == 0 and r.hi == r.n - 1 for r in got)
    chain = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (7, 7)], "a long, b long")
    comp = {r.node: r.comp for r in shared.components(chain).collect()}
    assert all(comp[i] == 0 for i in range(41)) and comp[101] == 100
    assert shared.components(chain.limit(0)).count() == 0


# --- op1 --------------------------------------------------------------------------------------------------------


def test_neighbours_equal_brute_force(spark):
    rng = np.random.default_rng(1)
    x = rng.standard_normal((1500, 16)).astype(np.float32)
    x[10:60] = x[10]  # copies: ties
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(2000, None), (2100, [0.0] * 16), (2200, [float("nan")] * 16), (2300, [1.0, 2.0]), (2400, [None] * 16)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = onebit_ann.nearest(df, F.col("vec_id") % 100 == 0).toPandas()
    hits = 0
    y = x.astype(float)
    for q in range(0, 1500, 100):
        s = np.sqrt(((y - y[q]) ** 2).sum(1))
        s[q] = np.inf
        want = np.lexsort((np.arange(1500), s))[:10]
        mine = got[got.query_id == q].sort_values("rank")
        hits += len(set(mine.vec_id) & set(want))
        assert mine["rank"].tolist() == list(range(1, 11)) and np.allclose(mine.score, s[mine.vec_id])
    assert hits >= 0.98 * 150 and got.query_id.max() < 2000
    assert onebit_ann.nearest(df.limit(0), F.lit(True)).count() == 0
    assert onebit_ann.nearest(df.where("vec_id < 4"), F.col("vec_id") == 0).count() == 3


def test_repeated_rows_widths_and_clashing_names(spark):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((60, 9)).astype(np.float32)
    rows = [(i, v.tolist(), 7) for i, v in enumerate(x)]
    rows += [rows[0], (0, x[5].tolist(), 1), (None, x[1].tolist(), 1)]  # an id seen three times, two rows of them equal
    rows += [(200 + i, [float(i + 1), 1.0, float(i % 3)], 2) for i in range(15)] + [(400, [1.0], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, row int")
    got = onebit_ann.nearest(df, F.col("vec_id") % 100 == 0)
    live = [(i, np.array(v)) for i, v, _ in rows if i is not None]
    want = []
    for a, (i, v) in enumerate(live):
        if i % 100 == 0:
            near = sorted((float(np.sqrt(((v - w) ** 2).sum())), j) for b, (j, w) in enumerate(live) if b != a and len(w) == len(v))[:10]
            want += [(i, r, j, round(s, 9)) for r, (s, j) in enumerate(near, 1)]
    assert sorted((r.query_id, r.rank, r.vec_id, round(r.score, 9)) for r in got.collect()) == sorted(want)


@pytest.mark.parametrize("d", [3, 64, 100])
def test_bounds_hold_and_codes_are_bits(d):
    rng = np.random.default_rng(d)
    x, q = rng.standard_normal((400, d)) + 0.3, rng.standard_normal((20, d))
    mean, turn = x.mean(0), onebit_ann.rotation(d, 1)
    codes, length, inner = onebit_ann.encode(x, mean, turn)
    assert codes.dtype == np.uint64 and codes.shape == (400, -(-d // 64))
    low, high = onebit_ann.bounds(codes, length, inner, onebit_ann.Queries(q, mean, turn), slice(None), 3.0)
    true = ((q[:, None, :] - x[None, :, :]) ** 2).sum(2)
    assert ((low <= true) & (true <= high)).mean() > 0.99


# --- op2, op10 --------------------------------------------------------------------------------------------------


def test_arrow_files_round_trip(spark, vocab):
    texts = [*EDGES, *[prose(400, s) for s in range(20)], prose(3000, 5)]
    from tokenizers import Tokenizer

    texts += ["hello <|endoftext|> world", han(45_000, 2), "x " + "Zm9v" * 30_000]
    plain = Tokenizer.from_file(vocab)
    got = token_arrow.round_trip(frame(spark, texts), vocab, length=64).orderBy("doc_id").collect()
    at = 0
    for r, text in zip(got, texts, strict=True):
        ids = np.array([*plain.encode(text or "", add_special_tokens=False).ids, 0])
        assert (r.start, r.n_tokens, r.ids_crc32) == (at, len(ids), zlib.crc32(ids.astype("<u4").tobytes()))
        at += len(ids)
    assert token_arrow.round_trip(frame(spark, []), vocab).count() == 0


def test_arrow_rows_are_views_with_masks(spark, vocab):
    m = token_arrow.write(frame(spark, ["a b c", "d e"]), vocab, shared.fresh_path(spark, "t"), length=8, shards=1).collect()
    reader = token_arrow.open_reader(m[0].uri)
    ids, mask = reader.row(0)
    assert mask.sum() == m[0].tokens == 7 and ids.base is not None and ids[:4].tolist()[-1] == 0


def check_packing(pieces, room):
    bins: dict = {}
    for size, seq, off in pieces:
        bins.setdefault(seq, []).append((off, size))
    for b in bins.values():
        at = 0
        for off, size in sorted(b):
            assert off == at
            at += size
        assert at <= room
    return len(bins)


def expand(plan):
    out = []
    for size, _, bins, first, offset, rounds in plan.rows:
        out += [(size, first + i, offset + k * size) for k in range(rounds) for i in range(bins)]
    return out


@pytest.mark.parametrize("seed", range(25))
def test_packing_is_valid_and_near_the_bound(seed):
    r = random.Random(seed)
    room = r.choice([7, 12, 30, 100])
    counts = {s: r.randint(1, 9) for s in r.sample(range(1, room + 1), r.randint(1, min(room, 12)))}
    plan = dominance_packing.make_plan(counts, room)
    pieces = expand(plan)
    assert {s: sum(1 for p in pieces if p[0] == s) for s in counts} == counts
    n = check_packing(pieces, room)
    assert plan.lower_bound <= n <= plan.lower_bound * 1.25 + 1


@pytest.mark.parametrize("seed", range(40))
def test_reduction_keeps_an_optimum(seed):
    """Small instances: fixed bins plus the best packing of the rest are no more than the best packing of all."""
    r = random.Random(seed)
    room = 12
    items = sorted((r.randint(1, room) for _ in range(8)), reverse=True)

    def best(left):
        low = [len(left)]

        def go(i, free):
            if len(free) >= low[0]:
                return
            if i == len(left):
                low[0] = len(free)
                return
            for j in range(len(free)):
                if free[j] >= left[i]:
                    go(i + 1, free[:j] + [free[j] - left[i]] + free[j + 1 :])
            go(i + 1, [*free, room - left[i]])

        go(0, [])
        return low[0]

    have = np.bincount(items, minlength=room + 1)
    plan = dominance_packing.Plan(room)
    left = dominance_packing.reduce_instance(have, plan)
    rest = [s for s in range(room, 0, -1) for _ in range(int(left[s]))]
    assert plan.fixed_bins + best(rest) == best(items)


@pytest.mark.parametrize("seed", range(6))
def test_the_plan_does_not_grow_with_the_counts(seed):
    r = random.Random(seed)
    room = 2048
    sizes = [[1500, 500], [1500, 540, 7], [900, 700, 400, 10], r.sample(range(1, room), 12), r.sample(range(600, room), 300), list(range(1, room + 1))][seed]
    rows = {n: len(dominance_packing.make_plan({s: n + s % 7 for s in sizes}, room).rows) for n in (1_000, 1_000_000, 1_000_000_000)}
    assert rows[1_000_000_000] <= 40 * len(sizes) + 40 and rows[1_000_000_000] <= rows[1_000] + 40 * len(sizes)


def test_repeating_a_choice_changes_nothing(monkeypatch):
    for seed in range(30):
        r = random.Random(seed)
        room = r.choice([12, 30, 64])
        counts = {s: r.randint(1, 40) for s in r.sample(range(1, room + 1), r.randint(2, 9))}
        fast = dominance_packing.make_plan(counts, room)
        with monkeypatch.context() as m:
            m.setattr(dominance_packing, "STEADY", 1 << 40)  # one choice at a time
            slow = dominance_packing.make_plan(counts, room)
        assert (fast.bins, fast.fixed_bins) == (slow.bins, slow.fixed_bins)


def test_sequences_hold_the_ids_of_their_pieces(spark, vocab):
    texts = [*EDGES, prose(3000, 1, 300)]
    packed = dominance_packing.pack(frame(spark, texts), vocab, room=64, with_ids=True)
    rows = packed.collect()
    seqs = {r.sequence_id: r for r in dominance_packing.sequences(packed).collect()}
    for i, ids in enumerate(tokens.encoder(vocab).encode_many(texts)):
        mine = sorted((r for r in rows if r.doc_id == i), key=lambda r: r.piece)
        assert [x for r in mine for x in seqs[r.sequence_id].ids[r.offset : r.offset + r.length]] == ids.tolist()
    assert all(len(r.ids) <= 64 for r in seqs.values()) and sum(len(r.ids) for r in seqs.values()) == sum(r.length for r in rows)


def test_documents_are_packed_whole(spark, vocab):
    texts = [*EDGES, *[prose(500, s) for s in range(15)], prose(9000, 3, 900)]
    got = dominance_packing.pack(frame(spark, texts), vocab).toPandas()
    check_packing(list(zip(got.length, got.sequence_id, got.offset, strict=True)), 2048)
    for i, ids in enumerate(tokens.encoder(vocab).encode_many(texts)):
        mine = got[got.doc_id == i].sort_values("piece")
        assert mine.length.sum() == len(ids) and mine.start.tolist() == [0, *np.cumsum(mine.length)[:-1]] and (mine.length[1:] == 2048).all()
        assert mine.ids_crc32.tolist() == [zlib.crc32(ids[s : s + n].astype("<u4").tobytes()) for s, n in zip(mine.start, mine.length, strict=True)]
    assert dominance_packing.pack(frame(spark, []), vocab).count() == 0


# --- op3 --------------------------------------------------------------------------------------------------------


def near_copies():
    base = [prose(300, s) for s in range(12)]
    out = list(base)
    r = random.Random(5)
    for t in base[:6]:
        w = t.split(" ")
        for _ in range(4):
            c = list(w)
            for _ in range(r.randint(0, 4)):
                c[r.randrange(len(c))] = "zz" + str(r.randrange(9))
            out.append(" ".join(c))
    out += [base[0]] * 150  # a large group of copies
    hot = base[1].split(" ")
    for i in range(130):  # a large group of near copies, above a leaf
        out.append(" ".join([*hot[:i], "qq" + str(i), *hot[i + 1 :]]))
    return [*out, None, "", "one two", "one two", "one two three"]


def test_classes_equal_brute_force(spark):
    texts = near_copies()
    sets = []
    for t in texts:
        w = words_of(t)
        sets.append(frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset())
    parent = list(range(len(texts)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    links = [0] * len(texts)
    for i in range(len(texts)):
        for j in range(i):
            if sets[i] and sets[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) - 1e-9:
                links[i] += 1
                links[j] += 1
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    got = {r.doc_id: r for r in chosen_path.join(frame(spark, texts)).collect()}
    assert [got[i].class_id for i in range(len(texts))] == [find(i) for i in range(len(texts))]
    assert [got[i].n_links for i in range(len(texts))] == links
    kept = sorted(r.doc_id for r in chosen_path.keep_first(frame(spark, texts)).collect())
    assert kept == [i for i in range(len(texts)) if find(i) == i]
    assert chosen_path.join(frame(spark, [])).count() == 0


@pytest.mark.parametrize("common,union", [(4, 5), (8, 10), (16, 20), (40, 50), (200, 250)])
def test_sparse_sets_share_paths_as_often_as_claimed(common, union):
    runs = chosen_path.runs_for(chosen_path.RECALL, 0.8, sum(chosen_path.LEVELS))
    orders = chosen_path.chosen_orders(runs, sum(chosen_path.LEVELS))
    rng = np.random.default_rng(union)
    missed = 0
    for _ in range(4000):
        u = rng.integers(0, 1 << 63, union, dtype=np.uint64) * np.uint64(2)
        a, b = (chosen_path.path_keys(np.sort(x), orders)[:, -1] for x in (u[:common], u))
        missed += not (a == b).any()
    assert missed <= 16  # 0.4%; 0.16% are expected


def test_short_hot_documents_meet_as_claimed(spark):
    line = "one two three four five six seven eight"
    texts = [line, *[f"{line} w{i}" for i in range(1000)]]
    got = {r.doc_id: r for r in chosen_path.join(frame(spark, texts)).collect()}
    # by brute force each of the thousand shares 4 of 5 shingles with the line, and 4 of 6 with the others
    met = sum(got[i].class_id == 0 and got[i].n_links == 1 for i in range(1, 1001))
    assert met >= 995 and got[0].n_links == met
    assert all(got[i].n_links <= 1 for i in range(1, 1001))


def test_rows_without_doc_id_stay_and_columns_may_clash(spark):
    df = spark.createDataFrame([(None, "a b c d e f", 1), (None, None, 2), (3, "a b c d e f", 3)], "doc_id long, text string, row long")
    twice = df.unionByName(df)
    assert sorted((r.doc_id or -1, r.row) for r in chosen_path.keep_first(twice).collect()) == [(-1, 1), (-1, 1), (-1, 2), (-1, 2), (3, 3)]
    got = chosen_path.join(df).collect()
    assert sorted((r.doc_id or -1, r.class_id or -1, r.n_links) for r in got) == [(-1, -1, 0), (-1, -1, 0), (3, 3, 0)]
    assert chosen_path.keep_first(df).count() == 3 and chosen_path.keep_first(df).columns == ["doc_id", "text", "row"]


# --- op4 --------------------------------------------------------------------------------------------------------


def test_license_phrases_are_counted_where_they_stand(spark):
    texts = [*EDGES, "Under the MIT-License, or the Apache License; the GNU General Public License. mit license", "general  public\nlicense mit", prose(900, 1, 900) + " released under the mit license", "permission is hereby granted free of charge to ANY person obtaining one copy of this software and associated documentation files"]
    phrases = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
    got = {r.doc_id: r for r in license_diagonals.scan(frame(spark, texts)).collect()}
    for i, t in enumerate(texts):
        w = words_of(t)
        at = [(j, lab) for p, lab in phrases.items() for j in range(len(w)) if w[j : j + len(p.split())] == p.split()]
        r = got[i]
        assert (r.n_words, r.n_base, r.base_labels) == (len(w), len(at), ",".join(sorted({x for _, x in at})))
        assert (r.first_word, r.last_word) == ((min(at)[0], max(at)[0]) if at else (None, None))
    assert "mit-notice" in got[len(EDGES) + 2].labels and got[len(EDGES) + 3].labels == "mit-notice" and got[len(EDGES) + 3].score < 1
    assert license_diagonals.scan(frame(spark, [])).count() == 0


def edits(have, want):
    """Least edits that make ``want`` of any stretch of ``have``."""
    row = list(range(len(want) + 1))
    low = row[-1]
    for w in have:
        new = [0]
        for j, t in enumerate(want):
            new.append(min(row[j] + (w != t), row[j + 1] + 1, new[j] + 1))
        row, low = new, min(low, new[-1])
    return low


def test_notices_are_scored_as_brute_force_does(spark):
    r = random.Random(8)
    notices = [t for t in license_diagonals.TEMPLATES if not t.base]
    texts = [None, "", prose(300, 2)]
    for t in notices:
        for rate in (0, 0.05, 0.15, 0.3, 0.5):
            w = []
            for x in t.text.split():
                if r.random() >= rate / 2:
                    w.append(x)
                w += ["zork"] * (r.random() < rate)
            texts.append(f"{prose(200, r.randrange(99))} {' '.join(w).upper()}. {prose(100, r.randrange(99))}")
    w = notices[1].text.split()
    texts.append(" ".join(x for i in range(0, len(w), 2) for x in [*w[i : i + 2], "a1", "b2", "c3"]))  # three foreign words after every two
    texts.append(" ".join([notices[0].text] * 50))
    texts.append("released under " * 3000 + notices[0].text)
    got = {x.doc_id: x for x in license_diagonals.scan(frame(spark, texts)).collect()}
    for i, text in enumerate(texts):
        have = words_of(text)
        want = {}
        for t in notices:
            score = 1 - edits(have, t.text.replace(".", " ").split()) / len(t.text.replace(".", " ").split())
            if score >= license_diagonals.SHARE:
                want[t.label] = max(score, want.get(t.label, 0))
        mine = set(got[i].labels.split(",")) - set(got[i].base_labels.split(",")) - {""}
        assert mine == set(want), (i, text)
        assert abs(got[i].score - max([1.0] * bool(got[i].n_base) + list(want.values()), default=0.0)) < 1e-12
    assert not got[len(texts) - 3].labels


def test_spans_say_where_notices_stand(spark):
    text = "x y Released under THE mit License z released under a the mit license"
    got = license_diagonals.spans(frame(spark, [text, "q"])).orderBy("first").collect()
    assert [(x.label, x.first, x.last, round(x.score, 3)) for x in got] == [("mit-notice", 2, 6, 1.0), ("mit", 5, 6, 1.0), ("mit", 12, 13, 1.0)]


def test_bands_are_shuffled_beyond_the_bound(spark, monkeypatch):
    df = frame(spark, [*EDGES, "released under the mit license " * 3])
    want = sorted(map(str, license_diagonals.scan(df).collect()))
    monkeypatch.setattr(license_diagonals, "BROADCAST_BANDS", 0)
    assert sorted(map(str, license_diagonals.scan(df).collect())) == want


def test_repeated_rows_do_not_vote_twice(spark):
    df = spark.createDataFrame([(1, "mit license"), (1, "mit license")], "doc_id long, text string")
    assert [r.n_base for r in license_diagonals.scan(df).collect()] == [1, 1]


# --- op5 --------------------------------------------------------------------------------------------------------


def test_warc_derivatives_link_back(spark):
    rows = [(1, "http://a/x", "<html><head><title>T &amp; U</title></head><body><p>One <b>two</b></p><script>no()</script><a href='/l?a=1&amp;b=2'>go</a></body></html>"), (2, None, None), (None, "http://b\r\nX: y", "<p>é"), (3, "", "")]
    got = warc_derivatives.build(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert len(got) == 8 and all(r.digest_ok for r in got)
    one = {r.record_type: r for r in got if r.page_id == 1}
    assert one["metadata"].refers_to == one["conversion"].refers_to
    assert one["conversion"].block == "One two\ngo" and '"T & U"' in one["metadata"].block and "/l?a=1&b=2" in one["metadata"].block
    assert {r.target_uri for r in got if r.page_id == 2} == {"urn:page:2"}
    assert warc_derivatives.build(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


class PlainReader(html.parser.HTMLParser):
    """Visible text, title and links by the library's parser, for pages that close what they open."""

    def __init__(self, page):
        super().__init__()
        self.out, self.hidden, self.title, self.links, self.inside = [], 0, None, [], False
        self.feed(page)
        self.close()
        lines = [" ".join(x.split()) for x in "".join(self.out).split("\n")]
        self.text = "\n".join(x for x in lines if x)

    def handle_starttag(self, tag, attrs):
        if tag in warc_derivatives.BLOCKS and not self.hidden:
            self.out.append("\n")
        self.hidden += tag in warc_derivatives.HIDDEN
        self.inside = tag == "title"
        if tag == "a" and not self.hidden and dict(attrs).get("href") is not None:
            self.links.append(dict(attrs)["href"])

    def handle_endtag(self, tag):
        self.hidden -= tag in warc_derivatives.HIDDEN
        if tag in warc_derivatives.BLOCKS and not self.hidden:
            self.out.append("\n")
        if tag in warc_derivatives.HIDDEN:
            self.out.append(" ")
        self.inside = False

    def handle_comment(self, data):
        self.out.append(" " * (not self.hidden))

    def handle_data(self, data):
        if self.inside and self.title is None:
            self.title = " ".join(data.split())
        if not self.hidden:
            self.out.append(data)


def test_derivatives_equal_brute_force(spark, small):
    import base64
    import hashlib
    import json

    pages = spark.read.parquet(f"{small}/pages.parquet")
    got = {(r.page_id, r.record_type): r for r in warc_derivatives.build(pages).collect()}
    rows = pages.collect()
    assert len(got) == 2 * len(rows)
    sha = lambda data: "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()
    for r in rows:
        want, meta, text = PlainReader(r.html), got[r.page_id, "metadata"], got[r.page_id, "conversion"]
        assert text.block == want.text, r.page_id
        inner = json.loads(meta.block)
        assert inner["html"] == {"title": want.title, "links": want.links} and inner["warc"]["WARC-Record-ID"] == meta.refers_to == text.refers_to
        assert inner["http"]["status"] == "HTTP/1.1 200 OK" and inner["http"]["headers"]["Content-Length"] == str(len(r.html.encode()))
        for x in (meta, text):
            assert x.target_uri == r.url and x.source_digest == sha(r.html.encode()) and x.block_digest == sha(x.block.encode()) and x.content_length == len(x.block.encode())


def test_references_resolve_and_ids_are_unique(spark):
    rows = [(1, "http://a", "<p>x"), (1, "http://a", "<p>x"), (1, "http://a", "<p>y"), (2, None, None), (None, None, "z")] * 3
    files = warc_derivatives.write(spark.createDataFrame(rows, "page_id long, url string, html string"), shared.fresh_path(spark, "w"))
    sources = {}
    for f in files.collect():
        with open(f.responses.removeprefix("file:").replace("///", "/"), "rb") as g:
            sources |= {r.headers["WARC-Record-ID"]: r for r in warc_derivatives.load(g)}
    got = warc_derivatives.read(files).collect()
    assert len(sources) == len(rows) and len({r.record_id for r in got} | set(sources)) == 3 * len(rows)
    assert all(sources[r.refers_to].headers["WARC-Payload-Digest"] == r.source_digest and sources[r.refers_to].kind == "response" for r in got)


@pytest.mark.parametrize("page,text", [
    ("if a < b and c > d", "if a < b and c > d"), ("x<script>var a = 1;", "x"), ("a<!-- b", "a"), ("a<noscript>b", "a\nb".replace("\n", "")), ("1 <2> 3", "1 <2> 3"),
    ("a<b title='>'>c</b>", "ac"), ("a<p title=\"x", "a"), ("<title>t &amp; u</title>b", "t & u\nb"), ("a</ x>b<!doctype y>c<?php z?>d", "abcd"), ("<", "<"), ("&lt;p&gt;", "<p>"),
    ("<SCRIPT>x</ScRiPt >y", "y"), ("<script>'</p>' </scripty> </script>z", "z"),
])
def test_broken_pages_are_read(page, text):
    assert warc_derivatives.read_page(page).text == text


@pytest.mark.parametrize("part", ["<script>", "<noscript>", "<a href=\"", "<!--", "</", "<b '", "<template><head>", "<", "&", "<title>"])
def test_very_long_broken_pages_take_linear_time(part):
    import time

    began = time.perf_counter()
    warc_derivatives.read_page(part * 200_000)
    assert time.perf_counter() - began < 5


def test_a_record_cut_short_is_told():
    import gzip
    import io

    whole = gzip.decompress(warc_derivatives.dump(warc_derivatives.response(1, "u", "body")))
    assert [r.kind for r in warc_derivatives.load(io.BytesIO(gzip.compress(whole)))] == ["response"]
    with pytest.raises(ValueError, match="short"):
        list(warc_derivatives.load(io.BytesIO(gzip.compress(whole[:-6]))))


# --- op6 --------------------------------------------------------------------------------------------------------


def test_windows_equal_brute_force(spark):
    items = [(1, prose(60, 50)), (2, "short one here"), (3, None), (4, ""), (10, prose(30, 51)), (5, "solo")]
    long = words_of(items[0][1])
    texts = [*EDGES, prose(300, 1) + " " + " ".join(long[5:19]) + " " + prose(20, 2), "a SHORT, one here b", " ".join(long), "solo " * 3, " ".join(long[:12]), prose(400, 3) + " solo"]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {r.doc_id: r for r in suffix_decontam.report(frame(spark, texts), bench).collect()}
    import hashlib

    for i, t in enumerate(texts):
        w = words_of(t)
        hit, names = set(), set()
        for name, x in items:
            v = words_of(x)
            k = min(13, len(v))
            for a in range(len(v) - k + 1) if v else ():
                for b in range(len(w) - k + 1):
                    if w[b : b + k] == v[a : a + k]:
                        hit |= set(range(b, b + k))
                        names.add(str(name))
        r = got[i]
        assert (r.n_words, r.n_hit, r.n_items, r.contaminated) == (len(w), len(hit), len(names), bool(hit) and 20 * len(hit) >= len(w))
        assert r.items_sha256 == hashlib.sha256(",".join(sorted(names)).encode()).hexdigest()
    best = {x.item_id: x.words for r in suffix_decontam.matches(frame(spark, texts), bench).where("doc_id = 9").collect() for x in r.longest}
    assert best == {"1": 14}
    kept = {r.doc_id for r in suffix_decontam.decontaminate(frame(spark, texts), bench).collect()}
    assert kept == {i for i in range(len(texts)) if not got[i].contaminated}
    assert suffix_decontam.report(frame(spark, texts), bench.limit(0)).where("n_hit > 0").count() == 0


@pytest.mark.parametrize("shard", [1 << 18, 40])
def test_many_blocks_and_shards_change_nothing(spark, monkeypatch, shard):
    r = random.Random(6)
    items = [(i % 9, prose(r.randint(1, 40), 100 + i)) for i in range(14)] + [(3, "one two"), (4, None)]
    texts = [*EDGES, "one two one two", *[prose(50, k) + " " + " ".join(words_of(r.choice(items[:14])[1])[r.randint(0, 9) :]) + " " + prose(9, k + 1) for k in range(30)]]
    texts += [texts[-1], " ".join(t or "" for _, t in items)]
    df, bench = frame(spark, texts), spark.createDataFrame(items, "item_id long, text string")
    df = df.withColumn("text_hash", F.lit(1)).withColumn("hits", F.lit(2))
    tell = lambda: sorted(map(str, suffix_decontam.matches(df, bench, 5).collect()))
    kept = lambda: sorted(x.doc_id for x in suffix_decontam.decontaminate(df, bench, 5).collect())
    want, stays = tell(), kept()
    assert len(stays) < len(texts)
    monkeypatch.setattr(suffix_decontam, "SHARD", shard)
    monkeypatch.setattr(suffix_decontam, "BLOCK", 200)
    assert len(list(suffix_decontam.load_items(bench, 5))) > 3
    assert tell() == want and kept() == stays
    assert suffix_decontam.decontaminate(df, bench, 5).columns == df.columns


# --- op7 --------------------------------------------------------------------------------------------------------


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        prev, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            prev, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, prev + (x != y))
    return row[-1]


@pytest.mark.parametrize("threshold", [1, 2, 3])
def test_bit_parallel_distance(spark, threshold):
    r = random.Random(threshold)
    pairs = [("", ""), ("", "a"), ("abc", ""), ("é€x", "é€y"), ("abcd" * 40, "abcd" * 39 + "bcd")]
    for _ in range(150):
        a = "".join(r.choice("abé") for _ in range(r.randint(0, 12)))
        b = list(a)
        for _ in range(r.randint(0, threshold + 1)):
            k = r.randint(0, len(b))
            b[k : k + r.randint(0, 1)] = r.choice(["", "a", "é"])
        pairs.append((a, "".join(b)))
    got = spark.createDataFrame(pairs, "a string, b string").withColumn("d", edit_join.edit_distance(F.col("a"), F.col("b"), threshold)).collect()
    for x in got:
        d = distance(x.a, x.b)
        assert x.d == (d if d <= threshold else None), (x.a, x.b)


@pytest.mark.parametrize("threshold", [1, 2])
def test_similar_lines_equal_brute_force(spark, threshold):
    r = random.Random(9 + threshold)
    base = ["".join(r.choice("abcdefgh é") for _ in range(r.randint(18, 40))).strip() for _ in range(25)]
    lines = set(base)
    for x in base:
        for _ in range(3):
            b = list(x)
            for _ in range(r.randint(1, threshold + 1)):
                k = r.randrange(len(b))
                b[k : k + r.randint(0, 1)] = [r.choice(["", "a", "zz"])]
            lines.add("".join(b).strip())
    lines = sorted(x for x in lines if x)
    df = spark.createDataFrame([(0, 0, i, x) for i, x in enumerate(lines)], "row long, doc long, at int, line string").withColumn("id", F.xxhash64("line"))
    name = {r.id: r.line for r in df.collect()}
    got = {frozenset((name[p.a], name[p.b])) for p in edit_join.similar(df, threshold, 16).collect()}
    want = {frozenset((a, b)) for a in lines for b in lines if a < b and min(len(a), len(b)) >= 16 and distance(a, b) <= threshold}
    assert got == want


def test_thresholds_grow_with_the_length(spark):
    r = random.Random(4)
    lines = set()
    for n in (20, 61, 63, 64, 65, 125, 127, 128, 160):
        x = "".join(r.choice("abcdefgh é") for _ in range(n - 2))
        lines.add(f"<{x}>")
        for _ in range(6):
            b = list(x)
            for _ in range(r.randint(1, 4)):
                k = r.randrange(len(b))
                b[k : k + r.randint(0, 1)] = [r.choice(["", "a", "z"])]
            lines.add("<" + "".join(b) + ">")
    lines = sorted(lines)
    df = spark.createDataFrame([(0, 0, i, x) for i, x in enumerate(lines)], "row long, doc long, at int, line string").withColumn("id", F.xxhash64("line"))
    name = {x.id: x.line for x in df.collect()}
    got = sorted(tuple(sorted((name[p.a], name[p.b]))) for p in edit_join.similar(df, edit_join.GROWN).collect())
    edits = lambda n: max(e for at, e in edit_join.GROWN if n >= at)
    apart = {(a, b): distance(a, b) for a in lines for b in lines if a < b and abs(len(a) - len(b)) <= 3}
    assert got == sorted(p for p, d in apart.items() if d <= edits(min(map(len, p))))
    assert any(apart[p] == 3 for p in got)


def test_only_first_lines_stay(spark):
    texts = ["first line of all documents\nunique one here\n\nshort", "first line of all document\nshort\n\nother text stays here", None, "", "first line of all documents", "  short  \nshort"]
    got = {r.doc_id: r for r in edit_join.dedup(frame(spark, texts)).collect()}
    assert [got[i].text for i in range(6)] == [texts[0], "\nother text stays here", None, "", "", ""]
    assert [got[i].n_removed for i in range(6)] == [0, 2, 0, 0, 1, 2]
    assert edit_join.dedup(frame(spark, [])).count() == 0


@pytest.mark.parametrize("threshold", [1, 2])
def test_crowds_lose_no_pair(spark, monkeypatch, threshold):
    monkeypatch.setattr(edit_join, "CROWD", 4)
    r = random.Random(threshold)
    head, tail = "the common beginning of many lines, ", " and their common end of it"
    lines = {head + f"{r.randrange(10**5):05d}" + tail for _ in range(150)}
    lines |= {f"{r.randrange(10**4):04d} é" + tail + tail for _ in range(60)} | {head + head + f"{r.randrange(50)}" for _ in range(30)}
    for x in list(lines)[:80]:
        k = r.randrange(len(x))
        lines.add((x[:k] + r.choice(["", "é", "q"]) + x[k + r.randint(0, 1) :]).strip())
    lines = sorted(lines)
    df = spark.createDataFrame([(0, 0, i, x) for i, x in enumerate(lines)], "row long, doc long, at int, line string").withColumn("id", F.xxhash64("line"))
    name = {x.id: x.line for x in df.collect()}
    got = sorted(tuple(sorted((name[p.a], name[p.b]))) for p in edit_join.similar(df, threshold, 16).collect())

    def near(a, b):
        if abs(len(a) - len(b)) > threshold:
            return False
        i = next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))
        j = next((j for j, (x, y) in enumerate(zip(a[i:][::-1], b[i:][::-1], strict=False)) if x != y), min(len(a), len(b)) - i)
        return distance(a[i : len(a) - j], b[i : len(b) - j]) <= threshold

    assert got == sorted((a, b) for a in lines for b in lines if a < b and near(a, b))


def test_near_copies_that_differ_in_places_make_few_pairs(spark, monkeypatch):
    made, whole = [], edit_join.cut

    def counted(df, what="cut"):
        out = whole(df, what)
        if what == "pairs":
            made.append(out.count())
        return out

    monkeypatch.setattr(edit_join, "cut", counted)
    r = random.Random(5)
    word = lambda: "".join(r.choice("etaoinshrdl") for _ in range(7))
    base = [word() for _ in range(50)]
    lines = {" ".join(base)}
    for i in range(160):
        copy = list(base)
        for _ in range(1 + i % 2):
            copy[r.randrange(50)] = word()
        lines.add(" ".join(copy))
    for x in sorted(lines)[:40]:
        for _ in range(2):
            k = r.randrange(len(x))
            x = (x[:k] + r.choice(["", "é", "qq"]) + x[k + r.randint(0, 1) :]).strip()
            lines.add(x)
    lines = sorted(lines)
    df = spark.createDataFrame([(0, 0, i, x) for i, x in enumerate(lines)], "row long, doc long, at int, line string").withColumn("id", F.xxhash64("line"))
    name = {x.id: x.line for x in df.collect()}
    got = {tuple(sorted((name[p.a], name[p.b]))) for p in edit_join.similar(df, 3).collect()}
    df.select("line").createOrReplaceTempView("near_lines")
    want = spark.sql("select a.line as a, b.line as b from near_lines a join near_lines b on a.line < b.line and levenshtein(a.line, b.line) <= 3").collect()
    assert got == {(p.a, p.b) for p in want}
    assert sum(made) < len(lines) ** 2 / 40  # 1,120 of 230 lines; 7,260 where all that share a segment met


def test_texts_of_crowds_move_once(spark, monkeypatch):
    """Only the crowd's own texts leave their scan, and each joined row is of numbers alone."""
    plans, columns, whole = [], {}, edit_join.cut

    def seen(df, what="cut"):
        if what == "crowded-lines":
            plans.append(df._jdf.queryExecution().executedPlan().toString())
        columns.setdefault(what, set()).update(t for _, t in df.dtypes)
        return whole(df, what)

    monkeypatch.setattr(edit_join, "cut", seen)
    lines = [f"one beginning that many lines have in common, {i:03d}" for i in range(40)] + [f"{i * 7919:09d} of a line apart from all others {i * 104729:09d}" for i in range(40)]
    df = spark.createDataFrame([(0, 0, i, x) for i, x in enumerate(lines)], "row long, doc long, at int, line string").withColumn("id", F.xxhash64("line"))
    limit = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # as on tables that are large
    try:
        assert edit_join.similar(df, 1).count()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
    assert plans and all("SortMergeJoin" not in p for p in plans)
    assert "string" not in columns["placed"] and columns["places"] == {"bigint", "int"}


def test_white_space_and_clashing_names(spark):
    rows = [(1, "short line\nsecond line of it", 7, 8, 9), (2, "short line\t\n\tsecond line of it\r\n \t\nnew", 7, 8, 9), (3, "x" * 200_000 + "\nshort line", 7, 8, 9)]
    df = spark.createDataFrame(rows, "doc_id long, text string, row int, gone int, n_removed int")
    got = {r.doc_id: r for r in edit_join.dedup(df, blank=edit_join.WHITE, counts=("lines", "went")).collect()}
    assert [got[i].text for i in (1, 2, 3)] == [rows[0][1], " \t\nnew", "x" * 200_000]
    assert all((r.row, r.gone, r.n_removed) == (7, 8, 9) for r in got.values()) and [got[i].went for i in (1, 2, 3)] == [0, 2, 1]
    plain = edit_join.dedup(df)
    assert plain.columns == ["doc_id", "text", "row", "gone", "n_lines", "n_removed"]
    assert {r.doc_id: r.n_removed for r in plain.collect()} == {1: 0, 2: 0, 3: 1}


def test_line_dedup_is_native(spark):
    plans = []
    DataFrame = type(spark.range(1))  # noqa: N806
    real = DataFrame.write.fget
    try:
        DataFrame.write = property(lambda self: (plans.append(self._jdf.queryExecution().executedPlan().toString()), real(self))[1])
        plans.append(edit_join.dedup(frame(spark, ["a\nb", "a"]))._jdf.queryExecution().executedPlan().toString())
    finally:
        DataFrame.write = property(real)
    assert len(plans) > 2 and not any(re.search("Python|Arrow|Pandas", p) for p in plans)


# --- op8 --------------------------------------------------------------------------------------------------------


def phrases_of(text, sample):
    n = i = 0
    while i < len(text):
        m = 0
        while i + m < len(text) and text[i : i + m + 1] in sample:
            m += 1
        i, n = i + max(1, m), n + 1
    return n


@pytest.mark.parametrize("segment,dense", [(1024, 1 << 24), (7, 1 << 24), (5, 300), (16, 1)])
def test_phrases_equal_brute_force(monkeypatch, segment, dense):
    monkeypatch.setattr(cross_parsing, "SEGMENT", segment)
    monkeypatch.setattr(cross_parsing, "DENSE", dense)
    samples = {"a": "the cat sat on the mat", "b": "le chat était sur le tapis aaa", "z": han(400, 1)}
    p = cross_parsing.Parser({**samples, "c": "", "d": "12"})
    texts = ["the chat sat", "éé xyz 12 the", None, prose(30), "a" * 100, han(300, 1) + han(50, 2), "the cat sat on the mat " * 9, "x", "ab" * 60 + "the cat"]
    code, begin = cross_parsing.normalise(texts)
    got = p.phrases(code, begin)
    assert p.languages == ["a", "b", "z"]
    for i in range(len(texts)):
        s = "".join(map(chr, code[begin[i] : begin[i + 1]]))
        assert got[i].tolist() == [phrases_of(s, v) for v in samples.values()], texts[i]


@pytest.fixture(scope="module")
def learned(spark, small):
    return dict(cross_parsing.learn(spark.read.parquet(f"{small}/documents.parquet")))


@pytest.mark.parametrize("sample", ["", "12345", "zz", "hello", "a e i o u", "the of and"])
def test_a_tiny_sample_wins_nothing(learned, spark, small, sample):
    d = spark.read.parquet(f"{small}/documents.parquet").where("crc32(string(doc_id)) % 5 = 0 and length(text) > 200").select("text", "lang").limit(60).collect()
    p = cross_parsing.Parser({**learned, "tiny": sample})
    got = p.predict([r.text for r in d])
    assert sum(g[0] == r.lang for g, r in zip(got, d, strict=True)) >= 0.98 * len(d)


def test_many_letters_and_unequal_samples(learned):
    zh, ja = han(32_000, 1), "".join(c + "のはをに"[i % 4] for i, c in enumerate(han(8_000, 1)))
    p = cross_parsing.Parser({**learned, "zh": zh, "ja": ja, "short": learned["en"][:600]})
    got = p.predict([zh[500:900], ja[300:700], learned["fr"][2000:2600], zh[31_000:31_050]])
    assert [g[0] for g in got] == ["zh", "ja", "fr", "zh"] and all(g[3] for g in got)


def test_many_languages_stay_within_the_table(monkeypatch):
    monkeypatch.setattr(cross_parsing, "DENSE", 20_000)
    samples = {f"l{i:03d}": prose(900, i, 900).replace("b", chr(0x400 + i)) for i in range(40)}
    p = cross_parsing.Parser(samples)
    assert p.width == 2 and len(p.keys) > 0
    assert [g[0] for g in p.predict([v[100:400] for v in samples.values()])] == list(samples)


def test_noise_is_of_no_language(spark, small):
    r = random.Random(1)
    noise = " ".join("".join(r.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(r.randint(3, 9))) for _ in range(400))
    d = spark.read.parquet(f"{small}/documents.parquet")
    more = spark.createDataFrame([(10**9, noise, None, "s", 1), (10**9 + 1, han(2_000), None, "s", 1), (10**9 + 2, "casa", None, "s", 1), (10**9 + 3, "Xq", None, "s", 1)], SCHEMA)
    kept = {x.doc_id for x in cross_parsing.keep_identified(d.unionByName(more)).select("doc_id").collect()}
    assert not {10**9, 10**9 + 1} & kept and {10**9 + 2, 10**9 + 3} <= kept
    assert len(kept) == 2 + d.where(F.col("text").rlike(r"\p{L}")).count()
    unlabelled = d.withColumn("lang", F.lit(None).cast("string"))
    assert cross_parsing.keep_identified(unlabelled).count() == d.where(F.col("text").rlike(r"\p{L}")).count()


def test_languages_are_told_on_held_out_rows(spark, small):
    d = spark.read.parquet(f"{small}/documents.parquet")
    got = cross_parsing.identify(d).join(d.select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (got.lang_pred == got.lang).mean() > 0.98 and got.score.between(0, 1).all()


def test_texts_without_letters_are_undetermined(spark):
    langs = {0: "en", 1: "xx"}
    df = frame(spark, ["the cat sat " * 40, "zu qua pok " * 40, None, "123 !!", "", "the cat"] + ["the cat sat " * 9] * 6, langs)
    got = {r.doc_id: r.lang_pred for r in cross_parsing.identify(df).collect()}
    assert got[2] == got[3] == got[4] == "und" and got[5] == "en"
    assert {r.doc_id for r in cross_parsing.keep_identified(df).collect()} == set(range(12)) - {2, 3, 4}
    assert cross_parsing.keep_identified(df.withColumn("lang", F.lit(None).cast("string"))).count() == 9
    assert {r.lang_pred for r in cross_parsing.identify(df.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}


# --- op9 --------------------------------------------------------------------------------------------------------


def test_a_new_shard_takes_rows_only_into_itself(spark):
    df = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit("té").alias("text"), F.lit(1).alias("shard")).unionByName(spark.createDataFrame([(None, None, 1), (5, "x", 2), (5, "x", 2)], "doc_id long, text string, shard int"))
    got = rendezvous.place(df).toPandas()
    moved = got[got.shard != got.grown_shard]
    assert len(got) == 4003 and (moved.grown_shard == 8).all() and 0.06 < len(moved) / 4003 < 0.17
    for _, g in got.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))
    assert set(got["size"]) == {1, 2, 4} and got[got["size"] == 4].text_crc32.iloc[0] == zlib.crc32("té".encode())
    assert rendezvous.place(df.limit(0)).count() == 0


def test_weights_set_the_shares(spark):
    got = rendezvous.assign(spark.range(6000), "id", [1.0, 2.0, 3.0]).groupBy("shard").count().collect()
    share = {r.shard: r["count"] / 6000 for r in got}
    assert abs(share[0] - 1 / 6) < 0.02 and abs(share[2] - 0.5) < 0.03


# --- pipeline ---------------------------------------------------------------------------------------------------


def test_pipeline_stages_hold(spark, tmp_path, vocab):
    import corpus_pipeline as cp

    text = prose(300, 1)
    bench = prose(40, 77)
    clean = [prose(200, s) for s in range(20, 30)]
    texts = [*clean, text, text.replace("ba", "BA", 1), "12 34", None, bench, "a line that comes twice\n" + prose(60, 91), "a line that comes twice\n" + prose(60, 92)]
    d = str(tmp_path)
    frame(spark, texts).write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame([(1, bench)], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    docs = spark.read.parquet(f"{d}/documents.parquet")
    kept = {}
    for name, stage in cp.STAGES[:-1]:
        docs = shared.cut(stage(spark, docs, d), name)
        assert docs.columns == SCHEMA.replace(",", "").split()[::2]
        kept[name] = {r.doc_id: r.text for r in docs.collect()}
    assert set(range(10)) <= set(kept["decontamination"])
    assert 12 not in kept["language"] and 13 not in kept["language"]
    assert kept["lines"][16] == texts[16].split("\n")[1]
    assert 10 in kept["near_duplicates"] and 11 not in kept["near_duplicates"]
    assert 14 in kept["near_duplicates"] and 14 not in kept["decontamination"]
    packed = cp.STAGES[-1][1](spark, docs, d)
    assert {r.doc_id for r in packed.collect()} == set(kept["decontamination"])


def test_stages_keep_columns_that_clash(spark, tmp_path, vocab):
    import corpus_pipeline as cp

    d = str(tmp_path)
    spark.createDataFrame([(1, "z y x")], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    names = ["n_removed", "n_lines", "row", "gone", "key", "hits", "class_id", "text_hash", "score"]
    docs = frame(spark, [prose(90, 1), prose(90, 2) + "\n" + prose(30, 3), None, "a b c d e f\t", "a b c d e f"]).select("*", *[F.lit(i).alias(n) for i, n in enumerate(names)])
    for name, stage in cp.STAGES[:-1]:
        docs = shared.cut(stage(spark, docs, d), name)
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars", *names]
        assert all(tuple(r)[5:] == tuple(range(len(names))) for r in docs.collect())
    assert {r.doc_id for r in docs.collect()} == {0, 1, 3}
    empty = docs.limit(0)
    for _, stage in cp.STAGES:
        assert stage(spark, empty, d).count() == 0


def test_files_can_be_left_out():
    here = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    text = open(f"{here}/corpus_pipeline.py").read()
    assert "except ImportError" not in text
