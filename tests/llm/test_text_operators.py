"""Packing, SentencePiece, chat, substrings, host rules, licenses: plain versions, round trips and edge cases."""

from __future__ import annotations

import hashlib
import re
import zlib
from collections import Counter
from re import _constants as sre_constants
from re import _parser as sre_parser

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from stepwalk.llm import oracles
from stepwalk.llm.license_rules import gate, rules
from stepwalk.llm.op1_sentencepiece import DoubleArray, Unigram, decode, digests, encode
from stepwalk.llm.op2_packing import Windows, pack, padding
from stepwalk.llm.op3_chat import PART, format_chat, loss_text, op3_chat, read_turns
from stepwalk.llm.op5_substring import COVERS, cover_for, remove_repeats
from stepwalk.llm.op8_host_rules import judge
from stepwalk.llm.op10_licenses import gated_text, scan
from stepwalk.llm.registry import oracle_sql, queries

from ..compare import connect, same
from .brute import WORD

TOKENIZER = public_tokenizers.path("word_bpe_49k.json")
PIECES = public_tokenizers.path("piece_bpe_32k.model")
DOC = "doc_id long, text string, score double, key string"
HARD = [(1, "a b c", 0.5, "k"), (1, "a b c", 0.5, "k"), (2, None, None, None), (3, "", None, "k"), (None, "null id", 0.1, "k"), (4, " \n\t ", 0.0, ""), (5, "wörter mit \x01 mark \x01", 1.0, "x"), (6, "long " * 3000, 1.0, "x"), (7, "w" * 5000, 1.0, "x"), (8, "<|endoftext|> It's 123 ÀÉ №5", 1.0, "x")]


@pytest.fixture(scope="module")
def hard(spark):
    return spark.createDataFrame(HARD, DOC)


@pytest.mark.parametrize("name", sorted(oracle_sql()))
def test_queries_match_sql(spark, sf, name):
    frame = queries()[name](spark, sf)
    same(connect(sf), frame, oracle_sql()[name])


def test_license_base_columns_match_sql(spark, sf):
    same(connect(sf), queries()["op10_licenses"](spark, sf).drop("labels", "score"), oracles.LICENSE_BASE)


def tokens(text):
    from tokenizers import Tokenizer

    ids = Tokenizer.from_file(TOKENIZER).encode(text or "", add_special_tokens=False).ids
    return np.append(np.array(ids, "<u4"), np.uint32(1)).astype("<u4")


def test_packing_covers_every_id_once(spark, hard):
    rows = pack(hard.repartition(3), TOKENIZER, size=256, open_windows=3).collect()
    texts = [r[1] for r in HARD]
    want = Counter()
    for (doc, _, _, _), t in zip(HARD, texts, strict=True):
        want[doc] += len(tokens(t))
    got = Counter()
    for r in rows:
        got[r.doc_id] += r.length
        piece = [x for x in {t for (d, t, _, _) in HARD if d == r.doc_id}]
        assert any(zlib.crc32(tokens(t)[r.start : r.start + r.length].tobytes()) == r.ids_crc32 and len(tokens(t)) == r.doc_tokens for t in piece)
    assert got == want
    for seq in {r.sequence_id for r in rows}:
        own = sorted((r.offset, r.length) for r in rows if r.sequence_id == seq)
        assert own[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(own, own[1:], strict=False))
        assert sum(n for _, n in own) <= 256
    made = pack(hard, TOKENIZER, size=256)
    assert padding(made, 256).first().padded == 0
    assert pack(hard.limit(0), TOKENIZER).count() == 0
    assert pack(hard.where("doc_id = 3"), TOKENIZER, end_id=None).count() == 0


def test_windows_are_bounded_and_best_fit():
    w = Windows(10, 2)
    assert [w.put(7), w.put(4)] == [[(0, 0, 7)], [(1, 0, 4)]]
    assert w.put(3) == [(0, 7, 3)] and 0 not in w.fill
    assert w.put(5) == [(1, 4, 5)]
    assert w.put(8) == [(2, 0, 8)]
    assert w.put(9) == [(1, 9, 1), (3, 0, 8)]
    assert len(w.fill) <= 2


def test_double_array_finds_exactly_its_keys():
    keys = [b"a", b"ab", b"abc", b"b", b"\xff\x00", b"zebra"]
    trie = DoubleArray(keys)

    def find(key):
        state = np.zeros(1, np.int32)
        for b in key:
            state, ok = trie.step(state, np.array([b], np.int32))
            if not ok[0]:
                return -1
        return int(trie.value[state[0]])

    assert [find(k) for k in keys] == list(range(6))
    assert find(b"abd") == find(b"ze") == find(b"c") == -1


def toy():
    pieces = [("<unk>", 0.0, "unknown"), *[(f"<0x{b:02X}>", 0.0, "byte") for b in range(256)]]
    pieces += [("▁", -3.0, "normal"), ("a", -2.0, "normal"), ("b", -2.0, "normal"), ("ab", -2.5, "normal"), ("▁ab", -4.0, "normal"), ("aba", -3.0, "normal"), ("é", -5.0, "normal")]
    return Unigram(pieces)


def best_score(model, text):
    data = ("▁" + text.replace(" ", "▁")).encode()
    score = {t: s for t, s, _ in [("▁", -3.0, 0), ("a", -2.0, 0), ("b", -2.0, 0), ("ab", -2.5, 0), ("▁ab", -4.0, 0), ("aba", -3.0, 0), ("é", -5.0, 0)]}
    chars = data.decode()
    best = [0.0] + [-1e18] * len(chars)
    for e in range(1, len(chars) + 1):
        for s in range(max(0, e - 3), e):
            part = chars[s:e]
            if part in score:
                best[e] = max(best[e], best[s] + score[part])
            elif len(part) == 1:
                best[e] = max(best[e], best[s] + model.unknown_score)
    return best[-1]


def path_score(model, text):
    data = ("▁" + text.replace(" ", "▁")).encode()
    return sum(model.score[v] if v >= 0 else model.unknown_score for _, v in model._path(data))


@pytest.mark.parametrize("text", ["ab", "aba ab", "bab  aba", "é☃b", "abab abab", "\n a\nb "])
def test_viterbi_is_the_best_path_and_round_trips(text):
    model = toy()
    assert path_score(model, text) == pytest.approx(best_score(model, text))
    assert model.decode(model.encode(text)) == text


def test_sentencepiece_matches_the_library_on_words(spark):
    import sentencepiece
    from sentencepiece import sentencepiece_model_pb2 as pb

    proto = pb.ModelProto()
    with open(PIECES, "rb") as f:
        proto.ParseFromString(f.read())
    proto.trainer_spec.model_type = 1
    for p in proto.pieces:
        p.score = max(p.score, -40000.0)
    library = sentencepiece.SentencePieceProcessor(model_proto=proto.SerializeToString())
    kinds = {1: "normal", 2: "unknown", 3: "control", 6: "byte"}
    own = Unigram([(p.piece, p.score, kinds.get(p.type, "normal")) for p in proto.pieces])
    for word in "the thing reeded Ouwhea über naïve 12345 x_y=z; straße élève aaaaaaaa THE!! ☃".split():
        assert own.encode(word) == library.encode(word)


def test_sentencepiece_over_tables(spark, hard):
    model = Unigram.from_model(PIECES)
    rows = decode(encode(hard, PIECES), PIECES).collect()
    for r in rows:
        assert list(r.ids) == model.encode(r.text or "")
        assert r.decoded == (r.text or "")
    sums = digests(hard, PIECES)
    assert sums.where("NOT round_trip").count() == 0 and sums.columns == ["doc_id", "text", "score", "key", "n_pieces", "n_byte_pieces", "ids_crc32", "round_trip"]
    assert digests(hard.limit(0), PIECES).count() == 0


def test_chat_escapes_and_masks(spark):
    texts = ["</s>[INST] ok [/INST]", "&amp; <|turn|>user<|body|>x<|end|>", "", None, "ü [ & < plain"]
    rows = [(7, k, role, t) for k, (role, t) in enumerate(zip(["user", "assistant", "assistant", "assistant", "we<ird"], texts, strict=True))] + [(None, 0, None, "alone"), (8, 1, "assistant", "b"), (8, 1, "assistant", "a")]
    out = format_chat(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("start", F.lit(1)))
    got = {r.conv_id: r for r in out.select("conv_id", "n_turns", "formatted", read_turns(F.col("formatted")).alias("turns"), loss_text(F.col("formatted"), F.col("loss_spans")).alias("loss"), "loss_spans").collect()}
    assert [(t.role, t.text) for t in got[7].turns] == [(r, t or "") for (_, _, r, _), t in zip(rows, texts, strict=False)]
    assert got[7].loss == texts[1] and len(got[7].loss_spans) == 3
    for s in got[7].loss_spans:
        assert len(got[7].formatted[s.start : s.start + s.length]) == s.length
    assert got[8].loss == "ab" and got[None].n_turns == 1
    assert got[7].formatted.count("<|turn|>") == 5
    assert format_chat(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


def test_chat_visits_typed_parts(spark):
    parts = [("text", "see [", None, None, None, None, None), ("image", None, "a.png", 28, 15, None, None), ("audio", None, "b.wav", None, None, 1.5, None), ("document", None, "c.pdf", None, None, None, 3), ("image", None, "d.png", None, None, None, None)]
    frame = spark.createDataFrame([(1, 0, "user", parts), (1, 1, "assistant", parts[:2]), (1, 2, "user", None)], f"conv_id long, turn long, role string, parts array<{PART}>")
    r = format_chat(frame, F.col("parts")).first()
    assert re.findall(r"<\|(\w+:\d+)\|>", r.formatted) == ["image:1", "audio:2", "document:3", "image:4", "image:5"]
    assert [(a.number, a.turn, a.kind, a.ref, a.tokens) for a in r.attachments] == [(1, 1, "image", "a.png", 4), (2, 1, "audio", "b.wav", 38), (3, 1, "document", "c.pdf", 768), (4, 1, "image", "d.png", 1), (5, 2, "image", "a.png", 4)]
    assert r.n_attachment_tokens == 815 and "see &lbr;" in r.formatted


def test_chat_plan_holds_no_python(spark, sf):
    plan = op3_chat(spark, sf)._jdf.queryExecution().toString()
    licenses = queries()["op10_licenses"](spark, sf)._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow", plan + licenses)


@pytest.mark.parametrize("period", sorted(COVERS))
def test_covers_hold_every_difference(period):
    assert {(a - b) % period for a in COVERS[period] for b in COVERS[period]} == set(range(period))


def plain_repeats(texts, window):
    words = [WORD.findall(t or "") for t in texts]
    seen = Counter(tuple(w[i : i + window]) for w in words for i in range(len(w) - window + 1))
    out = []
    for w in words:
        gone = {j for i in range(len(w) - window + 1) if seen[tuple(w[i : i + window])] > 1 for j in range(i, i + window)}
        out.append((len(w), len(gone), " ".join(x for i, x in enumerate(w) if i not in gone)))
    return out


@pytest.mark.parametrize("window", [2, 5, 12, 35, 50])
def test_substrings_match_plain(spark, window):
    r = np.random.default_rng(window)
    shared = [" ".join(f"s{k}_{i}" for i in range(60)) for k in range(3)]
    texts = []
    for _ in range(40):
        own = [f"w{r.integers(0, 400)}" for _ in range(int(r.integers(0, 120)))]
        cut = int(r.integers(0, len(own) + 1))
        a = int(r.integers(0, 30))
        piece = shared[int(r.integers(0, 3))].split()[a : a + int(r.integers(1, 60))]
        texts.append("\n".join([" ".join(own[:cut]), " ".join(piece), " ".join(own[cut:])]))
    texts += [None, "", "x " * 90, texts[0], texts[0]]
    frame = spark.createDataFrame([(i % 43, t, "k") for i, t in enumerate(texts)], "doc_id long, text string, key string")
    got = sorted((r.doc_id, r.n_words, r.n_removed, r.kept_text) for r in remove_repeats(frame, window).collect())
    assert got == sorted((i % 43, *x) for i, x in enumerate(plain_repeats(texts, window)))
    assert cover_for(35)[0] == 21


@pytest.mark.parametrize("groups", [1, 3, 7, 12, 31, 51, 200])
def test_substrings_at_any_number_of_partitions(spark, groups):
    r = np.random.default_rng(groups)
    shared = [" ".join(f"s{k}_{i}" for i in range(70)) for k in range(40)]
    texts = [" ".join([f"a{n}", *(f"w{r.integers(0, 10**6)}" for _ in range(20)), shared[n % 40], f"z{n}"]) for n in range(160)]
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(groups))
    try:
        got = sorted((x.n_words, x.n_removed, x.kept_text) for x in remove_repeats(frame).collect())
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert got == sorted(plain_repeats(texts, 35)) and sum(x[1] for x in got) == 160 * 70


def test_substrings_of_hard_rows(spark, hard):
    got = remove_repeats(hard)
    assert got.count() == len(HARD) and set(got.columns) == {"doc_id", "score", "key", "n_words", "n_removed", "kept_text"}
    assert got.where("doc_id = 6").first().n_removed == 3000
    assert remove_repeats(hard.limit(0)).count() == 0


def test_host_rules_shrink_and_reject(spark):
    good, bad = " ".join(f"w{i}" for i in range(60)), "x " * 60
    rows = [(i, good, "fine", "h") for i in range(30)] + [(100 + i, bad, "spam", "h") for i in range(30)] + [(200, good, "spam", "h"), (201, bad, "small", "h"), (202, good, None, "h"), (203, None, None, "h")]
    got = {r.doc_id: r for r in judge(spark.createDataFrame(rows, "doc_id long, text string, source string, host string")).collect()}
    assert got[0].kept and not got[200].base_failed and not got[200].kept
    assert 0.5 < got[200].shrunk < 30 / 31 and got[201].shrunk < 1
    assert got[203].n_words == 0 and got[203].base_failed and got[202].host is None
    assert judge(spark.createDataFrame([], "doc_id long, text string, source string")).count() == 0


def test_hosts_fail_by_any_rule(spark):
    good = " ".join(f"word{i}" for i in range(60))
    signs, lines = good + " # * $ % & | < > ##", "\n".join(["same line of words here"] * 5 + [f"{good} {k}" for k in range(6)])
    rows = [(i, good, "fine") for i in range(40)] + [(100 + i, signs, "signs") for i in range(40)] + [(200 + i, lines, "lines") for i in range(40)] + [(300, good, "signs")]
    got = {r.doc_id: r for r in judge(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert got[0].kept and got[0].n_failed == 0 and not got[100].base_failed and got[100].n_failed == 1
    assert got[200].n_lines == 11 and got[200].n_dup_lines == 4 and got[200].n_failed >= 1
    assert not got[100].kept and not got[200].kept and not got[300].kept and got[300].n_failed == 0


def plain_licenses(text):
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    norm = " " + " ".join(words) + " "
    found = []
    for n, label, word, pattern, priority, sure, base in rules():
        if word in norm:
            for m in re.finditer(pattern, norm):
                start = norm[: m.start()].count(" ")
                found.append((start, start + m[0].count(" "), priority, n, label, sure, base))
    kept = [d for d in found if not any(e is not d and e[2] >= d[2] and e[0] <= d[0] and e[1] >= d[1] and (e[0], -e[1], -e[2], e[3]) < (d[0], -d[1], -d[2], d[3]) for e in found)]
    base = [d for d in found if d[6]]
    labels = sorted({d[4] for d in kept} | {d[4] for d in base})
    return len(words), len(base), min((d[0] for d in base), default=None), max((d[0] for d in base), default=None), ",".join(sorted({d[4] for d in base})), ",".join(labels), max([d[5] for d in kept + base], default=0.0)


def test_license_rules_match_plain(spark):
    assert len(rules()) > 200
    texts = ["Released under the MIT License. under the mit license under the MIT-license", "Licensed under the Apache License, Version 2.0.", "Licensed under CC BY-NC 4.0. cc by nc sa", "SPDX-License-Identifier: GPL-3.0-only\nGNU General Public License version 3", None, "", "This is the BSD 3-Clause License; all rights reserved. Copyright (c) 2020", "the license", "Permission is hereby granted, free of charge, to any person obtaining a copy WITHOUT WARRANTY OF ANY KIND", "İ K under the mıt license Kelvin", "apache license version 2 " * 500, "dual licensed under MIT license or Apache-2.0 license"]
    frame = spark.createDataFrame([(i // 2, t, "k") for i, t in enumerate(texts)] + [(0, texts[0], "k")], "doc_id long, text string, key string")
    got = sorted(map(tuple, scan(frame).collect()), key=str)
    want = sorted([(i // 2, *plain_licenses(t)) for i, t in enumerate(texts)] + [(0, *plain_licenses(texts[0]))], key=str)
    assert got == want
    assert scan(frame.limit(0)).count() == 0


def test_kept_digest_is_of_kept_text(spark, hard):
    a = {(r.doc_id, r.kept_text) for r in remove_repeats(hard).collect()}
    b = {(r.doc_id, r.kept_sha256) for r in remove_repeats(hard, keep_text=False).collect()}
    assert {(i, hashlib.sha256(t.encode()).hexdigest()) for i, t in a} == b


def phrases(pattern):
    """Texts that a rule's pattern matches: between them they hold every alternative, and every optional part once and not at all."""

    def held(tree):
        columns = []
        for kind, what in tree:
            if kind is sre_constants.LITERAL:
                columns.append([chr(what)])
            elif kind is sre_constants.IN:
                columns.append([chr(x[1] if x[0] is sre_constants.LITERAL else x[1][0]) for x in what[:1]])
            elif kind is sre_constants.BRANCH:
                columns.append([t for branch in what[1] for t in held(branch)])
            elif kind is sre_constants.SUBPATTERN:
                columns.append(held(what[3]))
            elif kind is sre_constants.MAX_REPEAT:
                columns.append([t * n for n in dict.fromkeys((what[0], what[1])) for t in (held(what[2]) if n else [""])])
            else:
                assert kind is sre_constants.ASSERT
        return ["".join(c[k % len(c)] for c in columns) for k in range(max(map(len, columns), default=1))]

    found = held(sre_parser.parse(pattern))
    assert all(re.search(pattern, t + " ") for t in found)
    return found


def test_license_gate_passes_what_rules_match(spark):
    texts = [t.strip().replace(" ", "-\n") for r in rules() for t in phrases(r[3])]
    stopped = spark.createDataFrame([(t,) for t in texts], "text string").where(~F.col("text").rlike(gate()) | ~gated_text(F.col("text"))).collect()
    assert len(texts) > len(rules()) and not stopped
    rows = [(1, "Released under the GNU GPL v3."), (2, "distributed under BSD 3-clause"), (3, "Available under MIT"), (4, "free to use under zlib")]
    got = {r.doc_id: r.labels for r in scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: "gpl-3", 2: "bsd-3", 3: "mit", 4: "zlib"}


def test_license_keywords_lose_no_match(spark, monkeypatch):
    texts = [t.strip() for r in rules() for t in phrases(r[3])]
    texts += ["Licensed under the GNU Library General Public License version 2", "Zero-Clause BSD License", "licensed under PSF License Version 2", "see the Open Database License 1.0 license"]
    got = sorted(map(tuple, scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()))
    monkeypatch.setitem(globals(), "rules", lambda keyed=rules: [(n, label, "", *rest) for n, label, _, *rest in keyed()])
    assert got == [(i, *plain_licenses(t)) for i, t in enumerate(texts)]
    assert [r[6] for r in got[-4:]] == ["lgpl-2", "0bsd", "python-2", "odbl-1"]
