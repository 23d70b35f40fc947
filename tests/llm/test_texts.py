"""Operators on single documents: quality rules, SentencePiece, token files, licences."""

import hashlib
import re
import zlib

import numpy as np
import pytest

from lattica.llm import licenses, piece_bpe, quality, token_files
from lattica.llm.common import tokenizer_path, workspace

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"
LONG = "The long word story of " * 6000
ROWS = [
    (1, "The cat and the dog sat on the mat, and the cat was in the hat.", "en", "a", 63),
    (2, None, None, None, None),
    (3, "", "en", "a", 0),
    (4, " \n\t ", "en", "b", 4),
    (5, LONG, "en", "a", len(LONG)),
    (None, "null id text with the words of it", "en", "a", 1),
    (1, "The cat and the dog sat on the mat, and the cat was in the hat.", "en", "a", 63),
    (6, "  two  spaces ▁ and 日本語 ß 😀 e\u0301 \x00 <s> ... a.b 3.5 ,x", "fr", "b", 1),
    (7, "x" * 3000 + " " * 300 + ".", "fr", "b", 1),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def brute_quality(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    twice = {w for w in windows if windows.count(w) > 1} if len(windows) < 2000 else set(windows)
    covered = {i + k for i, w in enumerate(windows) if w in twice for k in range(5)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered)


def test_quality_measures(docs):
    rows = quality.judged(docs).select("text", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept").collect()
    for r in rows:
        want = brute_quality(r["text"])
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
        assert r["base_failed"] == (want[0] < 10 or 100 * want[4] > 20 * want[0])
    assert [r["kept"] for r in rows].count(True) == 3


def test_quality_keeps_columns_of_clashing_names(docs, empty):
    clash = docs.withColumnRenamed("n_chars", "n_words").withColumnRenamed("lang", "kept")
    assert quality.kept(clash).columns == clash.columns and quality.kept(clash).count() == 3
    own = quality.judged(docs.withColumnRenamed("n_chars", "_Words").withColumnRenamed("lang", "_keys").withColumnRenamed("source", "_lines"))
    assert {"_Words", "_keys", "_lines"} <= set(own.columns) and {r["_lines"] for r in own.collect()} == {"a", "b", None}
    assert quality.judged(empty).count() == 0
    assert "Python" not in quality.kept(docs)._jdf.queryExecution().executedPlan().toString()


def test_sentencepiece_equals_the_library(docs, empty):
    import sentencepiece

    path = tokenizer_path("piece_bpe_32k.model")
    library = sentencepiece.SentencePieceProcessor(model_file=path)
    out = piece_bpe.decoded(piece_bpe.encoded(docs.withColumnRenamed("n_chars", "ids"), path), path).collect()
    assert len(out) == len(ROWS)
    for r in out:
        want = library.encode(r["text"] or "")
        assert r["ids"] == want and r["decoded"] == library.decode(want)
    assert piece_bpe.encoded(empty, path).count() == 0


def test_sentencepiece_random_texts():
    import random

    import sentencepiece

    path = tokenizer_path("piece_bpe_32k.model")
    library, own = sentencepiece.SentencePieceProcessor(model_file=path), piece_bpe.model(path)
    rng = random.Random(5)
    alphabet = [*"abehtniorsATHE  ▁\n\t.,é漢字ñß😀\x00<s>", "  ", "ing", "   ", "ll"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.choice([1, 3, 30, 300]))) for _ in range(300)] + [" " * k for k in range(40)] + ["a" * k for k in range(60)]
    for text in texts:
        got = [i for b in own.encode_parts(own.parts_of(text)) for i in np.frombuffer(b, "<i4").tolist()]
        assert got == library.encode(text) and own.decode(got) == library.decode(got), text


def test_token_files(spark, docs, empty):
    from tokenizers import Tokenizer

    path = tokenizer_path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    data = token_files.write(docs, workspace(spark, "ids"), path, shards=3)
    assert data.dtype == "<u2" and token_files.Dataset.load(data.path) == data
    got = sorted(token_files.read(spark, data).collect(), key=lambda r: r["start"])
    ordered = sorted(ROWS, key=lambda r: (r[0] is not None, r[0] or 0))
    start = 0
    for r, (doc_id, text, *_) in zip(got, ordered, strict=True):
        ids = [*library.encode(text or "", add_special_tokens=False).ids, 1]
        assert (r["doc_id"], r["start"], r["n_tokens"], r["ids"]) == (doc_id, start, len(ids), ids)
        assert r["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes())
        start += len(ids)
    none = token_files.write(empty, workspace(spark, "ids"), path)
    assert token_files.read(spark, none).count() == 0


def test_token_cuts_are_exact():
    import random

    from tokenizers import Tokenizer

    path = tokenizer_path("word_bpe_49k.json")
    library, own, rng = Tokenizer.from_file(path), token_files._encoder(path), random.Random(6)
    alphabet = [*"abehtniorsATHE  ▁\n\t.,é漢ñß😀İΣς's\x00<\xa0", "<|endoftext|>", "  ", "'re", "ing"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.choice([0, 1, 3, 30, 200]))) for _ in range(400)]
    for text, raw in zip(texts, own.encode(texts), strict=True):
        assert np.frombuffer(raw, "<u4").tolist() == library.encode(text, add_special_tokens=False).ids, text


def test_licences(spark, docs, empty):
    rows = [(1, "All rights reserved. CC-BY and cc by. GNU General Public Licence"), (2, "Permision is hereby granted, free of charge, to any persson obtaining a copy"), (3, None), (4, "é" * 50 + " Released under the MIT License.")]
    out = {r["doc_id"]: r for r in licenses.scanned(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert [(s["label"], s["first_word"]) for s in out[1]["spans"] if s["base"]] == [("reserved", 0), ("cc-by", 3), ("cc-by", 6)]
    assert [(s["label"], s["edits"], s["first_word"], s["n_words"]) for s in out[2]["spans"]] == [("mit", 2, 0, 13)]
    assert out[3]["n_words"] == 0 and out[3]["spans"] == []
    assert [(s["label"], s["first_word"]) for s in out[4]["spans"]] == [("mit", 1)]
    assert licenses.scanned(docs.withColumnRenamed("lang", "spans")).count() == len(ROWS) and licenses.scanned(empty).count() == 0


def test_licence_seeds_find_every_fuzzy_match():
    import random

    import regex

    rng, scanner = random.Random(4), licenses.Scanner()
    for _ in range(150):
        notice = rng.choice(licenses.NOTICES)
        text = list(notice.text)
        for _ in range(rng.randint(0, notice.edits)):
            at = rng.randrange(len(text))
            text[at : at + rng.choice([0, 1])] = rng.choice(["", "z", "q"])
        hay = "foo bar " + "".join(text) + " baz"
        found = {s["label"] for s in scanner.scan(hay)[1]}
        words = licenses.normalised(hay).decode()
        if regex.search(f"(?:{notice.text}){{e<={notice.edits}}}", f" {words} "):
            assert notice.label in found, hay


def brute_scan(text):
    """Words and base places by plain Python; labels by matching every notice against the whole text."""
    import regex

    lower = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text)
    words = regex.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower)
    base = sorted((i, label) for phrase, label in licenses.PHRASES.items() for p in [phrase.split()] for i in range(len(words)) if words[i : i + len(p)] == p)
    hay = f" {' '.join(words)} "
    labels = {n.label for n in licenses.NOTICES if regex.search(f"(?:{n.text}){{e<={n.edits}}}", hay)}
    return len(words), base, labels


def test_licences_against_brute_force():
    import random

    rng, scanner = random.Random(14), licenses.Scanner()
    fillers = ["foo", "BAR", "the", "license", "rights", "é", "日本", "12", "cc", "by", "CC-BY", "permission is", "all", "-", "\n", "reserved"]
    for _ in range(250):
        parts = []
        for _ in range(rng.randint(0, 12)):
            if rng.random() < 0.3:
                text = list(rng.choice(licenses.NOTICES).text)
                for _ in range(rng.randint(0, 8)):
                    at = rng.randrange(len(text) + 1)
                    text[at : at + rng.choice([0, 1])] = rng.choice(["", "z", "é", "\u2009", "𝄞", "  ", "."])
                parts.append("".join(text))
            else:
                parts.append(rng.choice(fillers))
        text = rng.choice([" ", ", ", ""]).join(parts)
        n, spans = scanner.scan(text)
        want, base, labels = brute_scan(text)
        assert n == want and sorted((s["first_word"], s["label"]) for s in spans if s["base"]) == base, text
        assert {s["label"] for s in spans if not s["base"]} == labels, text
        assert all(0 <= s["first_word"] and s["first_word"] + s["n_words"] <= n for s in spans), text


def test_licences_in_long_repetitive_texts():
    import time

    scanner, began = licenses.Scanner(), time.perf_counter()
    for text in ("permission is " * 40_000, "license " * 60_000 + "released under the mit license", "rights all " * 40_000):
        scanner.scan(text)
    assert time.perf_counter() - began < 30
    assert {s["label"] for s in scanner.scan("license " * 60_000 + "released under the mit license")[1]} == {"mit"}


def test_query_digests(spark, tmp_path, docs):
    from lattica.llm import queries

    docs.write.parquet(str(tmp_path / "documents.parquet"))
    out = queries.op1_sentencepiece(spark, str(tmp_path)).collect()
    assert {r["decoded_sha256"] for r in out if r["doc_id"] == 2} == {hashlib.sha256(b"").hexdigest()}
    rows = queries.op4_licenses(spark, str(tmp_path)).collect()
    assert len(rows) == len(ROWS) and all(0 <= r["score"] <= 1 for r in rows)


@pytest.mark.parametrize("space", [0x00A0, 0x2009, 0x202F, 0x1D173])
def test_licence_edits_of_several_bytes(space):
    _, spans = licenses.Scanner().scan(f"words before all{chr(space)}rights{chr(space)}reserved and after")
    assert [(s["label"], s["edits"]) for s in spans] == [("reserved", 2)]


def test_licence_before_a_better_one():
    for hay in ("all rihts reservd foo all rights reserved", "all rights reserved foo all rihts reservd", "all rihts reserved all rihts reservd all rights reserved"):
        _, spans = licenses.Scanner(phrases={}).scan(hay)
        assert [s["label"] for s in spans] == ["reserved"] * hay.count("all")
