"""Encoding, counts, token files and packing against the library itself."""

import io
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from subgraph_spark.llm import packing, token_counts, token_ids
from subgraph_spark.llm.common import new_folder, tokenizer_path
from subgraph_spark.llm.encoding import PreTokenEncoder, encoder_for

BYTE, WORD = tokenizer_path("byte_bpe_50k.json"), tokenizer_path("word_bpe_49k.json")
ODD = st.lists(st.sampled_from(list(" \t\n\r\x0b\x0c\x1c\x1f\x85\xa0 　aAbBzZ019.,'!-éÉßΣσς́👍ǅ中<|>") + ["<|endoftext|>", "  ", "'s", "the ", " 0 ", "\n\n"]), max_size=40).map("".join)


def library(path):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@settings(max_examples=1500, deadline=None)
@given(st.lists(ODD, max_size=6))
def test_encoders_equal_the_library(texts):
    for path, keeps in ((BYTE, True), (WORD, False)):
        encoder = encoder_for(path, keeps)
        expected = [x.ids for x in encoder.library.encode_batch(texts, add_special_tokens=False)]
        assert [np.frombuffer(x, "<u2").tolist() for x in encoder.encode(texts)] == expected


@settings(max_examples=400, deadline=None)
@given(ODD)
def test_counts_equal_the_library(text):
    counter = token_counts.counter_for(BYTE)
    assert counter.count(text) == len(counter.library.encode(text, add_special_tokens=False).ids)


def test_chunks_that_begin_with_white_space():
    texts = ["\x85z", "\xa0b a", "a", "\x0bB\n", "x \x85y \xa0z", "a\nb. \x85"]
    encoder = PreTokenEncoder(BYTE, True)
    assert [np.frombuffer(x, "<u2").tolist() for x in encoder.encode(texts)] == [x.ids for x in encoder.library.encode_batch(texts, add_special_tokens=False)]


def test_every_plain_character_in_context():
    """Each plain character beside each kind of other, apostrophes before all pairs of letters, and white space in front and at the end."""
    from subgraph_spark.llm import encoding

    plain = [chr(c) for c in range(1, 0x2200) if not encoding._ODD.search(chr(c))]
    texts = [a + x + b for x in plain for a in ("", "a", "1", ".", " ", "\n", "'", "é") for b in ("", "a", "1", ".", " ", " b", "'s", "»")]
    letters = "abdelmrstvLS é1.'"
    texts += [a + "'" + x + y + b for a in ("", "it", " ", ".", "\n", "'", "7") for x in letters for y in letters for b in ("", "z ")]
    for path, keeps in ((BYTE, True), (WORD, False)):
        encoder = PreTokenEncoder(path, keeps)
        expected = encoder.library.encode_batch_fast(texts, add_special_tokens=False)
        for text, got, want in zip(texts, encoder.encode(texts), expected, strict=True):
            assert np.frombuffer(got, "<u2").tolist() == want.ids, repr(text)


def test_long_texts_and_small_stores(monkeypatch):
    from subgraph_spark.llm import encoding

    monkeypatch.setattr(encoding, "_PIECE", 100)
    monkeypatch.setattr(encoding, "_GROUP", 50)
    texts = ["some words\nand  more, " * 60, "", "y" * 1000 + " z", " lead " * 40, "sixteen-letters- abcdefghijklmnop abcdefghijklmno abcdefghijklmnopq " * 9]
    for path, keeps in ((BYTE, True), (WORD, False)):
        encoder = PreTokenEncoder(path, keeps, most=3)
        expected = [x.ids for x in encoder.library.encode_batch(texts, add_special_tokens=False)]
        for _ in range(3):  # the table is begun anew each time
            assert [np.frombuffer(x, "<u2").tolist() for x in encoder.encode(texts)] == expected
    monkeypatch.setattr(token_counts, "_PIECE", 100)
    counter = token_counts.TokenCounter(BYTE, most=3)
    assert [counter.count(x) for x in texts] == [len(x.ids) for x in counter.library.encode_batch(texts, add_special_tokens=False)]


def test_engines_agree_on_the_compared_ranges():
    """Both regular expression engines, for every character of the ranges that the counter trusts."""
    import regex

    counter = token_counts.counter_for(BYTE)
    split, odd = regex.compile(token_counts.PATTERN), regex.compile(token_counts._COMPARED)
    for c in range(0x110000):
        if 0xD800 <= c < 0xE000 or odd.search(chr(c)):
            continue
        x = chr(c)
        text = f"a{x}1{x} {x}!{x}{x} "
        assert [tuple(p[1]) for p in counter.library.pre_tokenizer.pre_tokenize_str(text)] == [m.span() for m in split.finditer(text)], hex(c)


def test_whole_tokens_are_proven():
    counter = token_counts.counter_for(BYTE)
    assert len(counter.whole) > 40_000
    some = sorted(counter.whole)[::997]
    assert all(len(counter.library.model.tokenize(x.encode().decode("latin-1").translate(counter._letters))) == 1 for x in some)


def test_token_counts(docs, docs_rows, empty):
    lib = library(BYTE)
    expected = sorted(((d, len((t or "").encode()), len(lib.encode(t or "", add_special_tokens=False).ids)) for d, t, *_ in docs_rows), key=repr)
    assert sorted(map(tuple, token_counts.count_tokens(docs, BYTE).collect()), key=repr) == expected
    assert token_counts.count_tokens(empty, BYTE).count() == 0


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 10**6), max_size=1500), st.integers(0, 3))
def test_elias_fano(gaps, scale):
    values = np.cumsum(np.array(gaps, np.int64) // 10 ** (2 * scale)) if gaps else np.zeros(0, np.int64)
    code = token_ids.EliasFano.frombytes(token_ids.EliasFano.build(values).tobytes())
    assert code.values().tolist() == values.tolist()
    for i in {0, len(values) // 2, len(values) - 1} if len(values) else ():
        assert code.select(i) == values[i]
    a, b = len(values) // 3, 2 * len(values) // 3
    assert code.values(a, b).tolist() == values[a:b].tolist()


def test_elias_fano_is_small():
    values = np.cumsum(np.random.default_rng(1).integers(1, 2000, 100_000))
    bits = 8 * len(token_ids.EliasFano.build(values).tobytes()) / len(values)
    assert bits < 2 + np.log2(values[-1] / len(values)) + 0.8
    with pytest.raises(ValueError):
        token_ids.EliasFano.build(np.array([2, 1]))


def test_token_files(spark, docs, docs_rows, empty):
    lib = library(BYTE)
    got = token_ids.token_round_trip(spark, docs, BYTE, 2).collect()
    ids = {(d, t): [*lib.encode(t or "", add_special_tokens=False).ids, 2] for d, t, *_ in docs_rows}
    expected = sorted(((d, len(x), zlib.crc32(np.array(x, "<u4").tobytes())) for d, t, *_ in docs_rows for x in [ids[d, t]]), key=repr)
    assert sorted(((r.doc_id, r.n_tokens, r.ids_crc32) for r in got), key=repr) == expected
    ordered = sorted(got, key=lambda r: r.start)
    names = [r.doc_id for r in ordered]
    assert names == sorted(names, key=lambda x: (x is not None, x))
    assert [r.start for r in ordered] == [0, *np.cumsum([r.n_tokens for r in ordered])[:-1].tolist()]
    assert token_ids.token_round_trip(spark, empty, BYTE, 2).count() == 0


def test_random_access(spark, docs):
    shards = token_ids.write_shards(docs, new_folder(spark, "ids"), BYTE, 2).collect()
    raw = open(shards[0].path.removeprefix("file://"), "rb").read()

    class File(io.BytesIO):
        def size(self):
            return len(raw)

    shard = token_ids.Shard(File(raw))
    assert len(shard) == shards[0].n_docs and shard.start(len(shard) - 1) + len(shard.ids(len(shard) - 1)) == shards[0].n_tokens
    assert [shard.doc_id(i) for i in range(len(shard))] == shard.doc_ids(0, len(shard))
    raw = raw[:-32] + b"NOTHING!" + raw[-24:]
    with pytest.raises(ValueError):
        token_ids.Shard(File(raw))


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 50), max_size=200))
def test_best_fit(lengths):
    bins = packing.best_fit(np.array(lengths, np.int64), 50)
    assert sorted(i for b in bins for i in b) == list(range(len(lengths)))
    used = [sum(lengths[i] for i in b) for b in bins]
    assert all(u <= 50 for u in used) and sum(u <= 25 for u in used) <= 1


def check_packed(got, expected_pieces, capacity):
    assert sorted((tuple(r)[:5] for r in got), key=repr) == sorted(expected_pieces, key=repr)
    by = {}
    for r in got:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= capacity
    return by


def pieces_of(rows, capacity):
    lib = library(WORD)
    for d, t in rows:
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 0]
        for k, at in enumerate(range(0, len(ids), capacity)):
            part = ids[at : at + capacity]
            yield d, k, at, len(part), zlib.crc32(np.array(part, "<u4").tobytes())


def test_packing(docs, docs_rows, empty):
    expected = list(pieces_of([(d, t) for d, t, *_ in docs_rows], 2048))
    by = check_packed(packing.pack_documents(docs, WORD).collect(), expected, 2048)
    assert len(by) <= 1.02 * sum(x[3] for x in expected) / 2048 + 2
    assert packing.pack_documents(empty, WORD).count() == 0


def test_packing_in_several_rounds(spark, docs, docs_rows, monkeypatch):
    monkeypatch.setattr(packing, "ITEMS", 20)
    monkeypatch.setattr(packing, "FAN_IN", 2)
    expected = list(pieces_of([(d, t) for d, t, *_ in docs_rows], 512))
    by = check_packed(packing.pack_documents(docs.repartition(8), WORD, 0, 512).collect(), expected, 512)
    assert len(by) <= 1.1 * sum(x[3] for x in expected) / 512 + 2
