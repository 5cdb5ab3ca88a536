"""Byte-exact operators against brute force: ids, files, spans, licenses, media."""

import hashlib
import re
import zlib

import numpy as np
import pytest

VOCAB = "word_bpe_49k.json"
ODD = [
    None, "", " ", "plain words, and more.", "Ünï ÇÖDÉ ΑΒΣ ς don't I'LL 12345 ½² x y\u0085z", "<|endoftext|> a<|startoftext|>b ###!!",
    "日本語のテキスト これ", "éclair İstanbul ﬁ", "\x1c\x1fabc", "###", "'s'tt's''s", "a" * 3000, "🙂🙂 né-né", "x " * 5000, "same", "same",
    "mail me at a.b@c.de_f@g.hi or +49 (0)30 123-4567 or +1 2, ip 10.0.0.1.2.3.4.5 and 300.1.1.1 001.002.003.255",
    "card 4111 1111 1111 1111 or 4111-1111-1111-1112, 4111111111111111 0000000000000 " + "9" * 200 + " 1 2 3", "é 🙂 4111 1111 1111 1111 x@y.z",
    "IBAN DE89 3704 0044 0532 0130 00 and GB82WEST12345698765432 not DE88370400440532013000", "call (487) 555-7209 now", "@.@.. +()- + 1.2.3 1.2.3.4",
    "CC BY 4.0 cc  by; cc-by General Public\nLicense ALL RIGHTS RESERVED. xcc by", "Kall rights reserved é all rights reservedé", "cc by cc by cc by",
    "Licensed under the Apache License, Version 2.0.", "foo " * 300 + "Released under the MIT License. " + "bar " * 300,
]


@pytest.fixture(scope="module")
def docs(spark):
    import pandas as pd

    real = pd.read_parquet("/root/testdata/sf0.001/documents.parquet")[["doc_id", "text"]]
    odd = pd.DataFrame({"doc_id": range(10_000, 10_000 + len(ODD)), "text": ODD})
    rows = [*real.itertuples(index=False, name=None), *odd.itertuples(index=False, name=None)]
    # extra columns whose names clash with those of results
    return spark.createDataFrame([(int(a), b, "k", 1.5, 7) for a, b in rows], "doc_id long, text string, key string, score double, n_tokens int").repartition(5)


def texts(docs):
    return {r.doc_id: r.text or "" for r in docs.select("doc_id", "text").collect()}


@pytest.fixture(scope="module")
def library():
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path(VOCAB))
    t.no_padding()
    t.no_truncation()
    return t


def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string")


def test_bpe_is_the_librarys(docs, library):
    from mlcurate.llm import bpe

    t = texts(docs)
    got = {r.doc_id: r for r in bpe.encode(docs, digests=True).collect()}
    assert got.keys() == t.keys()
    for k, text in t.items():
        ids = library.encode(text, add_special_tokens=False).ids
        assert got[k].n_tokens == len(ids)
        assert got[k].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), text[:60]
        assert got[k].decoded_sha256 == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest(), text[:60]


@pytest.mark.parametrize("kind", ["library", "trie"])
def test_ids_of_random_texts_are_the_librarys(library, kind):
    """Mixed chunks over the plain range, beyond it, and around its edges."""
    import random

    from mlcurate.llm import tokens

    rng = random.Random(11)
    plain, ascii_ = [chr(c) for c in range(1, 0x250)], list("abcdefgz ABC019.,'!-é ß\n\t")
    odd = lambda: chr(rng.choice([rng.randrange(0x250, 0xD800), rng.randrange(0xE000, 0x11000), rng.randrange(0x1F000, 0x20000)]))
    draw = [lambda: rng.choice(plain), lambda: rng.choice(rng.choice([plain, ascii_])), lambda: rng.choice(ascii_), lambda: odd() if rng.random() < 0.2 else rng.choice(ascii_)]
    texts = ["".join(f() for _ in range(rng.choice([1, 2, 3, 5, 10, 30]))) for f in draw for _ in range(6000)]
    texts += ["".join(x) for c in "ƏƐƆƁƊƉƔƖƲƷƝȺİ" for x in (c, c + "ß.", "9" + c + "z", c + "a.", "a" + c)] + [None, ""]
    t = tokens.ChunkTable(tokens.table(tokens.default_path(), kind).encoder, decoded=True)
    got = t.batch(texts)
    own, said = np.split(got.ids, np.cumsum(got.lens)[:-1]), t.spoken(got).to_pylist()
    for text, ids, s in zip(texts, own, said, strict=True):
        want = library.encode(text or "", add_special_tokens=False).ids
        assert ids.tolist() == want, repr(text)
        assert s == library.decode(want, skip_special_tokens=False), repr(text)


def test_bpe_decode_takes_its_own_ids(docs, library):
    from mlcurate.llm import bpe

    x = bpe.encode(docs.where("doc_id >= 10000"))
    said = {r.doc_id: r.text for r in bpe.decode(x).collect()}
    assert said == {r.doc_id: r.decoded for r in x.collect()}


def test_files_round_trip(spark, docs, library):
    from mlcurate.llm import id_files

    path = id_files.new_path(spark)
    id_files.write(docs, path)
    got = sorted(id_files.digest(spark, path).collect())
    t, start = texts(docs), 0
    assert [r.doc_id for r in got] == sorted(t)
    raw = {r.doc_id: bytes(r.ids) for r in id_files.read(spark, path).collect()}
    for r in got:
        ids = np.array([*library.encode(t[r.doc_id], add_special_tokens=False).ids, 2], "<u4")
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        assert raw[r.doc_id] == ids.tobytes()
        start += len(ids)


def test_files_of_nothing_and_of_null_keys(spark):
    from mlcurate.llm import id_files

    path = id_files.new_path(spark)
    id_files.write(empty(spark), path)
    assert id_files.digest(spark, path).count() == 0
    path = id_files.new_path(spark)
    id_files.write(spark.createDataFrame([(None, "a"), (1, None), (1, "b")], "doc_id long, text string").coalesce(1), path)
    assert [(r.doc_id, r.n_tokens) for r in sorted(id_files.digest(spark, path).collect(), key=lambda r: r.start)] == [(None, 2), (1, 1), (1, 2)]


@pytest.mark.parametrize("n", [0, 1, 2047, 4096, 4097, 9000])
@pytest.mark.parametrize("kind", ["random", "same", "cycle"])
def test_coder_round_trip(n, kind):
    from mlcurate.llm import range_coder as c

    rng = np.random.default_rng(n)
    ids = {"random": rng.integers(0, 49408, n), "same": np.full(n, 49407), "cycle": np.arange(n) % 7}[kind].astype(np.uint16)
    data = c.encode(ids)
    assert (c.decode(data) == ids).all()
    if kind != "random" and n > 2000:
        assert len(data) < n


def test_coder_learns_single_ids_and_contexts():
    """Order 0: few ids in any order take about their entropy; orders 1 and 2: what follows from the ids before takes next to nothing."""
    from mlcurate.llm import range_coder as c

    rng = np.random.default_rng(4)
    few = rng.choice([7, 300, 40_000, 40_001], 16_384, p=[0.7, 0.2, 0.05, 0.05]).astype(np.uint16)
    data = c.encode(few)
    assert (c.decode(data) == few).all() and 8 * len(data) < 2.5 * len(few)  # entropy 1.26 bits
    walk = rng.permutation(3000).astype(np.uint16)
    ids = np.concatenate([walk[a : a + 50] for a in rng.integers(0, 100, 400)])
    data = c.encode(ids)
    assert (c.decode(data) == ids).all() and 8 * len(data) < 2.0 * len(ids)


def test_files_order_ties(spark):
    from mlcurate.llm import id_files

    rows = [(1, "b b"), (1, "a"), (1, None), (None, "z z"), (None, "y")]
    got = []
    for n in (1, 3):
        path = id_files.new_path(spark)
        id_files.write(spark.createDataFrame(rows[::n] if n == 1 else rows[::-1], "doc_id long, text string").repartition(n), path)
        got.append(sorted(tuple(r) for r in id_files.digest(spark, path).select("start", "n_tokens", "ids_crc32").collect()))
    assert got[0] == got[1]


def test_coder_finds_damage():
    from mlcurate.llm import range_coder as c

    data = bytearray(c.encode(np.arange(5000, dtype=np.uint16)))
    data[-100] ^= 1
    with pytest.raises(ValueError):
        c.decode(bytes(data))


def test_length_histogram(spark, docs, library):
    from mlcurate.llm import token_counts as t

    n = sorted(len(library.encode(x, add_special_tokens=False).ids) for x in texts(docs).values())
    sums = t.suffix_sums(t.histogram(t.encoded_lengths(docs)))
    for r in sums.collect():
        assert r.n_docs == n.count(r.n_tokens)
        assert r.docs_from == sum(x >= r.n_tokens for x in n)
        assert r.tokens_from == sum(x for x in n if x >= r.n_tokens)
        assert r.tokens_cut_here == sum(min(x, r.n_tokens) for x in n)
    for r in t.at_limits(sums, [0, 1, 100, 777, 10**6]).collect():
        assert (r.docs_over, r.tokens_total, r.tokens_kept) == (sum(x > r.context for x in n), sum(n), sum(min(x, r.context) for x in n))
    assert t.quantile(sums, 0.5).first()[0] == n[-(-len(n) // 2) - 1]
    assert t.suffix_sums(t.histogram(t.encoded_lengths(empty(spark)))).count() == 0


PII = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), "ip": re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"), "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}


def base_spans(text):
    def luhn(d):
        return sum(x if i % 2 == 0 else x * 2 - 9 * (x > 4) for i, x in enumerate(map(int, d[::-1]))) % 10 == 0

    for kind, p in PII.items():
        for m in p.finditer(text):
            d = re.sub("[^0-9]", "", m[0])
            if {"email": True, "ip": kind == "ip" and all(int(x) <= 255 for x in m[0].split(".")), "card": 13 <= len(d) <= 19 and luhn(d), "phone": 9 <= len(d) <= 15}[kind]:
                yield kind, m.start(), m.end()


def test_pii_base(docs):
    from mlcurate.llm import pii

    t = texts(docs)
    got = {r.doc_id: r for r in pii.digest(docs).collect()}
    assert got.keys() == t.keys()
    for k, text in t.items():
        want = list(base_spans(text))
        said = ",".join(f"{a}:{b}:{c}" for a, b, c in want)
        assert got[k].base_sha256 == hashlib.sha256(said.encode()).hexdigest(), (said, got[k].spans)
        assert [got[k][f"n_{x}"] for x in PII] == [sum(w[0] == x for w in want) for x in PII]
        assert got[k].spans.startswith(said)
    iban = got[10_000 + 19].spans
    assert iban.count("iban:") == 2
    assert "tel:5:19" in got[10_000 + 20].spans


def test_pii_redacts(spark):
    from mlcurate.llm import pii

    df = spark.createDataFrame([(1, "é a@b.cd x 1.2.3.4!"), (2, None), (3, "")], "doc_id long, text string")
    assert [r.text for r in pii.redact(df).sort("doc_id").collect()] == ["é [email] x [ip]!", None, ""]
    assert pii.digest(empty(spark)).count() == 0


def test_licenses(spark, docs):
    from mlcurate.llm import licenses

    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    t = texts(docs)
    got = {r.doc_id: r for r in licenses.scan(docs).collect()}
    assert got.keys() == t.keys()
    for k, text in t.items():
        w = word.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text))
        places = sorted((i, label) for p, label in licenses.PHRASES.items() for i in range(len(w)) if w[i : i + len(p.split())] == p.split())
        r = got[k]
        assert (r.n_words, r.n_base) == (len(w), len(places)), text[:80]
        assert (r.first_word, r.last_word) == ((places[0][0], places[-1][0]) if places else (None, None)), text[:80]
        assert r.base_labels == ",".join(sorted({x for _, x in places}))
        want = {x for _, x in places}
        for i in range(0, max(len(w) - licenses.BLOCK // 2, 1), licenses.BLOCK // 2):
            block = set(w[i : i + licenses.BLOCK])
            want |= {label for label, x in licenses.TEMPLATES if len(block & set(x.split())) >= licenses.THETA * len(set(x.split())) - 1e-9}
        assert r.labels == ",".join(sorted(want)), text[:80]
        assert 0 <= r.score <= 1
    assert "apache" in got[10_025].labels and "mit" in got[10_026].labels
    assert licenses.scan(empty(spark)).count() == 0
    wrapped = ["Redistribution and use in source and binary forms, with or without\nmodification, are permitted", "x " * 40 + "Unless required by applicable law or agreed to in writing, software\n * distributed under the License is distributed on an\n * \"AS IS\" BASIS"]
    got = licenses.scan(spark.createDataFrame(list(enumerate(wrapped)), "doc_id long, text string")).sort("doc_id").collect()
    assert [r.labels for r in got] == ["bsd", "apache"]


def test_gif_digest(spark, docs):
    from mlcurate.llm import gif

    t = texts(docs)
    got = {r.doc_id: r for r in gif.digest(docs).collect()}
    for k, text in t.items():
        raw = text.encode()
        payload = raw + b" " * (max(192, -(-len(raw) // 192) * 192) - len(raw))
        r = got[k]
        assert (r.n_bytes, r.payload_bytes, r.tail_crc32) == (len(raw), len(payload), zlib.crc32(payload[-16:]))
        assert r.payload_sha256 == hashlib.sha256(payload).hexdigest()
        assert (r.media_bytes, r.media_sha256) == (len(gif.store(payload)), hashlib.sha256(gif.store(payload)).hexdigest())
    assert gif.digest(empty(spark)).count() == 0


def _lzw(pixels, least):
    """A full writer with growing codes, for streams that the plain form isn't."""
    table, width, out, held, bits = {bytes([i]): i for i in range(1 << least)}, least + 1, bytearray(), 0, 0
    clear, nxt = 1 << least, (1 << least) + 2

    def put(code):
        nonlocal held, bits
        held |= code << bits
        bits += width
        while bits >= 8:
            out.append(held & 255)
            held >>= 8
            bits -= 8

    put(clear)
    cur = b""
    for p in pixels:
        if cur + bytes([p]) in table:
            cur += bytes([p])
            continue
        put(table[cur])
        if nxt < 4096:
            table[cur + bytes([p])] = nxt
            if nxt == 1 << width and width < 12:
                width += 1
            nxt += 1
        cur = bytes([p])
    put(table[cur])
    put(clear + 1)
    out.append(held & 255)
    return bytes(out)


def test_gif_codes_are_lzw(spark):
    """The stored stream holds dictionary codes and starts its table anew; a long text has several timed frames; repeated rows repeat."""
    from mlcurate.llm import gif

    rng = np.random.default_rng(5)
    text = " ".join(f"w{x}" for x in rng.integers(0, 2000, 90_000))
    media = gif.store(gif.payload_of(text)[1])
    assert len(media) < 0.6 * len(text)
    wide, high, got = gif.parse(media)
    assert (wide, high, len(got)) == (192, 1024, -(-len(gif.payload_of(text)[1]) // (192 * 1024)))
    one = gif.lzw_encode(b"abababababab")
    held, codes, width = int.from_bytes(one, "little"), [], 9
    while not codes or codes[-1] != 257:
        codes.append(held & 511)
        held >>= width
    assert codes[0] == 256 and max(codes) > 257
    back, feature = gif.shown_samples(media)
    assert back == gif.payload_of(text)[1] and feature.startswith(f"{len(got)}:{10 * len(got)}:0+10=")
    for n in (0, 1, 191, 3838, 3839, 3840, 3841, 20_000):
        for high in (2, 256):
            px = rng.integers(0, high, n).astype(np.uint8).tobytes()
            assert gif.lzw_decode(gif.lzw_encode(px), 8, n).tobytes() == px
    rows = [(1, text), (1, text), (2, None), (2, "")]
    a, b, c, d = (tuple(r) for r in sorted(gif.digest(spark.createDataFrame(rows, "doc_id long, text string")).collect()))
    assert a == b and c == d


def test_gif_streams_of_other_writers():
    from mlcurate.llm import gif

    rng = np.random.default_rng(3)
    for least, n in ((2, 50), (4, 3000), (8, 40_000)):
        for high in (2, 1 << least):
            px = rng.integers(0, high, n)
            assert (gif.lzw_decode(_lzw(px.tolist(), least), least, n) == px).all()


def test_gif_disposal_and_transparency(spark):
    import struct

    from mlcurate.llm import gif

    palette = bytes([255, 0, 0, 0, 255, 0, 0, 0, 255, 9, 9, 9])
    data = b"GIF89a" + struct.pack("<HHBBB", 2, 2, 0x81, 0, 0) + palette
    for disposal, clear, px in ((1, None, [0, 0, 0, 0]), (3, 3, [1, 3, 3, 3]), (2, None, [2, 2, 2, 2]), (0, 3, [3, 3, 1, 1])):
        body = _lzw(px, 2)
        data += b"\x21\xf9\x04" + struct.pack("<BHB", disposal << 2 | (clear is not None), 5, clear or 0) + b"\0\x2c" + struct.pack("<HHHHB", 0, 0, 2, 2, 0) + b"\x02" + bytes([len(body)]) + body + b"\0"
    data += b"\x3b"
    r, g, b = (255, 0, 0, 255), (0, 255, 0, 255), (0, 0, 255, 255)
    none = (0, 0, 0, 0)
    got = gif.frames(spark.createDataFrame([(1, bytearray(data)), (2, bytearray(b"GIF")), (3, None)], "media_id long, gif binary")).collect()
    shown = [[tuple(x.rgba[i : i + 4]) for i in range(0, 16, 4)] for x in got if x.id == 1]
    assert shown == [[r] * 4, [g, r, r, r], [b] * 4, [none, none, g, g]]
    assert [x.start_cs for x in got if x.id == 1] == [0, 5, 10, 15]
    assert all(x.error for x in got if x.id != 1) and len(got) == 6
