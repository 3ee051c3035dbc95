"""Archives, pieces and token files: round trips and damage."""

import hashlib
import io
import random
import struct
import zlib

import pytest
import sentencepiece
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st

from xlsql.llm import pieces, token_files, warc


def test_warc_round_trip_with_revisits(spark, tmp_path):
    long = "<p>" + "é" * 700 + "</p>"
    rows = [(1, "http://a", long), (2, None, long), (9, "http://b\n", long), (4, "u", "short"), (5, "u", "short"), (6, "u", None), (7, "u", ""), (None, "u", long), (8, "u", "x" * 999), (10, "u", "x" * 999), (11, "u", "y" * 300_000)]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, digest string").repartition(3)
    got = {r["page_id"]: r for r in warc.warc_round_trip(spark, df).collect()}
    assert len(got) == len(rows)
    for i, _, html in rows:
        body = (html or "").encode()
        r = got[i]
        assert (r["payload_bytes"], r["payload_digest"], r["digest_ok"]) == (len(body), hashlib.sha1(body).hexdigest(), True)
        again = html == long and i != 9
        assert (r["record_type"], r["refers_to"]) == (("revisit", 9) if again else ("response", None))
        assert (r["payload"] is None) if again else (bytes(r["payload"]) == body)


def test_large_and_missing_ids_survive(spark):
    big = (1 << 60) + 1
    page = "x" * 2000
    got = warc.warc_round_trip(spark, spark.createDataFrame([(big, "u", page), (None, "u", page), (1, None, page)], "page_id long, url string, html string").coalesce(1)).collect()
    assert sorted((r["page_id"] or 0, r["refers_to"] or 0) for r in got) == [(0, big), (1, big), (big, 0)]
    docs = spark.createDataFrame([(big, "a b"), (None, "c")], "doc_id long, text string").coalesce(1)
    assert sorted((r["doc_id"] or 0, r["n_tokens"]) for r in token_files.token_counts(docs).collect()) == [(0, 1), (big, 2)]


def test_warc_of_hot_payloads(spark, monkeypatch):
    monkeypatch.setattr(warc, "HOT_ROWS", 3)
    rows = [(i, "u", "h" * 2000 if i % 3 == 0 else "" if i % 3 == 1 else f"{i // 12}" * 1500) for i in range(120)]
    got = {r["page_id"]: r for r in warc.warc_round_trip(spark, spark.createDataFrame(rows, "page_id long, url string, html string").repartition(4)).collect()}
    last = {}
    for i, _, h in rows:
        last[h] = i
    assert len(got) == 120 and all((got[i]["refers_to"], got[i]["record_type"]) == ((last[h], "revisit") if len(h) >= 1000 and last[h] != i else (None, "response")) for i, _, h in rows)


def test_warc_of_an_empty_table(spark):
    assert warc.warc_round_trip(spark, spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_records_are_single_gzip_members():
    raw = b"".join(warc.encode_record("response", {"X-Page-Id": str(i)}, b"body %d" % i * i) for i in range(5))
    inflate = zlib.decompressobj(31)
    inflate.decompress(raw)
    assert inflate.eof and inflate.unused_data
    records = list(warc.read_records(io.BytesIO(raw)))
    assert [r.headers["x-page-id"] for r in records] == list("01234") and all(r.digest_ok for r in records)
    assert records[3].block == b"body 3" * 3 and records[0].offset == 0


def test_damaged_archives_are_noticed():
    one = warc.encode_record("response", {}, b"hello")
    with pytest.raises(warc.WarcError):
        list(warc.read_records(io.BytesIO(one[:-3])))
    with pytest.raises(warc.WarcError):
        list(warc.read_records(io.BytesIO(one + b"junk")))
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    wrong = packer.compress(b"WARC/1.1\r\nContent-Length: 9\r\n\r\nhello\r\n\r\n") + packer.flush()
    with pytest.raises(warc.WarcError):
        list(warc.read_records(io.BytesIO(wrong)))
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    changed = packer.compress(zlib.decompress(one, 31).replace(b"hello", b"jello")) + packer.flush()
    assert [r.digest_ok for r in warc.read_records(io.BytesIO(changed))] == [False]


@pytest.fixture(scope="module")
def encoder():
    return pieces.Encoder(open(pieces.default_model(), "rb").read())


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet=st.one_of(st.sampled_from(" ▁\t\n aé日🙂"), st.characters(blacklist_categories=("Cs",))), max_size=60))
def test_pieces_equal_the_library(text):
    e = pieces.Encoder.__dict__.get("_test") or pieces.Encoder(open(pieces.default_model(), "rb").read())
    pieces.Encoder._test = e
    assert e.encode(text) == e.library.encode(text)
    normal, source = e.normalize(text)
    if text:
        same, places = e.alignment(text)
        assert same == normal and places.tolist() == source
    spans = e.spans(text)
    raw = text.encode()
    assert [s[0] for s in spans] == e.library.encode(text)
    # spans follow one another and cover the text
    assert all(0 <= s[2] <= s[3] <= len(raw) for s in spans)
    assert all(a[2] <= b[2] for a, b in zip(spans, spans[1:]))
    if spans:
        assert spans[-1][3] == len(raw)
    for i, piece, a, b in spans:
        plain = piece.replace("▁", "")
        if plain and not e.is_byte[i] and "▁" not in text:
            assert plain in raw[a:b].decode(errors="ignore")


def test_character_map_takes_the_longest_prefix():
    """A hand-made double array for the rules: a -> x, ab -> yz."""
    units = [0] * 512
    # root at 0 with offset 256: child 'a' at 256 ^ 97; then 'b', each with a leaf holding the replacement's offset
    offset = lambda o: o << 10
    units[0] = offset(256)
    a = 256 ^ ord("a")
    units[a] = ord("a") | (1 << 8) | offset(a ^ 8)
    units[8] = 0x80000000 | 0
    b = 8 ^ ord("b")
    units[b] = ord("b") | (1 << 8) | offset(b ^ 16)
    units[16] = 0x80000000 | 2
    blob = struct.pack("<I", 4 * len(units)) + struct.pack(f"<{len(units)}I", *units) + b"x\0yz\0"
    rules = pieces.CharacterMap(blob)
    assert rules.longest(b"abab", 0) == (2, 2) and rules.replacement(2) == b"yz"
    assert rules.longest(b"ac", 0) == (1, 0) and rules.replacement(0) == b"x"
    assert rules.longest(b"cab", 0) == (0, 0) and rules.longest(b"cab", 1) == (2, 2)
    e = pieces.Encoder(open(pieces.default_model(), "rb").read())
    e.rules = rules
    assert e.normalize("cabé") == ("▁cyzé".encode(), [0, 0, 0, 0, 1, 1, 3, 3, 5])
    # pieces over rewritten text point at what was rewritten
    ids = [e.library.piece_to_id(x) for x in ("▁c", "y", "z", "é")]
    assert list(zip(*(x.tolist() for x in e.span_arrays("cabé", ids)))) == [(0, 1), (1, 3), (1, 3), (3, 5)]
    e.squeeze = True
    assert e.normalize("  c  a ") == ("▁c▁x".encode(), [2, 2, 2, 2, 3, 3, 3, 5, 6])


def mapped_model():
    """The given model with a compiled map for the rules: a -> x, ab -> yz."""
    from sentencepiece import sentencepiece_model_pb2 as model_pb2

    units = [0] * 512
    offset = lambda o: o << 10
    units[0] = offset(256)
    a = 256 ^ ord("a")
    units[a] = ord("a") | (1 << 8) | offset(a ^ 8)
    units[8] = 0x80000000 | 0
    units[8 ^ ord("b")] = ord("b") | (1 << 8) | offset(8 ^ ord("b") ^ 16)
    units[16] = 0x80000000 | 2
    proto = model_pb2.ModelProto()
    proto.ParseFromString(open(pieces.default_model(), "rb").read())
    proto.normalizer_spec.precompiled_charsmap = struct.pack("<I", 4 * len(units)) + struct.pack(f"<{len(units)}I", *units) + b"x\0yz\0"
    return proto


@pytest.mark.parametrize("fallback", [True, False])
def test_pieces_of_a_model_with_a_map_equal_the_library(fallback):
    """Ids and spans with rules of the compiled map, and with one unknown piece in place of bytes."""
    proto = mapped_model()
    if not fallback:
        proto.trainer_spec.byte_fallback = False
        for p in proto.pieces:
            if p.type == pieces.BYTE:
                p.type = 1
                p.piece = "\u2400" + p.piece
    e = pieces.Encoder(proto.SerializeToString())
    assert e.merger is not None
    rng = random.Random(3)
    texts = ["".join(rng.choice("ab abc thing é日🙂 ▁ba") for _ in range(rng.randrange(1, 90))) for _ in range(300)] + ["ab" * 4000, "word " * 3000 + "a"]
    for t, (aligned, ids) in zip(texts, e.encode_batch(texts)):
        told = e.library.encode(t, return_type="proto").pieces
        assert ids.tolist() == [p.id for p in told] == e.encode(t)
        begin, end = e.span_arrays(t, ids, aligned)
        raw = t.encode()
        assert len(begin) == len(told) and (begin <= end).all() and end.max() == len(raw)
        # the library lets pieces within one source character begin or end at its other side
        assert [p.begin for p in told] == begin.tolist() or sum(p.begin != a for p, a in zip(told, begin.tolist())) <= sum(p.begin == p.end or e.is_byte[p.id] for p in told) + t.count("ab")
        wide, places = e.normalize(t)
        assert aligned[0] == wide and aligned[1].tolist() == places


def test_memory_of_words_is_bounded(monkeypatch):
    e = pieces.Encoder(open(pieces.default_model(), "rb").read())
    monkeypatch.setattr(pieces.Encoder, "REMEMBERED", 20)
    rng = random.Random(5)
    texts = [" ".join(f"w{rng.randrange(500)}x" + "y" * (40 * (rng.random() < 0.1)) for _ in range(60)) for _ in range(40)]
    assert [ids.tolist() for _, ids in e.encode_batch(texts)] == [e.library.encode(t) for t in texts]
    assert len(e.place) <= 40


@pytest.mark.parametrize("text", ["\x01the quick", "a\x01the", "x\x00the \x01in", "\x01\x01▁\x01of \x00", "the \x02in"])
def test_control_characters_are_no_space_marks(encoder, text):
    assert encoder.encode(text) == encoder.library.encode(text)
    assert encoder.encode_batch([text, "the"]).__next__()[1].tolist() == encoder.library.encode(text)


def test_new_words_of_many_texts_are_merged_together(monkeypatch):
    e, calls = pieces.Encoder(open(pieces.default_model(), "rb").read()), []
    monkeypatch.setattr(pieces.Encoder, "REMEMBERED", 200)
    monkeypatch.setattr(pieces.Merger, "__call__", lambda self, words, f=pieces.Merger.__call__: calls.append(len(words)) or f(self, words))
    texts = [" ".join(f"t{i}w{k}" for k in range(10)) for i in range(100)]
    assert [ids.tolist() for _, ids in e.encode_batch(texts)] == [e.library.encode(t) for t in texts]
    # 1,000 words in all, at most 200 at a time
    assert len(calls) == 5


def test_registered_query_equals_the_library(spark):
    from xlsql.llm.registry import op4_sentencepiece
    from xlsql.session import load_table

    sf = "/root/testdata/sf0.01"
    lib = sentencepiece.SentencePieceProcessor(model_file=pieces.default_model())
    texts = {r["doc_id"]: r["text"] for r in load_table(spark, sf, "documents").select("doc_id", "text").collect()}
    rows = op4_sentencepiece(spark, sf).collect()
    assert len(rows) == len(texts)
    for r in rows:
        ids = lib.encode(texts[r["doc_id"]] or "")
        assert (r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((lib.decode(ids) if ids else "").encode()).hexdigest())


def test_with_pieces_handles_nulls_and_clashes(spark):
    df = spark.createDataFrame([(1, None, "k"), (2, "", "k"), (3, "héllo  wörld " * 4000, "k"), (3, "a", "k")], "doc_id long, text string, pieces string")
    rows = pieces.with_pieces(df, fields=("ids", "n_tokens", "decoded", "ids_sha256", "decoded_sha256", "spans", "covered_bytes")).collect()
    lib = sentencepiece.SentencePieceProcessor(model_file=pieces.default_model())
    for r in rows:
        p, ids = r["pieces"], lib.encode(r["text"] or "")
        assert (p["ids"], p["n_tokens"], p["decoded"]) == (ids, len(ids), lib.decode(ids) if ids else "")
        assert p["ids_sha256"] == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert len(p["spans"]) == len(ids) and p["covered_bytes"] == len((r["text"] or "").encode())


@pytest.mark.parametrize("block", [1, 2, 3, 7, 1000])
def test_token_counts_over_any_block_size(spark, block):
    import public_tokenizers

    rng = random.Random(block)
    rows = [(i, rng.choice([None, "", "word " * rng.randrange(40), "é日本 x"])) for i in range(60)]
    coder = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=token_files.load_ranks(open(token_files.default_ranks(), "rb").read()), special_tokens={})
    df = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, n_tokens int").repartition(2)
    got = {r["doc_id"]: r["n_tokens"] for r in token_files.token_counts(df, block=block).collect()}
    assert got == {i: len(coder.encode_ordinary(t or "")) for i, t in rows}


def test_scan_of_given_files(spark, tmp_path):
    sep = 50256
    files = {"a": [1, 2, sep, sep, 3, sep], "b": [5, 6, 7], "c": [], "d": [sep], "e": [1] * 10 + [sep] + [2] * 9}
    for k, v in files.items():
        (tmp_path / k).write_bytes(struct.pack(f"<{len(v)}H", *v))
    df = spark.createDataFrame([(str(tmp_path / k),) for k in files], "path string")
    for block in (2, 3, 100):
        rows = token_files.count_tokens(spark, df, f"file://{tmp_path}", sep, block).collect()
        got = {k: [r["n_tokens"] for r in sorted(rows, key=lambda r: r["ordinal"]) if r["path"].endswith("/" + k)] for k in files}
        assert got == {"a": [2, 0, 1], "b": [3], "c": [], "d": [0], "e": [10, 9]}
    (tmp_path / "odd").write_bytes(b"abc")
    with pytest.raises(Exception, match="within a token"):
        token_files.count_tokens(spark, spark.createDataFrame([(str(tmp_path / "odd"),)], "path string"), f"file://{tmp_path}", sep).collect()


def test_token_counts_of_an_empty_table(spark):
    assert token_files.token_counts(spark.createDataFrame([], "doc_id long, text string")).count() == 0
