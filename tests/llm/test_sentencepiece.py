import hashlib
import random
import struct

import numpy as np
import pytest
import sentencepiece

from annspark.llm import sentencepiece_codec as S

PARTS = list("abc  \n\t▁éß日本😀́\x00ﬁ019.,ABthe") + ["<s>", "</s>", "<unk>", "<0x41>", "  ", "hello ", "the ", "x" * 90]


@pytest.fixture(scope="module")
def both():
    path = S.default_model_path()
    return S.codec(path), sentencepiece.SentencePieceProcessor(model_file=path)


def test_equals_the_library(both):
    mine, lib = both
    rng = random.Random(5)
    for _ in range(4000):
        t = "".join(rng.choice(PARTS) for _ in range(rng.randint(0, 30)))
        ids, starts, ends = mine.encode(t)
        assert ids.tolist() == lib.encode(t, add_bos=True, add_eos=True) and mine.decode(ids) == lib.decode(ids.tolist())
        assert (starts[1:] == ends[:-1]).all() and ends[-1] == len(t.encode())


def test_any_ids_decode_like_the_library(both):
    mine, lib = both
    rng = random.Random(6)
    for _ in range(3000):
        ids = [rng.randrange(0, 400) if rng.random() < 0.5 else rng.randrange(32000) for _ in range(rng.randint(0, 8))]
        assert mine.decode(np.array(ids, "<u4")) == lib.decode(ids)


def test_spans_cover_the_pieces(both):
    mine, _ = both
    t = "Zwölf Boxkämpfer▁ jagen 日本 😀"
    ids, starts, ends = mine.encode(t)
    raw = t.encode()
    for i, s, e in zip(ids[1:-1].tolist(), starts[1:-1], ends[1:-1]):
        piece = mine.pieces[i]
        if mine.kinds[i] == S.NORMAL:
            assert raw[s:e].decode().replace(" ", S.SPACE) in (piece, piece[1:])
        else:
            assert raw[s:e] == bytes([int(piece[3:5], 16)])


def test_long_chunks_merge_alike(both):
    mine, _ = both
    rng = random.Random(8)
    for n in (65, 200, 3000):
        chunk = "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(n))
        limit, S.CACHE_CHARS = S.CACHE_CHARS, 10**9
        try:
            short = mine.merge(chunk)
        finally:
            S.CACHE_CHARS = limit
        assert mine._merge_long(chunk) == short


def character_map(entries):
    """A compiled map of (bytes, replacement) entries: each node's children lie in a block of their own."""
    units, blocks, texts = [0] * 256 * 64, 1, b""
    units[0] = 256 << 10
    at = {b"": (0, 256)}
    for key, value in entries:
        for i in range(len(key)):
            part = key[: i + 1]
            if part not in at:
                _, base = at[part[:-1]]
                place = base ^ part[-1]
                blocks += 1
                units[place] = part[-1] | ((place ^ (blocks * 256)) << 10)
                at[part] = (place, blocks * 256)
        place, base = at[key]
        units[place] |= 1 << 8
        units[base] = (1 << 31) | len(texts)
        texts += value + b"\0"
    return struct.pack(f"<I{len(units)}I", 4 * len(units), *units) + texts


def test_character_map_aligns_to_the_source(both):
    mine, _ = both
    c = S.Codec(S.default_model_path())
    c.char_map = S.CharMap(character_map([("ﬁ".encode(), b"fi"), ("ﬁx".encode(), b"FX"), ("Ａ".encode(), b"A"), (b"\t", b" ")]))
    c.identity = False
    assert c.char_map.longest("ﬁxy".encode(), 0) == (4, b"FX") and c.char_map.longest("ﬁy".encode(), 0) == (3, b"fi") and c.char_map.longest(b"zz", 0) is None
    text = "ﬁne Ａ\tﬁx é"
    normal, source = c.normalise(text)
    assert normal == "▁fine▁A▁FX▁é" and source[-1] == len(text.encode()) and (np.diff(source) >= 0).all()
    ids, starts, ends = c.encode(text)
    assert c.decode(ids) == "fine A FX é" and ids.tolist() == mine.encode("fine A FX é")[0].tolist() and ends[-1] == len(text.encode())
    c.strip_spaces = True
    assert c.normalise("  a   b  ")[0] == "▁a▁b"


def test_query_and_edges(spark, edge, empty, folder_of, both):
    mine, lib = both
    rows = S.op8_sentencepiece_codec(spark, folder_of("documents", edge)).collect()
    texts = {r.doc_id: r.text or "" for r in edge.collect()}
    assert len(rows) == 10
    for r in rows:
        ids = lib.encode(texts[r.doc_id], add_bos=True, add_eos=True)
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(lib.decode(ids).encode()).hexdigest())
        *_, starts, ends = mine.encode(texts[r.doc_id])
        pairs = [x for p in zip(starts.tolist(), ends.tolist()) for x in p]
        assert r.spans_sha256 == hashlib.sha256(struct.pack(f"<{len(pairs)}q", *pairs)).hexdigest() and r.span_bytes == len(texts[r.doc_id].encode())
    assert S.encode_digests(empty).count() == 0 and S.encode_digests(empty, with_ids=True).columns[-1] == "ids"
    assert {r.doc_id: r.ids for r in S.encode_digests(edge, with_ids=True).collect()}[6] == lib.encode("two words", add_bos=True, add_eos=True)
    full = S.encode_spans(edge, keep=("doc_id",)).where("doc_id = 6").first()
    assert full.decoded == "two words" and full.ends[-1] == 9 and len(full.ids) == len(full.starts)
