"""Offset-preserving SentencePiece encoding and decoding.

The model file is read with a small wire-format reader: pieces, scores, types
and the normaliser's settings. Normalising walks the text once; at each place
the compiled character map (a double-array trie with a table of replacements)
gives the longest matching prefix, and every output byte records the original
byte it came from, so each piece projects to a byte span of the original text.

No piece of the vocabulary holds a space mark after another character (checked
on loading), so merges never cross from a word into the next space. The
normalised text therefore falls into chunks (space marks, then other
characters) that are merged one by one and remembered in a bounded cache; the
result equals merging the whole text at once. Memory is linear in one text.

Defined cases: a null text is an empty text, which encodes to the begin and end
ids only; characters outside the vocabulary become byte pieces; repeated rows
give equal results; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import heapq
import re
import struct
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.plans.session import ship_package
from annspark.sources.tables import table

SPACE = "▁"
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
#: The cache has two generations of at most so many chunks; long chunks aren't kept.
CACHE_ENTRIES, CACHE_CHARS = 100_000, 64
MODEL = "piece_bpe_32k.model"
#: Places between a letter and an ASCII mark, digit or control character.
_CUT = re.compile(r"(?<=[^\W\d_²³¹])(?=[\x00-\x1f!-@\[-`{-~])|(?<=[\x00-\x1f!-@\[-`{-~])(?=[^\W\d_²³¹])")


def default_model_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(MODEL)


def _fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(field number, value) pairs of one protobuf message."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            byte = data[at]
            at += 1
            value |= (byte & 127) << shift
            if byte < 128:
                return value
            shift += 7

    while at < len(data):
        tag = varint()
        kind = tag & 7
        if kind == 0:
            value: int | bytes = varint()
        elif kind == 2:
            n = varint()
            value = data[at : at + n]
            at += n
        else:
            n = {1: 8, 5: 4}[kind]
            value = data[at : at + n]
            at += n
        yield tag >> 3, value


class CharMap:
    """The compiled character map: longest-prefix lookup in a double array."""

    def __init__(self, blob: bytes):
        n = struct.unpack_from("<I", blob)[0] if blob else 0
        self.units = struct.unpack_from(f"<{n // 4}I", blob, 4) if blob else ()
        self.texts = blob[4 + n :] if blob else b""

    def longest(self, data: bytes, at: int) -> tuple[int, bytes] | None:
        """(bytes matched, replacement) of the longest entry that starts at ``at``."""
        units, found = self.units, None
        if not units:
            return None
        offset = lambda u: (u >> 10) << ((u & (1 << 9)) >> 6)
        node = offset(units[0])
        for i in range(at, len(data)):
            node ^= data[i]
            unit = units[node]
            if unit & ((1 << 31) | 0xFF) != data[i]:
                break
            node ^= offset(unit)
            if (unit >> 8) & 1:
                found = (i + 1 - at, units[node] & 0x7FFFFFFF)
        if not found:
            return None
        end = self.texts.index(b"\0", found[1])
        return found[0], self.texts[found[1] : end]


class Codec:
    """Encoder and decoder of one BPE model file."""

    def __init__(self, path: str):
        with open(path, "rb") as f:
            model = f.read()
        self.pieces: list[str] = []
        scores: list[float] = []
        kinds: list[int] = []
        norm: dict[int, int | bytes] = {}
        for number, value in _fields(model):
            if number == 1:
                fields = dict(_fields(value))
                self.pieces.append(fields.get(1, b"").decode("utf-8"))
                scores.append(struct.unpack("<f", fields.get(2, bytes(4)))[0])
                kinds.append(fields.get(3, NORMAL))
            elif number == 2 and dict(_fields(value)).get(3, 1) != 2:
                raise ValueError("only BPE models are supported")
            elif number == 3:
                norm = dict(_fields(value))
        if USER_DEFINED in kinds or UNUSED in kinds:
            raise ValueError("models with user-defined or unused pieces aren't supported")
        self.char_map = CharMap(norm.get(2, b""))
        self.dummy_prefix = bool(norm.get(3, 1))
        self.strip_spaces = bool(norm.get(4, 1))
        self.escape_spaces = bool(norm.get(5, 1))
        self.kinds = kinds
        self.normal = {p: i for i, (p, k) in enumerate(zip(self.pieces, kinds)) if k == NORMAL}
        order = {s: r for r, s in enumerate(sorted({scores[i] for i in self.normal.values()}, reverse=True))}
        #: Merging order of each piece: equal scores share a rank, and the leftmost goes first.
        self.rank = {p: order[scores[i]] for p, i in self.normal.items()}
        if any(SPACE in p.lstrip(SPACE) for p in self.rank):
            raise ValueError("a piece crosses from a word into a space")
        #: Whether letters and ASCII marks never share a piece; merges then don't cross from one to the other.
        self.cuts = not any(_CUT.search(p) for p in self.rank)
        self.reserved = {p: i for i, (p, k) in enumerate(zip(self.pieces, kinds)) if k in (CONTROL, UNKNOWN, BYTE)}
        self.unknown = kinds.index(UNKNOWN)
        self.bos, self.eos = self.reserved.get("<s>", -1), self.reserved.get("</s>", -1)
        self.byte_ids = [self.reserved.get(f"<0x{b:02X}>", self.unknown) for b in range(256)]
        self.has_bytes = BYTE in kinds
        self.plain = [
            b"" if k == CONTROL else bytes([int(p[3:5], 16)]) if k == BYTE else " ⁇ ".encode() if k == UNKNOWN else p.replace(SPACE, " ").encode()
            for p, k in zip(self.pieces, kinds)
        ]
        self.is_byte = np.array([k == BYTE for k in kinds])
        self.identity = not self.char_map.units and not self.strip_spaces and self.escape_spaces
        #: Words that follow one space: (id, original byte length) of their pieces, in two generations.
        self.words: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        #: Chunks of texts that the quick way doesn't fit.
        self.chunks: dict[str, list[int]] = {}

    # -- normalising ---------------------------------------------------------

    def normalise(self, text: str) -> tuple[str, np.ndarray]:
        """The normalised text and, for each of its bytes and its end, the original byte offset."""
        data = text.encode("utf-8")
        out, source = bytearray(), []
        at = 0
        mark = SPACE.encode() if self.escape_spaces else b" "
        held = self.strip_spaces  # true: a space here is leading or repeated
        if data and self.dummy_prefix:
            out += mark
            source += [0] * len(mark)
        while at < len(data):
            hit = self.char_map.longest(data, at)
            if hit:
                used, new = hit
            else:
                lead = data[at]
                used = 1 if lead < 128 else 2 if lead < 224 else 3 if lead < 240 else 4
                new = data[at : at + used]
            for ch in new.decode("utf-8"):
                if ch == " ":
                    if not (held and self.strip_spaces):
                        out += mark
                        source += [at] * len(mark)
                    held = True
                else:
                    raw = ch.encode("utf-8")
                    # an unchanged character keeps its own bytes' places
                    source += range(at, at + used) if not hit else [at] * len(raw)
                    out += raw
                    held = False
            at += used
        if self.strip_spaces:
            while out.endswith(mark):
                del out[-len(mark) :]
                del source[-len(mark) :]
        return out.decode("utf-8"), np.array([*source, len(data)], np.int64)

    # -- merging -------------------------------------------------------------

    def merge(self, chunk: str) -> list[str]:
        """The BPE pieces of one chunk: best score first, then leftmost."""
        if len(chunk) > CACHE_CHARS:
            return self._merge_long(chunk)
        rank, none = self.rank.get, len(self.pieces)
        parts = list(chunk)
        ranks = [rank(a + b, none) for a, b in zip(parts, parts[1:])]
        while ranks:
            best = min(ranks)
            if best == none:
                break
            i = ranks.index(best)
            new = parts[i] = parts[i] + parts.pop(i + 1)
            del ranks[i]
            if i:
                ranks[i - 1] = rank(parts[i - 1] + new, none)
            if i < len(ranks):
                ranks[i] = rank(new + parts[i + 1], none)
        return parts

    def _merge_long(self, chunk: str) -> list[str]:
        """The same through a heap and linked places, for long chunks."""
        rank = self.rank
        parts: list[str] = list(chunk)
        n = len(parts)
        left, right = list(range(-1, n - 1)), [*range(1, n), -1]
        heap = []

        def offer(i: int, j: int) -> None:
            if (r := rank.get(parts[i] + parts[j])) is not None:
                heapq.heappush(heap, (r, i, j, len(parts[i]) + len(parts[j])))

        for i in range(n - 1):
            offer(i, i + 1)
        while heap:
            _, i, j, size = heapq.heappop(heap)
            if not parts[i] or not parts[j] or right[i] != j or len(parts[i]) + len(parts[j]) != size:
                continue
            parts[i] += parts[j]
            parts[j] = ""
            right[i] = right[j]
            if right[j] >= 0:
                left[right[j]] = i
            if left[i] >= 0:
                offer(left[i], i)
            if right[i] >= 0:
                offer(i, right[i])
        return [p for p in parts if p]

    def chunk(self, chunk: str) -> list[int]:
        """id and normalised byte length of each piece of one chunk, in turn."""
        pairs: list[int] = []
        for piece in self.merge(chunk):
            known = self.normal.get(piece)
            raw = piece.encode("utf-8")
            if known is not None:
                pairs += (known, len(raw))
            elif self.has_bytes:
                for b in raw:
                    pairs += (self.byte_ids[b], 1)
            elif pairs and pairs[-2] == self.unknown:
                pairs[-1] += len(raw)
            else:
                pairs += (self.unknown, len(raw))
        return pairs

    def word(self, word: str) -> bytes:
        """id and original byte length of each piece of a space and a word, as packed unsigned 32-bit integers.

        Marks around letters are merged apart from them, so that a word is one
        entry whatever stands after it.
        """
        got = self.older.get(word)
        if got is None:
            parts = _CUT.split(word) if self.cuts and not word.isalpha() else [word]
            if len(parts) > 1:
                got = (self.words.get(parts[0]) or self.word(parts[0])) + b"".join(map(self._part, parts[1:]))
            else:
                pairs = self.chunk(SPACE + word)
                pairs[1] -= 2  # the mark's three bytes stand for a space
                got = struct.pack(f"<{len(pairs)}I", *pairs)
        if len(word) <= CACHE_CHARS:
            if len(self.words) >= CACHE_ENTRIES:
                self.older, self.words = self.words, {}
            self.words[word] = got
        return got

    def _part(self, part: str) -> bytes:
        """The same for a part that follows no space."""
        pairs = self.chunks.get(part)
        if pairs is None:
            pairs = self.chunk(part)
            if len(part) <= CACHE_CHARS and len(self.chunks) <= CACHE_ENTRIES // 4:
                self.chunks[part] = pairs
        return struct.pack(f"<{len(pairs)}I", *pairs)

    _chunks = re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+").findall

    def encode(self, text: str | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """ids with begin and end ids, and the original byte start and end of each piece.

        The begin and end ids have the empty spans at the text's ends.
        """
        text = text or ""
        if self.identity and self.dummy_prefix and text and SPACE not in text and "  " not in text and text[0] != " " and text[-1] != " ":
            # Words between single spaces: each is a chunk, the first one's space being the prefix.
            words = text.split(" ")
            packed = list(map(self.words.get, words))
            if None in packed:
                own = self.word
                packed = [got if got is not None else own(w) for got, w in zip(packed, words)]
            pairs = np.frombuffer(b"".join(packed), "<u4").reshape(-1, 2)
            ids, stops = pairs[:, 0], np.cumsum(pairs[:, 1], dtype=np.int64) - 1
        else:
            if self.identity:
                normal = text.replace(" ", SPACE)
                normal = SPACE + normal if text and self.dummy_prefix else normal
            else:
                normal, source = self.normalise(text)
            if len(self.chunks) > CACHE_ENTRIES // 4:
                self.chunks.clear()
            memo, own = self.chunks, self.chunk
            packed = [memo.get(c) or (memo.setdefault(c, own(c)) if len(c) <= CACHE_CHARS else own(c)) for c in self._chunks(normal)]
            pairs = np.array([n for p in packed for n in p], "<u4").reshape(-1, 2)
            ids, ends = pairs[:, 0], np.cumsum(pairs[:, 1], dtype=np.int64)
            stops = self._identity_source(text, normal, ends) if self.identity else source[ends]
        total = int(stops[-1]) if len(stops) else 0
        starts = np.concatenate([[0, 0], stops[:-1], [total]]) if len(stops) else np.zeros(2, np.int64)
        stops = np.concatenate([[0], stops, [total]]) if len(stops) else np.zeros(2, np.int64)
        return np.concatenate([[self.bos], ids, [self.eos]]).astype("<u4"), starts, stops

    def _identity_source(self, text: str, normal: str, ends: np.ndarray) -> np.ndarray:
        """Original byte offsets of normalised ``ends`` where only spaces and the prefix changed."""
        if not len(ends):
            return ends
        raw = np.frombuffer(normal.encode("utf-8"), np.uint8)
        width = np.ones(len(raw), np.int8)
        # A mark takes three bytes, of which a space has one and the prefix none.
        marks = np.flatnonzero((raw[:-2] == 0xE2) & (raw[1:-1] == 0x96) & (raw[2:] == 0x81)) if len(raw) > 2 else np.empty(0, np.int64)
        if SPACE in text:
            chars = np.array([ch == SPACE for ch in text if ch in (" ", SPACE)], bool)
            body = marks[1:] if self.dummy_prefix else marks
            spaces = body[~chars]
        else:
            spaces = marks[1:] if self.dummy_prefix else marks
        width[spaces + 1] = 0
        width[spaces + 2] = 0
        if self.dummy_prefix:
            width[:3] = 0
        return np.cumsum(width, dtype=np.int64)[ends - 1]

    # -- decoding ------------------------------------------------------------

    def decode(self, ids: np.ndarray) -> str:
        """The text of ``ids``: byte pieces joined, ill-formed bytes replaced, one leading prefix dropped."""
        plain = self.plain
        if not len(ids):
            return ""
        parts = list(map(plain.__getitem__, ids.tolist()))
        flags = self.is_byte[ids]
        if flags.any():
            # Each run of byte pieces is decoded by itself, an ill-formed byte as one replacement.
            edges = np.flatnonzero(np.diff(np.concatenate([[0], flags.view(np.int8), [0]])))
            for s, e in zip(edges[::2].tolist(), edges[1::2].tolist()):
                run = b"".join(parts[s:e])
                parts[s:e] = [_utf8_or_marks(run)] + [b""] * (e - s - 1)
        if self.dummy_prefix or self.strip_spaces:
            for i, part in enumerate(parts):
                if self.kinds[int(ids[i])] == CONTROL:
                    continue
                if self.kinds[int(ids[i])] == NORMAL and part.startswith(b" "):
                    parts[i] = part.lstrip(b" ") if self.strip_spaces else part[1:]
                break
        return b"".join(parts).decode("utf-8")


def _utf8_or_marks(run: bytes) -> bytes:
    try:
        run.decode("utf-8")
        return run
    except UnicodeDecodeError:
        pass
    out, at = bytearray(), 0
    while at < len(run):
        for n in (1, 2, 3, 4):
            piece = run[at : at + n]
            try:
                piece.decode("utf-8")
            except UnicodeDecodeError:
                continue
            if len(piece) == n:
                out += piece
                at += n
                break
        else:
            out += "�".encode()
            at += 1
    return bytes(out)


@lru_cache(maxsize=4)
def codec(path: str) -> Codec:
    return Codec(path)


def encode_spans(df: DataFrame, text: str = "text", model_path: str | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """``keep`` columns, ids, and starts and ends: byte spans in the original text, and decoded text."""
    ship_package(df.sparkSession)
    path = model_path or default_model_path()
    frame = df.select(*keep, F.coalesce(F.col(text).cast("string"), F.lit("")).alias("_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            rows = [c.encode(t.as_py()) for t in batch.column(len(keep))]
            yield pa.RecordBatch.from_arrays(
                [
                    *batch.columns[: len(keep)],
                    pa.array([r[0].astype(np.int32) for r in rows], pa.list_(pa.int32())),
                    pa.array([r[1] for r in rows], pa.list_(pa.int64())),
                    pa.array([r[2] for r in rows], pa.list_(pa.int64())),
                    pa.array([c.decode(r[0]) for r in rows], pa.string()),
                ],
                [*keep, "ids", "starts", "ends", "decoded"],
            )

    kept = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in frame.schema.fields[:-1])
    return frame.mapInArrow(run, (kept + ", " if kept else "") + "ids array<int>, starts array<long>, ends array<long>, decoded string")


def encode_digests(df: DataFrame, model_path: str | None = None, with_ids: bool = False) -> DataFrame:
    """doc_id with digests of the ids, the decoded text and the pieces' byte spans, made beside the encoder.

    spans_sha256 is over each piece's start and end in the text's bytes, as
    little-endian signed 64-bit integers; span_bytes is the last end, the text's
    own length. ``with_ids`` adds the ids themselves.
    """
    ship_package(df.sparkSession)
    path = model_path or default_model_path()
    names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "spans_sha256", "span_bytes"] + ["ids"] * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            n, ids_hex, text_hex, span_hex, size, all_ids = [], [], [], [], [], []
            for t in batch.column(1):
                ids, starts, ends = c.encode(t.as_py())
                n.append(len(ids))
                ids_hex.append(hashlib.sha256(ids.tobytes()).hexdigest())
                text_hex.append(hashlib.sha256(c.decode(ids).encode("utf-8")).hexdigest())
                span_hex.append(hashlib.sha256(np.stack([starts, ends], axis=1).astype("<i8").tobytes()).hexdigest())
                size.append(int(ends[-1]))
                if with_ids:
                    all_ids.append(ids.astype(np.int32))
            columns = [batch.column(0), pa.array(n, pa.int64()), *(pa.array(x, pa.string()) for x in (ids_hex, text_hex, span_hex)), pa.array(size, pa.int64())]
            yield pa.RecordBatch.from_arrays([*columns, *([pa.array(all_ids, pa.list_(pa.int32()))] if with_ids else [])], names)
        c.older = {}  # the worker may go on to other stages

    frame = df.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    kinds = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, spans_sha256 string, span_bytes long"
    return frame.mapInArrow(run, kinds + (", ids array<int>" if with_ids else ""))


def op8_sentencepiece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: doc_id, n_tokens, ids_sha256, decoded_sha256; with the digest of all byte spans and the last byte."""
    return encode_digests(table(spark, sf_dir, "documents"))
