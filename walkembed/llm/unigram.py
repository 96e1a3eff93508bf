"""SentencePiece encoding and decoding: unigram Viterbi over a double-array trie.

Pieces and scores come from a public model file (a parameter).  Scores of a
unigram model are log probabilities; the file that is given by default ranks its
pieces, so a rank r becomes the Zipf log score -ln(r + 2).  Spaces become the
marker U+2581 and one stands before the text.  A character that no piece covers
falls back to its UTF-8 bytes.

No piece holds a marker behind another character, and none a line feed, so the
best path of a text is the best paths of its segments (markers and the run behind
them; line feeds) end to end.  Distinct segments are solved together, one NumPy
step a byte for all of them, and kept in a bounded cache of the worker.

The trie is a double array (base, check) over bytes: a child of state s for byte
b is base[s] + b, if check there is s.  It is built once on the driver and
broadcast; its size is the vocabulary's.

Defined results: null texts count as empty and have no pieces; every text decodes
to itself; repeated rows repeat; null ids are returned; an empty table gives no
rows; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .workers import keep_cache, take_over

MARKER = "▁"
SEGMENT_CACHE = 500_000
LONG = 200  # bytes; longer segments are solved alone
BYTE_PENALTY = 6.0
_LITERAL = f"{MARKER}\n"  # no segment is like this
_SEGMENT = re.compile(f"\n|{MARKER}*[^{MARKER}\n]+|{MARKER}+")


def default_model() -> str:
    from public_tokenizers import path

    return path("piece_bpe_32k.model")


@dataclass
class Vocabulary:
    """Pieces by id with log scores; ``byte_id[b]`` the piece of byte b."""

    pieces: list[str]
    scores: list[float]
    usable: list[bool]
    byte_id: list[int]
    unknown: int


def load_vocabulary(path: str) -> Vocabulary:
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    n = model.get_piece_size()
    pieces = [model.id_to_piece(i) for i in range(n)]
    scores = [model.get_score(i) for i in range(n)]
    byte_id = [-1] * 256
    for i in range(n):
        if model.is_byte(i):
            byte_id[int(pieces[i][1:-1], 16)] = i
    usable = [not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i)) for i in range(n)]
    ranked = all(float(s).is_integer() for s, u in zip(scores, usable) if u)
    if ranked:
        scores = [-math.log(2 - s) for s in scores]
    return Vocabulary(pieces, scores, usable, byte_id, model.unk_id())


class DoubleArrayTrie:
    """Byte trie of the usable pieces: ``base``, ``check``, and the piece that ends in a state (-1: none)."""

    def __init__(self, vocabulary: Vocabulary):
        children: list[dict[int, int]] = [{}]
        piece = [-1]
        for i, text in enumerate(vocabulary.pieces):
            if not vocabulary.usable[i] or not text:
                continue
            node = 0
            for b in text.encode():
                if b not in children[node]:
                    children[node][b] = len(children)
                    children.append({}), piece.append(-1)
                node = children[node][b]
            if piece[node] < 0 or vocabulary.scores[i] > vocabulary.scores[piece[node]]:
                piece[node] = i
        size = len(children) * 2 + 1024
        base, check, ends = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
        taken = bytearray(size)
        taken[0] = 1
        place = [0] * len(children)
        free, todo = [1, 1], [0]  # where to look next, for nodes of one child and of several
        for node in todo:  # grows breadth first
            keys = sorted(children[node])
            if not keys:
                continue
            many = len(keys) > 1
            at, tries = max(free[many], keys[0]), 0
            while True:
                if at + 600 >= size:
                    base, check, ends = np.concatenate([base, np.zeros(size, np.int32)]), np.concatenate([check, np.full(size, -1, np.int32)]), np.concatenate([ends, np.full(size, -1, np.int32)])
                    taken.extend(bytes(size))
                    size *= 2
                start = at - keys[0]
                if not taken[at] and not any(taken[start + k] for k in keys):
                    break
                at, tries = at + 1, tries + 1
            if tries > 40:  # a dense stretch: later nodes start behind it
                free[many] = at - 8
            base[place[node]] = start
            for k in keys:
                child = children[node][k]
                place[child] = start + k
                taken[start + k] = 1
                check[start + k] = place[node]
                ends[start + k] = piece[child]
                todo.append(child)
        self.base, self.check, self.ends = base, check, ends

    def step(self, states: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Next states for bytes; -1 where there is none."""
        to = self.base[states] + codes
        return np.where((self.check[to] == states) & (to > 0), to, -1)


class UnigramEncoder:
    def __init__(self, vocabulary: Vocabulary, trie: DoubleArrayTrie):
        self.vocabulary, self.trie = vocabulary, trie
        self.scores = np.array(vocabulary.scores)
        low = min((s for s, u in zip(vocabulary.scores, vocabulary.usable) if u), default=-10.0)
        self.byte_score = low - BYTE_PENALTY
        self.byte_id = np.array([b if b >= 0 else vocabulary.unknown for b in vocabulary.byte_id])
        self.cache: dict[str, bytes] = {}

    def solve(self, segments: list[str]) -> list[bytes]:
        """Piece ids (little-endian unsigned 32-bit) of each segment."""
        data = [s.encode() for s in segments]
        out: list[bytes] = [b""] * len(data)
        short: list[int] = []
        for i, d in enumerate(data):
            if len(d) > LONG:
                out[i] = self._solve_one(d)
            else:
                short.append(i)
        short.sort(key=lambda i: len(data[i]))
        for lo in range(0, len(short), 20_000):  # alike in length: few idle steps
            part = short[lo : lo + 20_000]
            for i, ids in zip(part, self._solve_many([data[i] for i in part])):
                out[i] = ids
        return out

    def _solve_many(self, data: list[bytes]) -> list[bytes]:
        n, size = len(data), np.array([len(d) for d in data])
        width = int(size.max(initial=0))
        codes = np.frombuffer(b"".join(d.ljust(width, b"\0") for d in data), dtype=np.uint8).reshape(n, width).astype(np.int32)
        best = np.full((n, width + 1), -np.inf)
        best[:, 0] = 0
        via = np.full((n, width + 1), -1, dtype=np.int32)  # the piece that ends here; -2: bytes of one character
        back = np.zeros((n, width + 1), dtype=np.int32)
        for s in range(width):
            rows = np.flatnonzero((best[:, s] > -np.inf) & (size > s))
            if not len(rows):
                continue
            lead = codes[rows, s]
            span = np.where(lead < 0x80, 1, np.where(lead < 0xE0, 2, np.where(lead < 0xF0, 3, 4)))
            uncovered = np.ones(len(rows), dtype=bool)
            live, state = np.arange(len(rows)), np.zeros(len(rows), dtype=np.int32)
            k = s
            while len(live):
                inside = size[rows[live]] > k
                live, state = live[inside], state[inside]
                if not len(live):
                    break
                state = self.trie.step(state, codes[rows[live], k])
                good = state >= 0
                live, state = live[good], state[good]
                k += 1
                piece = self.trie.ends[state]
                full = piece >= 0
                if full.any():
                    r, p = rows[live[full]], piece[full]
                    uncovered[live[full][span[live[full]] == k - s]] = False
                    value = best[r, s] + self.scores[p]
                    better = value > best[r, k]
                    r, p = r[better], p[better]
                    best[r, k], via[r, k], back[r, k] = value[better], p, s
            if uncovered.any():
                r, to = rows[uncovered], s + span[uncovered]
                value = best[r, s] + self.byte_score * span[uncovered]
                better = value > best[r, to]
                r, to = r[better], to[better]
                best[r, to], via[r, to], back[r, to] = value[better], -2, s
        return [self._trace(d, via[i], back[i]) for i, d in enumerate(data)]

    def _trace(self, data: bytes, via: np.ndarray | list[int], back: np.ndarray | list[int]) -> bytes:
        ids: list[int] = []
        at = len(data)
        while at > 0:
            piece, before = int(via[at]), int(back[at])
            if piece == -2:
                ids.extend(int(self.byte_id[b]) for b in reversed(data[before:at]))
            else:
                ids.append(piece)
            at = before
        return np.array(ids[::-1], dtype="<u4").tobytes()

    def _solve_one(self, data: bytes) -> bytes:
        base, check, ends, scores = self.trie.base, self.trie.check, self.trie.ends, self.scores
        n = len(data)
        best, via, back = [-math.inf] * (n + 1), [-1] * (n + 1), [0] * (n + 1)
        best[0] = 0.0
        for s in range(n):
            if best[s] == -math.inf:
                continue
            lead = data[s]
            span = 1 if lead < 0x80 else 2 if lead < 0xE0 else 3 if lead < 0xF0 else 4
            state, covered = 0, False
            for k in range(s, n):
                to = int(base[state]) + data[k]
                if to <= 0 or check[to] != state:
                    break
                state = to
                piece = int(ends[state])
                if piece >= 0:
                    covered |= k + 1 - s == span
                    value = best[s] + scores[piece]
                    if value > best[k + 1]:
                        best[k + 1], via[k + 1], back[k + 1] = value, piece, s
            if not covered and best[s] + self.byte_score * span > best[s + span]:
                best[s + span], via[s + span], back[s + span] = best[s] + self.byte_score * span, -2, s
        return self._trace(data, via, back)

    def _segments(self, text: str) -> list[str]:
        if not text:
            return []
        if MARKER not in text:
            return _SEGMENT.findall(MARKER + text.replace(" ", MARKER))
        out: list[str] = []  # a marker of the text itself goes by its bytes, so that it comes back
        for k, part in enumerate(text.split(MARKER)):
            out += [_LITERAL] * (k > 0) + _SEGMENT.findall(MARKER * (k == 0) + part.replace(" ", MARKER))
        return out

    def encode(self, texts: list[str]) -> list[bytes]:
        if len(self.cache) > SEGMENT_CACHE:
            self.cache.clear()
        self.cache[_LITERAL] = self.byte_id[list(MARKER.encode())].astype("<u4").tobytes()
        split = [self._segments(t) for t in texts]
        missing = list(set().union(*split) - self.cache.keys())
        self.cache.update(zip(missing, self.solve(missing)))
        get = self.cache.__getitem__
        return [b"".join(map(get, s)) for s in split]


class Decoder:
    """Ids back to text: bytes of byte pieces joined, markers back to spaces, the first one dropped."""

    def __init__(self, vocabulary: Vocabulary):
        byte_of = {i: bytes([b]) for b, i in enumerate(vocabulary.byte_id) if i >= 0}
        self.bytes = [byte_of.get(i, p.replace(MARKER, " ").encode()) for i, p in enumerate(vocabulary.pieces)]

    def decode(self, ids: np.ndarray | list[int]) -> str:
        text = b"".join(map(self.bytes.__getitem__, ids if isinstance(ids, list) else ids.tolist())).decode("utf-8", "replace")
        return text[1:] if text[:1] == " " else text


_encoders: dict[str, UnigramEncoder] = {}


def _worker_encoder(path: str, shared) -> UnigramEncoder:
    take_over("pieces")
    if path not in _encoders:
        _encoders[path] = UnigramEncoder(*shared.value)
    keep_cache("pieces", _encoders.clear)
    return _encoders[path]


def encode_documents(docs: DataFrame, model: str | None = None, emit_ids: bool = False) -> DataFrame:
    """(doc_id, n_pieces, n_byte_pieces, ids_crc32, round_trip) of every text, and its ids if asked for.

    ``round_trip`` says whether decoding the ids gives the text again.
    """
    path = model or default_model()
    vocabulary = load_vocabulary(path)
    shared = docs.sparkSession.sparkContext.broadcast((vocabulary, DoubleArrayTrie(vocabulary)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _worker_encoder(path, shared)
        decoder = Decoder(encoder.vocabulary)
        is_byte = np.zeros(len(encoder.vocabulary.pieces), dtype=bool)
        is_byte[[i for i in encoder.vocabulary.byte_id if i >= 0]] = True
        for batch in batches:
            for lo in range(0, len(batch), 256):
                part = batch.slice(lo, 256)
                texts = [t or "" for t in part.column("text").to_pylist()]
                rows = [np.frombuffer(b, dtype="<u4") for b in encoder.encode(texts)]
                columns = [
                    part.column("doc_id"), pa.array([len(r) for r in rows], pa.int64()), pa.array([int(is_byte[r].sum()) for r in rows], pa.int64()),
                    pa.array([zlib.crc32(r.tobytes()) for r in rows], pa.int64()), pa.array([decoder.decode(r) == t for r, t in zip(rows, texts)], pa.bool_()),
                ]
                names = ["doc_id", "n_pieces", "n_byte_pieces", "ids_crc32", "round_trip"]
                if emit_ids:
                    columns.append(pa.array([r.astype(np.int32) for r in rows], pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)

    schema = "doc_id long, n_pieces long, n_byte_pieces long, ids_crc32 long, round_trip boolean" + ", ids array<int>" * emit_ids
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, schema)


def decode_documents(encoded: DataFrame, model: str | None = None) -> DataFrame:
    """(doc_id, text) from (doc_id, ids)."""
    shared = encoded.sparkSession.sparkContext.broadcast(Decoder(load_vocabulary(model or default_model())))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [None if ids is None else shared.value.decode(ids) for ids in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select(F.col("doc_id").cast("long").alias("doc_id"), "ids").mapInArrow(run, "doc_id long, text string")
