"""SentencePiece encoding and decoding by a streaming Viterbi search over a public vocabulary.

The text is normalised as the vocabulary's model says (identity, a leading blank, blanks written as U+2581) and
cut into the pieces with the greatest sum of scores; what no piece covers falls back to byte pieces, so every
text can be decoded. The search keeps best scores and back pointers only for a window of the longest piece, and
commits ids whenever the back pointer paths of all surviving boundaries run through one boundary.

A document goes through one search, as a stream of parts. Where no piece of the vocabulary runs over the end of a word,
all paths run through every word end, so the search commits there, and a stretch between two commits that it has met
before is answered from memory. A stretch longer than a part is searched as it arrives, in the window alone.

The vocabulary comes from a byte-pair model: its scores are merge ranks. They are read as a Zipf law, the score of
rank r being -ln(r + 3), and a byte piece scores below any other. Ids are thus those of the best segmentation
under these scores, not the merges that the model's own library would make; decoding is the library's.

Defined results: a null counts as empty and gives no ids; a U+2581 in a text decodes to a blank, as in the
library; repeated rows are encoded each; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
import math
import re
from array import array
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

BLANK = "▁"
#: What lies between two word ends: blanks and a word, or blanks at the end.
_STRETCH = re.compile(f"{BLANK}*[^{BLANK}]+|{BLANK}+")
#: Characters of a part in which a document is handed to the search.
PART = 1 << 14
_loaded: dict[str, Vocabulary] = {}


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class Vocabulary:
    """Pieces with scores, a trie of them, and the byte pieces. A byte piece must score below every other."""

    def __init__(self, pieces: dict[str, tuple[int, float]], byte_ids: list[int], byte_score: float) -> None:
        self.pieces, self.byte_ids, self.byte_score = pieces, byte_ids, byte_score
        self.longest = max(map(len, pieces), default=1)
        self.single = {p for p in pieces if len(p) == 1}
        #: Children by character; under the empty string the (id, score) of the piece that ends there.
        self.trie: dict = {}
        for p, hit in pieces.items():
            node = self.trie
            for c in p:
                node = node.setdefault(c, {})
            node[""] = hit
        self.spelling = {i: p.replace(BLANK, " ").encode() for p, (i, _) in pieces.items()} | {i: bytes([b]) for b, i in enumerate(byte_ids)}
        #: No piece runs over the end of a word, so every word end is a boundary on all paths.
        self.words_stand_alone = not any(a != BLANK and b == BLANK for p in pieces for a, b in zip(p, p[1:], strict=False))

    @staticmethod
    def load(path: str) -> Vocabulary:
        if path not in _loaded:
            import sentencepiece

            model = sentencepiece.SentencePieceProcessor(model_file=path)
            n = model.get_piece_size()
            byte_ids = [model.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
            plain = [i for i in range(n) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
            ranked = sorted(plain, key=lambda i: (-model.get_score(i), i))
            pieces = {model.id_to_piece(i): (i, -math.log(r + 3.0)) for r, i in enumerate(ranked)}
            _loaded[path] = Vocabulary(pieces, byte_ids, -math.log(n + 3.0) - 10.0)
        return _loaded[path]


class _Open:
    """The parts of a stretch whose end has not arrived; ``rest`` is what follows the end."""

    def __init__(self, held: str, parts: Iterator[str], to_word_end: bool) -> None:
        self.held, self.parts, self.to_word_end, self.rest, self.ended = held, parts, to_word_end, "", False

    def __iter__(self) -> Iterator[str]:
        yield self.held
        before = self.held[-1:]
        for part in self.parts:
            at = next((i for i, c in enumerate(part) if c == BLANK and (part[i - 1] if i else before) != BLANK), -1) if self.to_word_end else -1
            if at >= 0:
                self.rest = part[at:]
                if at:
                    yield part[:at]
                return
            if part:
                before = part[-1]
                yield part
        self.ended = True


class StreamingViterbi:
    """Best segmentation of a stream of text, in memory bounded by the longest piece and the open stretch.

    Boundaries are taken in order; the pieces that begin at one are followed along a trie, so scores are kept only for
    the boundaries that a piece from behind has reached, at most the longest piece ahead. These are the survivors; once
    the open stretch is some pieces long, their back pointers are walked to the boundary that all share, and what lies
    before it is committed. Ties go to the longer last piece. ``peak`` is the longest open stretch so far.
    """

    def __init__(self, vocabulary: Vocabulary, check: int | None = None) -> None:
        self.v, self.check, self.peak = vocabulary, check or 2 * vocabulary.longest, 0
        #: Commits at word ends, and inside a stretch.
        self.commits, self.early = 0, 0

    def document(self, stream: Iterable[str], known: dict[str, bytes] | None = None, most: int = 200_000, part: int = 1 << 14) -> Iterator[bytes]:
        """Packed ids of a text (blanks written as U+2581) given in parts, each yielded when it is committed."""
        known = {} if known is None else known
        parts, held, ended = iter(stream), "", False
        while held or not ended:
            while not ended and len(held) < part:
                more = next(parts, None)
                ended = more is None
                held += more or ""
            stretches = _STRETCH.findall(held) if self.v.words_stand_alone else [held]
            closed = stretches if ended else stretches[:-1]
            for stretch in closed:
                ids = known.get(stretch)
                if ids is None:
                    ids = b"".join(self._search((stretch,)))
                    if len(stretch) <= 64:
                        if len(known) >= most:
                            known.clear()
                        known[stretch] = ids
                yield ids
            self.commits += len(closed)
            if ended:
                return
            if closed:
                held = stretches[-1]
                continue
            open_ = _Open(held, parts, self.v.words_stand_alone)
            yield from self._search(open_)
            self.commits += 1
            held, ended = open_.rest, open_.ended

    def _search(self, stream: Iterable[str]) -> Iterator[bytes]:
        for k, ids in enumerate(self.encode(stream)):
            self.early += k > 0
            yield array("i", ids).tobytes()

    def encode(self, stream: Iterable[str]) -> Iterator[list[int]]:
        """Lists of ids, each yielded as soon as it is certain. ``stream`` gives the text in parts of any size."""
        parts, ended = iter(stream), False
        trie, longest, byte_score, low = self.v.trie, self.v.longest, self.v.byte_score, float("-inf")
        text, at = "", 0  # the open stretch, and the boundary whose pieces come next
        score, back, ids = [0.0], [-1], [-1]  # of each boundary reached: best score, boundary before it, last piece
        while True:
            while not ended and len(text) < at + longest:
                part = next(parts, None)
                ended = part is None
                text += part or ""
            end = len(text)
            if at == end:
                break
            own, node, j = score[at], trie, at
            while j < end:
                node = node.get(text[j])
                if node is None:
                    break
                j += 1
                if j == len(score):
                    score.append(low)
                    back.append(-1)
                    ids.append(-1)
                hit = node.get("")
                if hit is not None and own + hit[1] > score[j]:
                    score[j], back[j], ids[j] = own + hit[1], at, hit[0]
            if at + 1 == len(score):
                score.append(low)
                back.append(-1)
                ids.append(-1)
            if text[at] not in self.v.single and (s := own + byte_score * len(text[at].encode())) > score[at + 1]:
                score[at + 1], back[at + 1], ids[at + 1] = s, at, -1
            at += 1
            if at >= self.check and at % longest == 0:
                self.peak = max(self.peak, len(score))
                meeting = self._meeting(at, score, back)
                if meeting:
                    yield self._ids(text, back, ids, meeting)
                    floor, at = score[meeting], at - meeting
                    text, ids = text[meeting:], ids[meeting:]
                    score = [s - floor for s in score[meeting:]]
                    back = [b - meeting for b in back[meeting:]]
        self.peak = max(self.peak, len(score))
        if text:
            yield self._ids(text, back, ids, len(text))

    @staticmethod
    def _meeting(at: int, score: list[float], back: list[int]) -> int:
        """The last boundary that the best paths of all survivors run through; 0 if only the start."""
        spots = {b for b in range(at, len(score)) if score[b] > float("-inf")}
        while len(spots) > 1:  # walk the furthest path back until all stand on one boundary
            far = max(spots)
            spots.remove(far)
            spots.add(back[far] if far > 0 else 0)
        return spots.pop()

    def _ids(self, text: str, back: list[int], ids: list[int], to: int) -> list[int]:
        out: list[int] = []
        while to > 0:
            if ids[to] >= 0:
                out.append(ids[to])
            else:
                out.extend(self.v.byte_ids[x] for x in reversed(text[back[to] : to].encode()))
            to = back[to]
        out.reverse()
        return out


class Codec:
    """Encoder and decoder of one worker; stretches once committed are remembered, up to ``most`` of them."""

    def __init__(self, vocabulary: Vocabulary, most: int = 200_000) -> None:
        self.v, self.most, self.viterbi = vocabulary, most, StreamingViterbi(vocabulary)
        self.known: dict[str, bytes] = {}

    def encode(self, text: str | None) -> bytes:
        """The ids of a text as packed 32-bit integers."""
        if not text:
            return b""
        text = BLANK + text.replace(" ", BLANK)
        parts = (text[i : i + PART] for i in range(0, len(text), PART))
        return b"".join(self.viterbi.document(parts, self.known, self.most, PART))

    def decode(self, ids: bytes) -> str:
        numbers = array("i")
        numbers.frombytes(ids)
        text = b"".join(map(self.v.spelling.__getitem__, numbers)).decode("utf-8", "replace")
        return text[1:] if text.startswith(" ") else text


def encode(docs: DataFrame, model_path: str | None = None, batch_bytes: int = 4 << 20) -> DataFrame:
    """One row per document: doc_id, ids array<int>."""
    path = model_path or default_model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(Vocabulary.load(path))
        for batch in slices(batches, "text", batch_bytes):
            packed = [codec.encode(t) for t in batch.column("text").to_pylist()]
            ends = [0]
            for p in packed:
                ends.append(ends[-1] + len(p) // 4)
            flat = pa.Array.from_buffers(pa.int32(), ends[-1], [None, pa.py_buffer(b"".join(packed))])
            yield pa.record_batch([batch.column("doc_id"), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), flat)], names=["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, ids array<int>")


def decode(encoded: DataFrame, model_path: str | None = None) -> DataFrame:
    """One row per document: doc_id, text, from doc_id and ids."""
    path = model_path or default_model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(Vocabulary.load(path))
        for batch in batches:
            texts = [codec.decode(array("i", ids or []).tobytes()) for ids in batch.column("ids").to_pylist()]
            yield pa.record_batch([batch.column("doc_id"), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def round_trip(docs: DataFrame, model_path: str | None = None, batch_bytes: int = 4 << 20) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_ids, ids_sha256 (of the ids as little-endian 32-bit words), decoded_sha256, lossless.

    Ids are decoded where they were made, so the check moves no data.
    """
    path = model_path or default_model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(Vocabulary.load(path))
        for batch in slices(batches, "text", batch_bytes):
            out = []
            for text in batch.column("text").to_pylist():
                ids = codec.encode(text)
                decoded = codec.decode(ids)
                raw = decoded.encode()
                out.append((len((text or "").encode()), len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(raw).hexdigest(), decoded == (text or "").replace(BLANK, " ")))
            columns = [pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.bool_()), strict=True)]
            yield pa.record_batch([batch.column("doc_id"), *columns], names=["doc_id", "n_bytes", "n_ids", "ids_sha256", "decoded_sha256", "lossless"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, n_bytes long, n_ids long, ids_sha256 string, decoded_sha256 string, lossless boolean")
