"""Vector bin packing of token sequences by the dot-product heuristic.

Each example has a demand in three dimensions (tokens, one segment, loss-bearing tokens) and each
sequence a capacity in all three. A task streams its rows through a buffer of bounded size. It fills one
sequence at a time: of the buffered pieces that fit, it takes the one with the largest inner product of
demand and what is left of the capacity (both as shares of the capacity), so scarce dimensions are
spared. If none fits, it cuts a piece at what is left, since pieces may be cut freely. The rest at the
end of a task is cut into sequences of power-of-two lengths, which need no padding. No row moves
between tasks, so there is no shuffle and a hot source is spread as the input's splits are.

Defined cases: null text counts as empty; an empty document still has its end id; documents longer than
a sequence fill whole sequences; an empty table gives no rows; other columns are ignored. A task's
result depends only on its input split, so a retried task gives the same rows and sequence ids.
"""

from __future__ import annotations

import json
import os
import re
import unicodedata
import zlib
from array import array
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import byte_alphabet
from .common import release

#: Pieces that wait for a place in a task, pre-tokens kept in the memo, longest one (characters) kept there.
BUFFER, MEMO, WORD = 256, 400_000, 64
# The pre-token pattern of word vocabularies.
PRETOKEN = r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+"
# The same for lower-case texts of Latin-1 alone, whose letters and numbers can be listed.
LETTERS, NUMBERS = "a-zªµºß-öø-ÿ", "0-9²³¹¼-¾"
LATIN = rf"'s|'t|'re|'ve|'m|'ll|'d|[{LETTERS}]+|[{NUMBERS}]|[^\s{LETTERS}{NUMBERS}]+"
SCHEMA = "`{0}` {1}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, loss_tokens long"


@dataclass(frozen=True)
class Limits:
    """Capacity of one sequence. segments: pieces in it; loss: tokens that bear loss."""

    tokens: int = 4096
    segments: int = 128
    loss: int = 4096


def splits_alike(spec: dict) -> bool:
    """Whether a vocabulary file asks for the normalising and splitting that WordEncoder does itself."""

    def steps(part: dict | None, key: str) -> list[dict]:
        return [] if not part else part[key] if part.get("type") == "Sequence" else [part]

    kinds = [(x["type"], x.get("pattern"), x.get("content")) for x in steps(spec.get("normalizer"), "normalizers")]
    spaces = [("NFC", None, None), ("Replace", {"Regex": r"\s+"}, " "), ("Lowercase", None, None)]
    split = [(x["type"], x.get("behavior"), x.get("invert"), (x.get("pattern") or {}).get("Regex")) for x in steps(spec.get("pre_tokenizer"), "pretokenizers")]
    wanted = PRETOKEN.replace("\\p{L}", "[\\p{L}]", 1).replace("|\\p{N}|", "|[\\p{N}]|")
    return kinds == spaces and len(split) == 2 and split[0] == ("Split", "Removed", True, wanted) and split[1][0] == "ByteLevel"


class WordEncoder:
    """Ids of a text by the tokenizers library, pre-token by pre-token with a memo of two generations.

    Vocabularies that compose (NFC), lower the case, drop white space and split as PRETOKEN does have
    pre-tokens that are independent of each other; the file says whether it is one. Of other vocabularies every text goes to
    the library whole, and so do texts with special tokens, or with characters on which engines differ (separators
    U+001C to U+001F, the capital sigma).
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.tokenize = self.library.model.tokenize
        self.symbols = {b: c for c, b in byte_alphabet().items()}
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        special = [re.escape(t.content) for t in self.library.get_added_tokens_decoder().values()]
        self.odd = re.compile("|".join([r"[\x1c-\x1f\u03a3]", *special])).search
        self.alike = splits_alike(json.loads(self.library.to_str()))
        self.words = regex.compile(PRETOKEN).findall
        self.latin = re.compile(LATIN).findall

    def _whole(self, text: str) -> bytes:
        return array("I", self.library.encode(text, add_special_tokens=False).ids).tobytes()

    def _ids(self, word: str) -> bytes:
        """One pre-token through the library's model, whose symbols stand for bytes."""
        if not (word.isascii() and word.isalpha()):
            word = word.encode("utf-8").decode("latin-1").translate(self.symbols)
        return array("I", [t.id for t in self.tokenize(word)]).tobytes()

    def encode(self, text: str) -> bytes:
        if not self.alike:
            return self._whole(text)
        try:
            text.encode("latin-1")
            find = self.latin
        except UnicodeEncodeError:
            find = self.words
            text = unicodedata.normalize("NFC", text)
        if self.odd(text):
            return self._whole(text)
        words = find(text.lower())
        young, found = self.young, None
        missing = set(words).difference(young)
        if missing:
            if len(young) >= MEMO // 2:
                self.old, self.young = young, {}
                young, missing = self.young, set(words)
            old = self.old
            new = [w for w in missing if w not in old]
            for w in missing.difference(new):
                young[w] = old[w]
            for w, ids in zip(new, map(self._ids, new)):
                if len(w) <= WORD:
                    young[w] = ids
                else:
                    found = found or {}
                    found[w] = ids
        if found:
            return b"".join([young[w] if w in young else found[w] for w in words])
        return b"".join(map(young.__getitem__, words))


_encoders: dict[str, WordEncoder] = {}


def word_encoder(path: str) -> WordEncoder:
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


@dataclass
class Piece:
    """Part of a document that has no place yet. loss_from: ids of the document from here on bear loss."""

    doc: object
    ids: bytes
    start: int
    end: int
    loss_from: int
    doc_tokens: int

    def loss(self, end: int) -> int:
        return max(0, end - max(self.start, self.loss_from))


class Packer:
    """Places pieces; put(doc, index of the sequence, offset, piece, end) is called for each part placed."""

    def __init__(self, limits: Limits, put: Callable[[Piece, int, int, int], None], first: int = 0):
        self.cap = np.array([limits.tokens, limits.segments, limits.loss], float)
        self.limits, self.put, self.sequence = limits, put, first
        self.waiting: list[Piece] = []
        self.demand = np.zeros((BUFFER, 3))

    def add(self, piece: Piece) -> None:
        if len(self.waiting) == BUFFER:
            self._fill()
        self._hold(piece)

    def _hold(self, piece: Piece) -> None:
        self.demand[len(self.waiting)] = (piece.end - piece.start, 1, piece.loss(piece.end))
        self.waiting.append(piece)

    def _drop(self, k: int) -> None:
        last = self.waiting.pop()
        if k < len(self.waiting):
            self.waiting[k] = last
            self.demand[k] = self.demand[len(self.waiting)]

    def _fill(self) -> list[tuple[Piece, int]]:
        """One sequence; if nothing waits any more before it is full, its parts come back unplaced."""
        left, parts, full = self.cap.copy(), [], False
        while self.waiting and left[0] > 0 and left[1] > 0:
            need = self.demand[: len(self.waiting)]
            fits = (need <= left).all(axis=1)
            if fits.any():
                k = int(np.argmax(np.where(fits, (need / self.cap) @ (left / self.cap), -1.0)))
                piece = self.waiting[k]
                take = piece.end
                self._drop(k)
            else:
                k, most = -1, 0
                for j in np.argsort(-need[:, 0], kind="stable")[:8]:  # the longest ones: short pieces stay whole
                    end = self._cut(self.waiting[j], left)
                    if end - self.waiting[j].start > most:
                        k, most = int(j), end - self.waiting[j].start
                if k < 0:
                    full = True
                    break
                piece = self.waiting[k]
                take = piece.start + most
                rest = Piece(piece.doc, piece.ids, take, piece.end, piece.loss_from, piece.doc_tokens)
                self._drop(k)
                self._hold(rest)
            parts.append((piece, take))
            left -= (take - piece.start, 1, piece.loss(take))
        if not self.waiting and not full and left[0] > 0 and left[1] > 0:
            return parts
        self._place(parts)
        return []

    @staticmethod
    def _cut(piece: Piece, left: np.ndarray) -> int:
        """Furthest end at which the piece's first part fits."""
        end = min(piece.end, piece.start + int(left[0]))
        if piece.loss(end) > left[2]:
            end = max(piece.start, piece.loss_from) + int(left[2])
        return end

    def _place(self, parts: list[tuple[Piece, int]]) -> None:
        offset = 0
        for piece, end in parts:
            self.put(piece, self.sequence, offset, end)
            offset += end - piece.start
        self.sequence += 1

    def finish(self) -> None:
        rest: list[tuple[Piece, int]] = []
        while self.waiting:
            rest = self._fill()
        total = sum(end - piece.start for piece, end in rest)
        while total:
            room, parts = 1 << total.bit_length() - 1, []
            total -= room
            while room:
                piece, end = rest.pop(0)
                take = min(end, piece.start + room)
                parts.append((piece, take))
                room -= take - piece.start
                if take < end:
                    rest.insert(0, (Piece(piece.doc, piece.ids, take, end, piece.loss_from, piece.doc_tokens), end))
            self._place(parts)


def pack(docs: DataFrame, path: str, limits: Limits = Limits(), end_id: int | None = 2, id_col: str = "doc_id", text_col: str = "text", loss_from: str | None = None) -> DataFrame:
    """Pack all texts into sequences; one row per piece with its ids' CRC-32.

    loss_from: optional column with the number of a document's first ids that bear no loss (a prompt);
    null or absent counts as 0. Sequences are numbered from task number times 2^33.
    """
    columns = [F.col(id_col), F.col(text_col).cast("string"), (F.col(loss_from) if loss_from else F.lit(0)).cast("long").alias("_loss_from")]
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, rows = word_encoder(path), []
        end = b"" if end_id is None else end_id.to_bytes(4, "little")

        def put(piece: Piece, sequence: int, offset: int, to: int) -> None:
            part = piece.ids[4 * piece.start : 4 * to]
            rows.append((piece.doc, piece.start, to - piece.start, zlib.crc32(part), piece.doc_tokens, sequence, offset, piece.loss(to)))

        def taken() -> pa.RecordBatch:
            values = list(zip(*rows)) or [[]] * 8
            rows.clear()
            types = [id_type, *[pa.int64()] * 7]
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(values, types)], names)

        names = [id_col, "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "loss_tokens"]
        packer, id_type = Packer(limits, put, TaskContext.get().partitionId() << 33), pa.int64()
        for batch in batches:
            id_type = batch.column(0).type
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                for doc, text, skip in zip(*(part.column(i).to_pylist() for i in range(3))):
                    code = coder.encode(text or "") + end
                    n = len(code) // 4
                    if n:
                        whole = min(limits.tokens, limits.loss)
                        k = 0
                        while n - k >= whole:  # a full sequence of one document
                            packer._place([(Piece(doc, code, k, n, skip or 0, n), k + whole)])
                            k += whole
                        if k < n:
                            packer.add(Piece(doc, code, k, n, skip or 0, n))
                if len(rows) > 8192:
                    yield taken()
        packer.finish()
        if rows:
            yield taken()
        release()

    return docs.select(columns).mapInArrow(run, SCHEMA.format(id_col, kind))
