"""Byte-pair encoding as a bounded-lookahead streaming transducer, and incremental decoding.

How it works. A merge list fixes, for every byte string, one token sequence. Every prefix of that
sequence is the sequence of its own bytes, and a sequence is the right one exactly when each token encodes
to itself and each pair of neighbours stands side by side, that is, no merge ever joins the symbols at
their common edge. So a left-to-right automaton needs to remember one thing per position: the last token
of the encoding of what ends there.

How far ahead one must look. While a boundary stands, both sides develop alone. The merge of rank r of
symbols a and b removes a boundary if b comes to stand behind it, which only a merge of a lower rank can
prevent, by joining the symbol that ends b to what follows. That symbol lies on the right edge of b, and
its own merge again waits for what follows. So the reach of a merge is the length of b and the largest
reach of the earlier merges whose left symbol lies on b's right edge; the largest reach of all,
``sufficient_lookahead``, is how many bytes decide a boundary for good. Tokens are emitted as soon as
so many bytes follow them, and the window is trimmed then: memory does not grow with the text, nor with
a pre-token. Every pre-token goes through the transducer; finished short ones are memoised in a bounded table.

Defined cases: null text counts as empty (0 ids); the special token's string in a text is that token;
any other text, however long, is read in windows, and so is one unbroken pre-token. Decoding maps ids to bytes
and runs an incremental UTF-8 state machine; undecodable bytes become U+FFFD.
"""

from __future__ import annotations

import codecs
import hashlib
import json
from array import array
from collections.abc import Iterable, Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Characters of a text that are looked at together; entries kept in the table of finished pre-tokens;
#: longest pre-token (bytes) that this table keeps.
WINDOW, MEMO, KEEP_BYTES = 1 << 16, 600_000, 96
#: Bytes by whose value the tokens that end there are remembered.
TAIL = 6
NEVER = 1 << 62

# The pre-token pattern of byte-level vocabularies. White space is spelt out, since engines differ on \s.
SPACE = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
PRETOKEN = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{SPACE}\p{{L}}\p{{N}}]+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+"


def byte_alphabet() -> dict[str, int]:
    """Printable stand-ins of the 256 bytes: Latin-1's visible characters stand for themselves, the rest follow from U+0100."""
    seen = [b for b in range(256) if 0x21 <= b <= 0x7E or 0xA1 <= b <= 0xAC or 0xAE <= b]
    hidden = [b for b in range(256) if b not in set(seen)]
    return {chr(b): b for b in seen} | {chr(256 + i): b for i, b in enumerate(hidden)}


class MergeList:
    """The merge list of a vocabulary file, with what the transducer derives from it."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        alphabet = byte_alphabet()
        raw = lambda s: bytes(alphabet[c] for c in s)
        model = spec["model"]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        vocab = {s: i for s, i in model["vocab"].items() if s not in self.special}
        self.bytes_of: dict[int, bytes] = {i: raw(s) for s, i in vocab.items()}
        self.bytes_of |= {i: s.encode() for s, i in self.special.items()}
        self.id_of = {b: i for i, b in self.bytes_of.items() if i not in self.special.values()}
        self.single = [self.id_of[bytes([b])] for b in range(256)]
        #: Pair of ids to place in the list, shifted, plus the id that it makes.
        self.merged: dict[tuple[int, int], int] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            self.merged[vocab[a], vocab[b]] = rank << 32 | vocab[a + b]
        self.longest = max(map(len, self.id_of))
        self.pairs: dict[int, bool] = {}
        self.edges: dict[int, tuple | None] = {}
        self.tails: dict[bytes, tuple[tuple[int, int], ...]] = {}
        #: Suffix trie of the tokens: byte to node, -1 to the token that ends the walk.
        self.reverse: dict = {}
        for b, i in self.id_of.items():
            node = self.reverse
            for x in reversed(b):
                node = node.setdefault(x, {})
            node[-1] = i
        self.sufficient_lookahead = self._reach()

    def _reach(self) -> int:
        """Bytes behind a boundary that decide it, whatever follows them; merges are taken in the order of the list."""
        right: dict[int, list[int]] = {}  # a token to the right halves it can be made with
        reach: dict[int, int] = {}  # a left symbol to the largest reach of its merges so far
        most = 1
        for (a, b), made in self.merged.items():
            edge, stack = set(), [b]
            while stack:
                x = stack.pop()
                if x not in edge:
                    edge.add(x)
                    stack.extend(right.get(x, ()))
            far = len(self.bytes_of[b]) + max((reach.get(x, 0) for x in edge), default=0)
            reach[a] = max(reach.get(a, 0), far)
            right.setdefault(made & 0xFFFFFFFF, []).append(b)
            most = max(most, far)
        return most

    def ending(self, tail: bytes, data: bytes, i: int) -> tuple[tuple[int, int], ...]:
        """Length and id of the tokens that end at data[:i], long ones first; tail is what the walk sees first. Kept where no more than the tail counts."""
        node, k, found = self.reverse, i, []
        while k > 0 and (node := node.get(data[k - 1])) is not None:
            k -= 1
            t = node.get(-1)
            if t is not None:
                found.append((i - k, t))
        out = tuple(reversed(found))
        if i < TAIL or node is None and i - k < TAIL:
            if len(self.tails) >= MEMO:
                self.tails.clear()
            self.tails[tail] = out
        return out

    def close(self, data: bytes) -> tuple[list[int], dict[int, tuple[int, int, int]]]:
        """All ids of a finished byte string: repeatedly the merge that comes first in the list, leftmost first; and how each symbol was made: rank, left, right."""
        ids, made = [self.single[b] for b in data], {}
        look = self.merged.get
        steps = [look(p, NEVER) for p in zip(ids, ids[1:])]
        while steps and (best := min(steps)) != NEVER:
            k = steps.index(best)
            made[best & 0xFFFFFFFF] = (best >> 32, ids[k], ids[k + 1])
            ids[k : k + 2] = [best & 0xFFFFFFFF]
            del steps[k]
            if k:
                steps[k - 1] = look((ids[k - 1], ids[k]), NEVER)
            if k < len(steps):
                steps[k] = look((ids[k], ids[k + 1]), NEVER)
        return ids, made

    def edge(self, token: int) -> tuple | None:
        """Symbols at the left and at the right edge of a token while it is made, with the ranks between which they stand; None if it does not encode to itself."""
        if token in self.edges:
            return self.edges[token]
        ids, made = self.close(self.bytes_of[token])
        out = None
        if ids == [token]:
            sides = []
            for side in (1, 2):
                x, dies, line = token, NEVER, []
                while x in made:
                    born = made[x][0]
                    line.append((x, born, dies))
                    x, dies = made[x][side], born
                sides.append((*line, (x, -1, dies)))
            out = tuple(sides)
        self.edges[token] = out
        return out

    def fits(self, left: int, right: int) -> bool:
        """Whether the two tokens stand side by side: no merge finds both its symbols at their common edge at its rank. A left of -1 is the start."""
        key = left << 32 | right
        known = self.pairs.get(key)
        if known is None:
            if len(self.pairs) >= MEMO:
                self.pairs.clear()
            known = self.pairs[key] = self._stand(left, right)
        return known

    def _stand(self, left: int, right: int) -> bool:
        heads = self.edge(right)
        if heads is None or left == -1:
            return heads is not None
        look = self.merged.get
        for a, born, dies in self.edge(left)[1]:
            for b, born_too, dies_too in heads[0]:
                made = look((a, b))
                # of equal pairs that overlap the leftmost is merged first
                if made is not None and max(born, born_too) < made >> 32 < dies and made >> 32 <= dies_too:
                    return False
        return True


class Transducer:
    """Takes the bytes of one pre-token piece by piece; gives ids as soon as they are stable."""

    def __init__(self, merges: MergeList):
        self.m = merges
        self.data, self.last = b"", [-1]  # last[i]: last token of the encoding of data[:i]; the start is a stable boundary
        self.before = -1  # the token emitted last: the left neighbour of the window's first one
        self.most = 0  # largest window so far, in bytes

    def feed(self, piece: bytes) -> list[int]:
        out: list[int] = []
        step = self.m.sufficient_lookahead + 1024
        for at in range(0, len(piece), 1024):
            self._read(piece[at : at + 1024])
            if len(self.data) >= step:
                out += self._stable()
        return out

    def _read(self, piece: bytes) -> None:
        m, last, before = self.m, self.last, self.before
        ending, known, fits = m.tails.get, m.pairs.get, m.fits
        i = len(self.data)
        data = self.data = self.data + piece
        for i in range(i + 1, len(data) + 1):
            tail = data[i - TAIL if i > TAIL else 0 : i]
            # exactly one of the tokens that end here is the last one of this prefix; it is mostly a long one
            for size, t in ending(tail) or m.ending(tail, data, i):
                left = last[i - size] if size < i else before
                good = known(left << 32 | t)
                if fits(left, t) if good is None else good:
                    last.append(t)
                    break

    def _chain(self, i: int) -> list[int]:
        ids = []
        while i > 0:
            ids.append(self.last[i])
            i -= len(self.m.bytes_of[self.last[i]])
        return ids[::-1]

    def _stable(self) -> list[int]:
        """Tokens that end at least the sufficient lookahead before what has been read: no continuation changes them."""
        self.most = max(self.most, len(self.data))
        ids, cut, bound = [], 0, len(self.data) - self.m.sufficient_lookahead
        for t in self._chain(len(self.data)):
            if cut + len(self.m.bytes_of[t]) > bound:
                break
            cut += len(self.m.bytes_of[t])
            ids.append(t)
        if ids:
            self.before = ids[-1]
            self.data = self.data[cut:]
            self.last = [-1, *self.last[cut + 1 :]]
        return ids

    def finish(self) -> list[int]:
        ids = self._chain(len(self.data))
        self.data, self.last, self.before = b"", [-1], -1
        return ids


class Encoder(dict):
    """Pre-token to ids (little-endian unsigned 32-bit); the dictionary itself is the bounded memo.

    The memo has two generations of MEMO / 2 entries: when the young one is full it becomes the old one,
    so frequent pre-tokens stay.
    """

    def __init__(self, path: str):
        super().__init__()
        self.old: dict[str, bytes] = {}
        self.m = MergeList(path)
        self.pattern = regex.compile(PRETOKEN)
        self.cut = regex.compile(rf"(?r)(?<=[^{SPACE}])[{SPACE}]")
        self.marks = regex.compile("|".join(map(regex.escape, self.m.special))) if self.m.special else None
        self.table = [self.m.bytes_of.get(i, b"") for i in range(max(self.m.bytes_of) + 1)]

    def __missing__(self, word: str) -> bytes:
        packed = self.old.get(word)
        if packed is not None:
            self._keep(word, packed)
            return packed
        data = word.encode("utf-8", "surrogatepass")
        machine = Transducer(self.m)
        packed = array("I", machine.feed(data) + machine.finish()).tobytes()
        if len(data) <= KEEP_BYTES:
            self._keep(word, packed)
        return packed

    def _streamed(self, text: str, at: int, end: int) -> Iterator[bytes]:
        """The ids of one long pre-token, some at a time."""
        machine = Transducer(self.m)
        for k in range(at, end, 8192):
            yield array("I", machine.feed(text[k : min(end, k + 8192)].encode("utf-8", "surrogatepass"))).tobytes()
        yield array("I", machine.finish()).tobytes()

    def _keep(self, word: str, packed: bytes) -> None:
        if len(self) >= MEMO // 2:
            self.old = dict(self)
            self.clear()
        self[word] = packed

    def _plain(self, text: str, at: int, n: int) -> Iterator[bytes]:
        """The ids of text[at:n], which has no special token; a cut between a visible character and white space never splits a pre-token."""
        look = self.__getitem__
        while n - at > WINDOW:
            found = self.cut.search(text, at + 1, at + WINDOW)
            if found and found.start() > at:
                yield b"".join(map(look, self.pattern.findall(text, at, found.start())))
                at = found.start()
            else:
                end = self.pattern.match(text, at, n).end()
                yield from self._streamed(text, at, end)
                at = end
        if at < n:
            yield b"".join(map(look, self.pattern.findall(text, at, n)))

    def encode(self, text: str) -> Iterator[bytes]:
        """The ids of a whole text, some at a time."""
        at = 0
        for mark in self.marks.finditer(text) if self.marks and any(s in text for s in self.m.special) else ():
            yield from self._plain(text, at, mark.start())
            yield self.m.special[mark[0]].to_bytes(4, "little")
            at = mark.end()
        yield from self._plain(text, at, len(text))

    def decode(self, packed: Iterable[bytes]) -> Iterator[str]:
        """Text of ids given some at a time; a character split over ids waits in the decoder's state."""
        machine = codecs.getincrementaldecoder("utf-8")("replace")
        for ids in packed:
            yield machine.decode(b"".join(map(self.table.__getitem__, memoryview(ids).cast("I"))))
        yield machine.decode(b"", True)


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """One per Python worker, kept between tasks."""
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def encode_decode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", keep: bool = False) -> DataFrame:
    """Encode every text and decode the ids again; no shuffle, one pass, Arrow batches.

    Returns the id column, ``n_tokens``, ``ids_sha256``, ``decoded_sha256``; with keep=True also ``ids``
    (binary) and ``decoded`` (string). Other columns of the input are ignored, whatever their names.
    """
    kind = docs.schema[id_col].dataType
    schema = f"`{id_col}` {kind.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids binary, decoded string" if keep else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoder(path)
        for batch in (whole.slice(at, 512) for whole in batches for at in range(0, whole.num_rows, 512)):
            rows: list[list] = [[] for _ in range(5)]
            for text in batch.column(1).to_pylist():
                ids_hash, text_hash, count, kept = hashlib.sha256(), hashlib.sha256(), 0, []

                def seen() -> Iterator[bytes]:
                    nonlocal count
                    for part in coder.encode(text or ""):
                        ids_hash.update(part)
                        count += len(part) // 4
                        if keep:
                            kept.append(part)
                        yield part

                words = []
                for piece in coder.decode(seen()):
                    text_hash.update(piece.encode("utf-8"))
                    if keep:
                        words.append(piece)
                for to, value in zip(rows, (count, ids_hash.hexdigest(), text_hash.hexdigest(), b"".join(kept), "".join(words))):
                    to.append(value)
            columns = [batch.column(0), pa.array(rows[0], pa.int64()), pa.array(rows[1], pa.string()), pa.array(rows[2], pa.string())]
            names = [id_col, "n_tokens", "ids_sha256", "decoded_sha256"]
            if keep:
                columns += [pa.array(rows[3], pa.binary()), pa.array(rows[4], pa.string())]
                names += ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays(columns, names)

    return docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, schema)
