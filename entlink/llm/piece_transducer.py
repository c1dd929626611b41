"""SentencePiece encoding and decoding as a weighted finite-state transducer.

A model file is compiled into three machines that are composed with an input
position by position, as far as paths of finite weight reach:

* the normaliser, which rewrites blanks to the escape symbol, puts the dummy
  prefix in front and, if the model asks for it, drops extra blanks;
* the pieces, a trie whose paths spell a piece and write its identifier, with an
  arc from any character that is no piece to its bytes (or to the unknown id);
* the neighbours, an acceptor whose state is the last piece read.

Weights are added along a path and the encoding is the path of least weight: the
tropical semiring.  For a unigram model a piece weighs minus its score and any
neighbours are free.  A merge model has no additive scores, but its encodings
are regular: a sequence of pieces is the encoding of its text exactly if every
two neighbours, merged alone, come out as those two.  So its pieces weigh
nothing, and the neighbours ``a, b`` weigh nothing if merging ``a + b`` gives
``[a, b]`` and infinity if not.  Either way one state of finite weight is enough
for a position (a prefix of a text has one encoding by merges), so one
relaxation over positions finds the path, in time linear in the text.  Weights of
neighbours are kept in a bounded dictionary, as are the paths of words.

The input is cut where no piece can span: before an escaped blank (if no
piece has one inside after another character) and around a line break (if no
longer piece has one).

Read are unigram and merge models whose normaliser has no character map and
escapes blanks, without user-defined pieces; others raise ``ValueError``.

Defined results: a null text counts as empty and has no pieces; decoding gives
the text back, except that the escape character itself comes back as a blank
(and extra blanks are gone if the model drops them);
an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import pickle
import re
import struct
import zlib
from array import array
from collections.abc import Iterator
from contextlib import suppress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entlink.storage import release_memory

BLANK = "▁"
NORMAL, UNKNOWN, CONTROL, USER, BYTE, UNUSED = 1, 2, 3, 4, 6, 5
UNIGRAM, BPE = 1, 2
UNKNOWN_PENALTY = 10.0
NEVER = float("-inf")
FAR = float("inf")
KNOWN_WORDS, KNOWN_PAIRS = 400_000, 200_000
LONG = 64  # characters of a chunk that is not kept


def _fields(buf: bytes) -> Iterator[tuple[int, int | bytes]]:
    """Fields of a protocol buffer message."""
    at = 0

    def varint():
        nonlocal at
        n = shift = 0
        while True:
            b = buf[at]
            at += 1
            n |= (b & 127) << shift
            shift += 7
            if b < 128:
                return n

    while at < len(buf):
        tag = varint()
        if tag & 7 == 0:
            yield tag >> 3, varint()
            continue
        size = {1: 8, 5: 4}.get(tag & 7) or varint()
        yield tag >> 3, buf[at : at + size]
        at += size


class Model:
    """What the transducer needs of a model file."""

    def __init__(self, raw: bytes):
        self.pieces: list[tuple[str, float, int]] = []
        trainer, normaliser = {}, {}
        for number, value in _fields(raw):
            if number == 1:
                d = dict(_fields(value))
                self.pieces.append((d.get(1, b"").decode(), struct.unpack("<f", d[2])[0] if 2 in d else 0.0, d.get(3, NORMAL)))
            elif number == 2:
                trainer = dict(_fields(value))
            elif number == 3:
                normaliser = dict(_fields(value))
        self.kind = trainer.get(3, UNIGRAM)
        self.byte_fallback = bool(trainer.get(35, 0))
        self.dummy_prefix = bool(normaliser.get(3, 1))
        if self.kind not in (UNIGRAM, BPE):
            raise ValueError("only unigram and merge models are known")
        self.fewer_blanks = bool(normaliser.get(4, 1))
        if normaliser.get(2, b"") or not normaliser.get(5, 1) or trainer.get(24, 0):
            raise ValueError("a character map, bare blanks and blanks as suffixes are not known")
        if any(t == USER for _, _, t in self.pieces):
            raise ValueError("user-defined pieces are not known")


class PieceTransducer:
    def __init__(self, raw: bytes):
        self.model = m = Model(raw)
        self.ids = {p: i for i, (p, _, t) in enumerate(m.pieces) if t == NORMAL}
        self.scores = {p: s for p, s, t in m.pieces if t == NORMAL}
        self.unknown = next(i for i, (_, _, t) in enumerate(m.pieces) if t == UNKNOWN)
        self.byte_ids = {int(p[3:5], 16): i for i, (p, _, t) in enumerate(m.pieces) if t == BYTE}
        unigram = m.kind == UNIGRAM
        self.weights = {p: -s if unigram else 0.0 for p, s in self.scores.items()}
        self.fallback = UNKNOWN_PENALTY - min(self.scores.values(), default=0.0) if unigram else 0.0
        # The trie: by character the piece that ends there (or None), its weight, and what follows.
        self.arcs: dict = {}
        for p in self.ids:
            node = self.arcs
            for c in p[:-1]:
                node = node.setdefault(c, [None, 0.0, {}])[2]
            end = node.setdefault(p[-1], [None, 0.0, {}])
            end[0], end[1] = p, self.weights[p]
        self.longest = max(map(len, self.ids), default=1)
        self.cut_at_blank = not any(BLANK in p.lstrip(BLANK) for p in self.ids)
        self.cut_at_newline = not any("\n" in p and len(p) > 1 for p in self.ids)
        self.stories: dict[str, tuple[list, list] | None] = {}
        self.verdicts: dict[str, dict[str, float]] = {}
        self.n_verdicts = 0
        self.led: dict[str, bytes] = {}  # paths of words after a blank
        self.bare: dict[str, bytes] = {}
        surface = []
        for p, _, t in m.pieces:
            surface.append(bytes([int(p[3:5], 16)]) if t == BYTE else p.encode() if t == NORMAL else b"")
        surface[self.unknown] = " ⁇ ".encode()
        self.surface = surface

    def story(self, text: str) -> tuple[list, list] | None:
        """How merging one piece alone goes: its first and its last part after each merge, each with the score of
        the merge that comes next.  None if merging does not end in the piece."""
        if text in self.stories:
            return self.stories[text]
        parts, scores, first, last = list(text), self.scores, [], []
        while True:
            best, where = NEVER, -1
            for i in range(len(parts) - 1):
                s = scores.get(parts[i] + parts[i + 1], NEVER)
                if s > best:
                    best, where = s, i
            first.append((parts[0], best))
            last.append((parts[-1], best))
            if where < 0:
                found = (first, last) if len(parts) == 1 else None
                if text in self.ids:  # pieces only, so the dictionary is no larger than the model
                    self.stories[text] = found
                return found
            parts[where : where + 2] = [parts[where] + parts[where + 1]]

    def follows(self, a: str, b: str) -> bool:
        """Whether the arc of ``b`` after piece ``a`` has weight zero: merged side by side, best score first and
        leftmost of equals, no merge across their border ever comes first."""
        ends, starts, score, i, j = self.story(a), self.story(b), self.scores.get, 0, 0
        if ends is None or starts is None:
            return False
        ends, starts = ends[1], starts[0]
        while True:
            (end, after_a), (start, after_b) = ends[i], starts[j]
            across = score(end + start)
            if across is not None and across > after_a and across >= after_b:
                return False
            if after_a >= after_b:
                if after_a == NEVER:
                    return True
                i += 1
            else:
                j += 1

    def neighbours(self, a: str, b: str) -> float:
        """Weight of piece ``b`` after piece ``a``, or at the start if that is empty."""
        if self.model.kind == UNIGRAM:
            return 0.0
        if self.n_verdicts >= KNOWN_PAIRS:
            self.verdicts, self.n_verdicts = {}, 0
        good = self.follows(a, b) if a else self.story(b) is not None
        found = self.verdicts.setdefault(a, {})[b] = 0.0 if good else FAR
        self.n_verdicts += 1
        return found

    def shortest_path(self, chunk: str) -> list[str]:
        """Pieces along the path of least weight through one chunk composed with the machines.

        Positions of a unigram model are settled in the order of the text.  Finite weights of a merge model are all
        zero, so any state reached is settled at once; the furthest arc is tried first, and the search ends at the end
        of the chunk.  Arcs are weighed when they are tried.
        """
        n, pieces, trie = len(chunk), self.ids, self.arcs
        cost, last = [0.0] + [FAR] * n, [""] * (n + 1)
        if self.model.kind != UNIGRAM:
            self._settle_furthest_first(chunk, cost, last)
        for at in range(n) if self.model.kind == UNIGRAM else ():
            here = cost[at]
            if chunk[at] not in pieces and here + self.fallback < cost[at + 1]:
                cost[at + 1], last[at + 1] = here + self.fallback, chunk[at]
            node, to = trie, at
            for c in chunk[at : at + self.longest]:
                found = node.get(c)
                if found is None:
                    break
                to += 1
                piece, weight, node = found
                if piece is None:
                    continue
                if here + weight < cost[to]:
                    cost[to], last[to] = here + weight, piece
        path, at = [], n
        while at:
            path.append(last[at])
            at -= len(last[at])
        return path[::-1]

    def _settle_furthest_first(self, chunk: str, cost: list[float], last: list[str]) -> None:
        """Relax the arcs of a merge model, the furthest first, until the end of the chunk is settled."""
        n, weights, trie, longest = len(chunk), self.weights, self.arcs, self.longest
        at, here, before, waiting = 0, 0.0, "", []
        while at < n:
            arcs, node = [] if chunk[at] in weights else [chunk[at]], trie
            for c in chunk[at : at + longest]:
                found = node.get(c)
                if found is None:
                    break
                piece, _, node = found
                if piece is not None:
                    arcs.append(piece)
            while True:
                while not arcs:
                    at, here, before, arcs = waiting.pop()
                piece = arcs.pop()
                to = at + len(piece)
                if cost[to] < FAR:
                    continue
                weight = weights.get(piece)
                if weight is None:  # a character that is no piece
                    weight = self.fallback
                else:
                    known = self.verdicts.get(before)
                    extra = known.get(piece) if known else None
                    weight += self.neighbours(before, piece) if extra is None else extra
                if weight < FAR:
                    break
            if arcs:
                waiting.append((at, here, before, arcs))
            at, here, before = to, here + weight, piece
            cost[at], last[at] = here, piece

    def _ids(self, chunk: str) -> bytes:
        out: list[int] = []
        path = self.shortest_path(chunk)
        with suppress(KeyError):
            return array("I", [self.ids[p] for p in path]).tobytes()
        for p in path:
            i = self.ids.get(p)
            if i is not None:
                out.append(i)
            elif self.model.byte_fallback:
                out += [self.byte_ids[b] for b in p.encode()]
            elif not out or out[-1] != self.unknown:
                out.append(self.unknown)
        return array("I", out).tobytes()

    def _make_room(self, wanted: int) -> None:
        """Keep the words after a blank within bounds: short ones recur most and stay."""
        if len(self.led) + wanted > KNOWN_WORDS:
            short = {w: v for w, v in self.led.items() if len(w) < 7}
            self.led = short if len(short) < KNOWN_WORDS // 2 else {}

    def _bare(self, chunk: str) -> bytes:
        found = self.bare.get(chunk)
        if found is None:
            found = self._ids(chunk)
            if len(chunk) < LONG:
                if len(self.bare) > KNOWN_WORDS // 4:
                    self.bare.clear()
                self.bare[chunk] = found
        return found

    def _line(self, line: str, lead: bool) -> Iterator[bytes]:
        words = line.split(" ")
        if not self.cut_at_blank:
            yield self._ids((BLANK if lead else "") + line.replace(" ", BLANK))
        elif "" not in words and BLANK not in line:
            led = words if lead else words[1:]
            found = list(map(self.led.get, led))
            if None in found:
                new = {w for w, f in zip(led, found) if f is None}
                self._make_room(len(new))
                for w in new:
                    self.led[w] = self._ids(BLANK + w)
                found = [self.led[w] if f is None else f for w, f in zip(led, found)]
            if not lead:
                yield self._bare(words[0])
            yield from found
        else:
            yield from map(self._bare, re.findall(f"{BLANK}+[^{BLANK}]*|[^{BLANK}]+", (BLANK if lead else "") + line.replace(" ", BLANK)))

    def encode(self, text: str | None) -> bytes:
        """Identifiers of a whole text as little-endian unsigned 32-bit bytes."""
        if text and self.model.fewer_blanks:
            text = re.sub(" +", " ", text.strip(" "))
        if not text:
            return b""
        lines = text.split("\n") if self.cut_at_newline else [text]
        out: list[bytes] = []
        for k, line in enumerate(lines):
            lead = k == 0 and self.model.dummy_prefix
            if k:
                out.append(self._bare("\n"))
            if line or lead:
                out += self._line(line, lead) if line else [self._ids(BLANK)]
        if not self.model.byte_fallback:
            return self._one_unknown(b"".join(out))
        return b"".join(out)

    def _one_unknown(self, raw: bytes) -> bytes:
        """Neighbouring unknowns count as one."""
        ids = np.frombuffer(raw, np.uint32)
        again = np.concatenate(([False], (ids[1:] == self.unknown) & (ids[:-1] == self.unknown)))
        return ids[~again].tobytes()

    def decode(self, raw: bytes) -> str:
        """The text of identifiers: the same transducer with input and output exchanged."""
        surface = self.surface
        text = b"".join([surface[i] for i in np.frombuffer(raw, np.uint32).tolist()]).decode("utf-8", "replace").replace(BLANK, " ")
        return text[1:] if self.model.dummy_prefix and text[:1] == " " else text


RESULT = "id long, n_pieces long, ids_crc32 long, round_trip boolean, ids binary"


def encode_documents(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """Encode every whole text, decode it again and compare: ``RESULT``, ids as little-endian 32-bit.

    Only the driver reads the model's file and compiles it; executors get the machines.
    """
    with open(model_path, "rb") as f:
        compiled = docs.sparkSession.sparkContext.broadcast(pickle.dumps(PieceTransducer(f.read())))
    names = [c.split()[0] for c in RESULT.split(", ")]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.binary()]

    def run(batches):
        t = pickle.loads(compiled.value)  # a worker that goes on to other tasks keeps nothing
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                rows = []
                for doc_id, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    raw = t.encode(text)
                    rows.append((doc_id, len(raw) // 4, zlib.crc32(raw), t.decode(raw) == (text or ""), raw if with_ids else None))
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)
        del t
        release_memory()

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return slim.mapInArrow(run, RESULT)
