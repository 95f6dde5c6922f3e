"""SentencePiece encoding and decoding, giant documents by a max-plus scan over chunks.

A giant text is cut into chunks anywhere. A boundary's state is the piece that lies over
it (or ends at it), given by where the piece begins and ends. A chunk's transfer matrix has, for each
state at its beginning and at its end, the best score of a way through; the matrices combine associatively
in the max-plus sense, which fixes the state at each boundary, and every chunk is traced back by
itself between its two states.

Scores: of a unigram model those of its pieces. Of a BPE model (the given vocabulary is one) the
sum of scores isn't what merging maximises. There a step scores 0 if merging leaves the two neighbouring
pieces as they are, else minus infinity: a sequence of pieces is what merging gives for a text just if that holds
for all neighbours, as the first merge across a border would also happen with the two neighbours alone.

No piece of the given vocabulary goes on with a space mark after another character. So at such a cut a text
falls apart: between its first and its last cut a chunk is encoded by words, which are looked up in a table as whole arrays;
only its ends need the search. Without that property, which is checked, all of it does.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import _text
from ._spark import discard, materialize

#: Characters of a chunk of a giant document; slots of a worker's table of words, as a power of two; bytes encoded at once; ids decoded at once.
CHUNK, SLOTS, PIECE, SLICE = 1 << 16, 19, 1 << 18, 1 << 16
#: Fixed value: the mark that stands for a space.
MARK = "▁"

State = tuple[int, int]
Matrix = dict[State, dict[State, float]]


# -- Max-plus scan -----------------------------------------------------------------------


class Unigram:
    """Pieces with log probabilities; a character that is no piece costs ``unknown``."""

    def __init__(self, pieces: dict[str, float], unknown: float | None = None):
        self.pieces = pieces
        self.longest = max(map(len, pieces), default=1)
        self.unknown = unknown if unknown is not None else min(pieces.values(), default=0.0) - 10.0

    def arcs(self, text: str, at: int) -> Iterator[tuple[int, float]]:
        """(length, score) of pieces that begin at a place; a single character always can."""
        single = False
        for n in range(1, min(self.longest, len(text) - at) + 1):
            score = self.pieces.get(text[at : at + n])
            if score is not None:
                single |= n == 1
                yield n, score
        if not single:
            yield 1, self.unknown

    def fits(self, left: str, right: str) -> bool:
        return True

    def cut(self, text: str, begin: int, end: int) -> State | None:
        """The first and last place in a span where the text falls apart."""
        return None


class Merging:
    """A BPE model: pieces by score, the best pair of neighbours merges first, of equal ones the leftmost."""

    def __init__(self, scores: dict[str, float], plain: bool):
        self.scores, self.plain = scores, plain
        self.longest = max(map(len, scores), default=1)
        self.known: dict[tuple[str, str], bool] = {}
        self.whole: dict[str, bool] = {}

    def merged(self, text: str) -> list[str]:
        parts = list(text)
        while len(parts) > 1:
            best = max(((self.scores.get(parts[i] + parts[i + 1], -np.inf), -i) for i in range(len(parts) - 1)))
            if best[0] == -np.inf:
                break
            i = -best[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def arcs(self, text: str, at: int) -> Iterator[tuple[int, float]]:
        yield 1, 0.0
        for n in range(2, min(self.longest, len(text) - at) + 1):
            piece = text[at : at + n]
            if piece in self.scores:
                if piece not in self.whole:
                    self.whole[piece] = len(self.merged(piece)) == 1
                if self.whole[piece]:
                    yield n, 0.0

    def fits(self, left: str, right: str) -> bool:
        got = self.known.get((left, right))
        if got is None:
            if len(self.known) > 100_000:
                self.known.clear()
            got = self.known[left, right] = self.merged(left + right) == [left, right]
        return got

    def cut(self, text: str, begin: int, end: int) -> State | None:
        if not self.plain:
            return None
        at = [i for i in _cuts(text) if begin <= i < end]
        return (at[0], at[-1]) if at else None


def _cuts(text: str) -> list[int]:
    """Places of marks after another character."""
    at = np.frombuffer(text.encode("utf-32-le"), np.uint32) == ord(MARK)
    return (np.flatnonzero(at[1:] & ~at[:-1]) + 1).tolist()


def _forward(model, text: str, state: State, end: int, like: tuple | None = None) -> tuple[dict[int, float], dict[int, int]]:
    """Best scores, and the last piece's beginning, at all places up to the piece over ``end``, from a piece text[state].

    like: the same from another state; once the last ``longest`` places agree (but for a constant) the rest is taken from there.
    """
    start, at = state
    best, back, equal, shift = {at: 0.0}, {at: start}, 0, None
    for p in range(at, end):
        if p in best:
            left = text[back[p] : p]
            for n, score in model.arcs(text, p):
                if best[p] + score > best.get(p + n, -np.inf) and (not left or model.fits(left, text[p : p + n])):
                    best[p + n], back[p + n] = best[p] + score, p
        if like:
            here = (best.get(p), back.get(p)), (like[0].get(p), like[1].get(p))
            if here[0][0] is None and here[1][0] is None:
                equal += 1
            elif here[0][1] == here[1][1] and here[0][0] is not None and here[1][0] is not None and (shift is None or abs(here[0][0] - here[1][0] - shift) < 1e-9):
                equal, shift = equal + 1, here[0][0] - here[1][0]
            else:
                equal, shift = 0, None
            if equal > 2 * model.longest and shift is not None:
                for q, score in like[0].items():
                    if q > p:
                        best[q], back[q] = score + shift, like[1][q]
                break
    return best, back


def _leaving(best: dict[int, float], back: dict[int, int], end: int) -> dict[State, float]:
    return {(back[q], q): score for q, score in best.items() if q >= end and back[q] < end}


def transfer(model, text: str, begin: int, end: int, first: bool) -> Matrix:
    """Scores from states at ``begin`` to states at ``end``, as places from the boundary. text has a piece's length of margin on either side."""
    if first:
        entering = [(begin, begin)]
    else:
        entering = [(s, s + n) for s in range(max(0, begin - model.longest), begin) for n, _ in model.arcs(text, s) if s + n >= begin]
    cut = model.cut(text, begin, end)
    out: Matrix = {}
    like = tail = None
    if cut and not first:
        tail = _leaving(*_forward(model, text, (cut[1], cut[1]), end), end)
    for state in entering:
        if tail is not None:
            best, _ = _forward(model, text, state, cut[0]) if state[1] <= cut[0] else ({}, {})
            leaving = {x: score + best[cut[0]] for x, score in tail.items()} if cut[0] in best else {}
        elif cut:
            leaving = _leaving(*_forward(model, text, (cut[1], cut[1]), end), end)
        else:
            if state[1] >= end:  # the piece covers all of the chunk
                leaving = {state: 0.0}
            else:
                got = _forward(model, text, state, end, like)
                like = like or got
                leaving = _leaving(*got, end)
        if leaving:
            out[state[0] - begin, state[1] - begin] = {(s - end, e - end): score for (s, e), score in leaving.items()}
    return out


def max_plus(a: Matrix, b: Matrix) -> Matrix:
    """The associative product of two transfer matrices."""
    out: Matrix = {}
    for x, row in a.items():
        best: dict[State, float] = {}
        for y, score in row.items():
            for z, more in b.get(y, {}).items():
                if score + more > best.get(z, -np.inf):
                    best[z] = score + more
        if best:
            out[x] = best
    return out


def scan(matrices: list[Matrix], last: Callable[[State], bool] = lambda s: s[1] == 0) -> list[State]:
    """The state at each boundary, the beginning and the end of the text with them, on the best way."""
    upto = [{(0, 0): {(0, 0): 0.0}}]
    for m in matrices:
        upto.append(max_plus(upto[-1], m))
    reach = [x.get((0, 0), {}) for x in upto]
    at = max((s for s in reach[-1] if last(s)), key=lambda s: (reach[-1][s], s))
    states = [at]
    for m, before in zip(reversed(matrices), reversed(reach[:-1])):
        at = max((s for s in before if at in m.get(s, {})), key=lambda s: (before[s] + m[s][states[-1]], s))
        states.append(at)
    return states[::-1]


def trace(model, text: str, begin: int, end: int, enter: State, leave: State) -> list[tuple[int, int, bool]]:
    """The pieces that begin in a chunk, as places, between its states; True for a span between cuts that falls apart by itself."""

    def back_from(state: State, to: int, until: int) -> list[tuple[int, int, bool]]:
        _, back = _forward(model, text, state, until)
        out = []
        while to > state[1]:
            out.append((back[to], to, False))
            to = back[to]
        return out[::-1]

    enter, leave = (enter[0] + begin, enter[1] + begin), (leave[0] + end, leave[1] + end)
    cut = model.cut(text, begin, end)
    if not cut:
        return back_from(enter, leave[1], end) if enter[1] < leave[1] else []
    head = [(begin, cut[0], True)] if enter[0] == enter[1] == begin else back_from(enter, cut[0], cut[0])
    return [*head, (*cut, True), *back_from((cut[1], cut[1]), leave[1], end)]


def segment(model, text: str, chunk: int = CHUNK) -> list[str]:
    """The best pieces of a text, by chunks: matrices, a scan, then each chunk's trace."""
    if not text:
        return []
    cuts = [*range(0, len(text), max(1, chunk)), len(text)]
    spans = list(zip(cuts, cuts[1:]))
    states = scan([transfer(model, text, a, b, a == 0) for a, b in spans])
    out = []
    for i, (a, b) in enumerate(spans):
        for s, e, apart in trace(model, text, a, b, states[i], states[i + 1]):
            out += model.merged(text[s:e]) if apart else [text[s:e]]
    return out


# -- The given model ---------------------------------------------------------------------


class Codec:
    """A SentencePiece model file: whole arrays of words through a table of ids, ids to bytes by a table of surfaces."""

    def __init__(self, path: str):
        from sentencepiece import SentencePieceProcessor

        self.model = m = SentencePieceProcessor(model_file=path)
        n = m.get_piece_size()
        pieces = [m.id_to_piece(i) for i in range(n)]
        odd, byte = np.array([m.is_control(i) or m.is_unknown(i) or m.is_unused(i) for i in range(n)]), np.array([m.is_byte(i) for i in range(n)])
        self.id = {p: i for i, p in enumerate(pieces) if not odd[i] and not byte[i]}
        self.bytes = {int(pieces[i][3:5], 16): i for i in np.flatnonzero(byte)}
        probe = "a  b é "
        self.plain = not any(MARK in p.lstrip(MARK) for p in self.id) and m.decode(m.encode(probe)) == probe and m.encode("a b") == [*m.encode("a"), *m.encode("b")] and m.encode(" b") != m.encode("b")
        self.merging = Merging({p: m.get_score(i) for p, i in self.id.items()}, self.plain)
        surface = [b"" if odd[i] else bytes([int(p[3:5], 16)]) if byte[i] else p.replace(MARK, " ").encode() for i, p in enumerate(pieces)]
        self.odd, self.byte = odd, byte
        self.size = np.array([len(x) for x in surface], np.int64)
        self.start, self.surface = np.cumsum(self.size) - self.size, np.frombuffer(b"".join(surface), np.uint8)
        decimal = [b"%d," % i for i in range(n)]
        self.digits = np.array([len(x) for x in decimal], np.int64)
        self.digits_at, self.decimal = np.cumsum(self.digits) - self.digits, np.frombuffer(b"".join(decimal), np.uint8)
        self.words = _text.HashTable(SLOTS)
        self._clear()

    def _clear(self) -> None:
        self.words.clear()
        self.pool, self.used = np.zeros(1 << 20, np.int32), 0
        self.at, self.n = np.zeros(self.words.most + 1, np.int64), np.zeros(self.words.most + 1, np.int64)
        # No word after the mark: one space at the end.
        self._learn(_text.span_hashes(np.zeros(0, np.uint64), np.zeros(1, int), np.zeros(1, int)), [[self.model.piece_to_id(MARK)]])

    def _learn(self, keys: np.ndarray, ids: list[list[int]]) -> None:
        size = np.array([len(x) for x in ids], np.int64)
        more = int(size.sum())
        if self.used + more > len(self.pool):
            self.pool = np.concatenate((self.pool, np.zeros(max(len(self.pool), more), np.int32)))
        self.pool[self.used : self.used + more] = np.fromiter((y for x in ids for y in x), np.int32, more)
        places = np.arange(self.words.size, self.words.size + len(keys))
        self.at[places], self.n[places] = self.used + np.cumsum(size) - size, size
        self.words.add(keys, places)
        self.used += more

    def encode_rows(self, raw: np.ndarray, offsets: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of rows of UTF-8 without marks, end to end, and offsets. first: the row is a text's beginning; others begin at a cut."""
        if not self.plain:
            got = [self.model.encode(raw[a:b].tobytes().decode()) for a, b in zip(offsets[:-1], offsets[1:])]
            return np.array([y for x in got for y in x], np.int32), np.concatenate(([0], np.cumsum([len(x) for x in got]))).astype(np.int64)
        space, row = raw == 32, np.diff(offsets) > 0
        begins = np.zeros(len(raw), bool)
        begins[1:] = space[1:] & ~space[:-1]
        begins[offsets[:-1][row]] = True
        opening = np.zeros(len(raw), bool)
        opening[offsets[:-1][row & first]] = True
        start = np.flatnonzero(begins)
        end = np.append(start[1:], len(raw))
        word = start + ~opening[start]  # a text's first word stands without the mark before it
        keys = _text.span_hashes(raw.astype(np.uint64) + np.uint64(1), word, end)
        place = self.words.find(keys)
        if (place < 0).any():
            new, at = np.unique(keys[place < 0], return_index=True)
            if self.words.size + len(new) > self.words.most or self.used > 1 << 23:
                self._clear()
                new, at = np.unique(keys, return_index=True)
                at = at[self.words.find(new) < 0]
                new = keys[at]
            else:
                at = np.flatnonzero(place < 0)[at]
            self._learn(new, self.model.encode([raw[word[j] : end[j]].tobytes().decode() for j in at.tolist()]))
            place = self.words.find(keys)
        size = self.n[place]
        bound = np.concatenate(([0], np.cumsum(size)))
        return _text.ragged(self.pool, self.at[place], size), bound[np.searchsorted(start, offsets)]

    def encode(self, text: str) -> list[int]:
        """Ids of one text."""
        raw = np.frombuffer(text.replace(MARK, " ").encode(), np.uint8)
        return self.encode_rows(raw, np.array([0, len(raw)]), np.array([True]))[0].tolist()

    def piece_ids(self, piece: str) -> list[int]:
        """A piece's id; of a character that is no piece its bytes'."""
        i = self.id.get(piece)
        return [i] if i is not None else [self.bytes[b] for b in piece.encode()] if self.bytes else [self.model.unk_id()]

    def trace_ids(self, text: str, begin: int, end: int, enter: State, leave: State) -> list[int]:
        """Ids of the pieces that begin in a chunk; text has marks for spaces."""
        out: list[int] = []
        for s, e, apart in trace(self.merging, text, begin, end, enter, leave):
            if not apart:
                out += self.piece_ids(text[s:e])
            elif e > s:
                raw = np.frombuffer(text[s:e].replace(MARK, " ").encode(), np.uint8)
                # The text's own beginning has a mark that the library puts there; other spans begin at a cut.
                out += self.encode_rows(raw, np.array([0, len(raw)]), np.array([False]))[0].tolist()
        return out

    def decode_rows(self, ids: np.ndarray, offsets: np.ndarray) -> pa.Array:
        """Texts of rows of ids."""
        rows = np.flatnonzero(np.diff(offsets) > 0)
        start, size = self.start[ids], self.size[ids].copy()
        lead = offsets[:-1][rows]
        mark = (size[lead] > 0) & (self.surface[np.minimum(start[lead], len(self.surface) - 1)] == 32)  # the mark that the library put there
        start[lead[mark]] += 1
        size[lead[mark]] -= 1
        bound = np.concatenate(([0], np.cumsum(size)))[offsets]
        data = _text.ragged(self.surface, start, size)
        own = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
        special = np.zeros(len(offsets) - 1, bool)
        special[own[self.odd[ids] | self.byte[ids]]] = True
        texts = pa.Array.from_buffers(pa.large_binary(), len(offsets) - 1, [None, pa.py_buffer(bound.astype(np.int64)), pa.py_buffer(data)])
        if not special.any():
            return texts.cast(pa.string())
        out = []
        for i, x in enumerate(texts.to_pylist()):
            if special[i]:
                part = ids[offsets[i] : offsets[i + 1]]
                try:
                    x = None if self.odd[part].any() or self.byte[part[0]] else x.decode().encode()
                except UnicodeDecodeError:
                    x = None
                x = self.model.decode(part.tolist()).encode() if x is None else x
            out.append(x)
        return pa.array(out, pa.binary()).cast(pa.string())


_codecs: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    if path not in _codecs:
        _codecs[path] = Codec(path)
    return _codecs[path]


def _list(values: np.ndarray, offsets: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(values.astype(np.int32)))


def _unmarked(column: pa.Array) -> pa.Array:
    """The mark itself in a text is read as a space."""
    return pc.replace_substring(column, MARK, " ") if pc.any(pc.match_substring(column, MARK)).as_py() else column


def _encode(path: str, text: str, name: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            for row, raw, offsets in _text.pieces(_unmarked(batch.column(text)), PIECE):
                ids, bound = c.encode_rows(raw, offsets, np.ones(len(offsets) - 1, bool))
                part = batch.slice(row, len(offsets) - 1)
                yield pa.RecordBatch.from_arrays([*part.columns, _list(ids, bound)], names=[*part.schema.names, name])

    return _text.lean(run)


def split_giants(df: DataFrame, longest: int, chunk: int = CHUNK) -> DataFrame:
    """(rid, text) to chunks of ``chunk`` characters (the longest piece's at least): rid, part_no, parts, part, and the characters next to it, left and right."""
    chunk = max(chunk, longest)
    pieces = F.regexp_extract_all("text", F.lit(rf"(?s).{{1,{chunk}}}"), F.lit(0))
    beside = lambda i, f: F.coalesce(f(F.get(F.col("pieces"), i), F.lit(longest)), F.lit(""))
    rows = df.select("rid", pieces.alias("pieces"))
    each = F.transform("pieces", lambda x, i: F.struct(i.alias("part_no"), beside(i - 1, F.right).alias("left"), x.alias("part"), beside(i + 1, F.left).alias("right")))
    return rows.select("rid", F.size("pieces").alias("parts"), F.explode(each).alias("x")).select("rid", "x.part_no", "parts", "x.left", "x.part", "x.right")


def _marked(row: dict) -> tuple[str, int, int]:
    """A chunk with its margins, spaces as marks and the mark before a text's beginning; where it begins and ends."""
    mark = lambda t: t.replace(" ", MARK)
    left, part = mark(row["left"]), (MARK if row["part_no"] == 0 else "") + mark(row["part"])
    return left + part + mark(row["right"]), len(left), len(left) + len(part)


def _transfers(make: Callable[[], object], marked: Callable):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = make()
        for batch in batches:
            moves = []
            for row in batch.to_pylist():
                text, begin, end = marked(row)
                matrix = transfer(model, text, begin, end, row["part_no"] == 0)
                moves.append([{"a": a, "b": b, "c": c, "d": d, "score": score} for (a, b), found in matrix.items() for (c, d), score in found.items()])
            yield pa.RecordBatch.from_arrays([batch.column("rid"), batch.column("part_no"), pa.array(moves, pa.list_(pa.struct([(x, pa.int32()) for x in "abcd"] + [("score", pa.float64())])))], names=["rid", "part_no", "moves"])

    return _text.lean(run)


def _scan(group: pa.Table) -> pa.Table:
    """The states of one text's chunks from all their matrices."""
    rows, matrices = group.sort_by("part_no").to_pylist(), []
    for row in rows:
        m: Matrix = {}
        for x in row["moves"]:
            m.setdefault((x["a"], x["b"]), {})[x["c"], x["d"]] = x["score"]
        matrices.append(m)
    s = scan(matrices)
    cols = {"rid": [r["rid"] for r in rows], "part_no": [r["part_no"] for r in rows], **{x: [y[i] for y in at] for x, at, i in (("a", s, 0), ("b", s, 1), ("c", s[1:], 0), ("d", s[1:], 1))}}
    n = len(rows)
    return pa.table([pa.array(v[:n], pa.int64() if k == "rid" else pa.int32()) for k, v in cols.items()], names=list(cols))


def scan_chunks(parts: DataFrame, make: Callable[[], object], marked: Callable, back: Callable, kind: str) -> DataFrame:
    """(rid, got array<kind>) of texts in chunks: transfer matrices by chunk, a scan by text, and each chunk traced back by itself."""
    moves = "rid long, part_no int, moves array<struct<a int, b int, c int, d int, score double>>"
    states = parts.mapInArrow(_transfers(make, marked), moves).groupBy("rid").applyInArrow(_scan, "rid long, part_no int, a int, b int, c int, d int")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = make()
        for batch in batches:
            got = []
            for row in batch.to_pylist():
                text, begin, end = marked(row)
                got.append(back(model, text, begin, end, (row["a"], row["b"]), (row["c"], row["d"])))
            yield pa.RecordBatch.from_arrays([batch.column("rid"), batch.column("part_no"), pa.array(got, pa.list_(pa.int32() if kind == "int" else pa.string()))], names=["rid", "part_no", "got"])

    traced = parts.join(states, ["rid", "part_no"]).mapInArrow(run, f"rid long, part_no int, got array<{kind}>")
    return traced.groupBy("rid").agg(F.flatten(F.transform(F.sort_array(F.collect_list(F.struct("part_no", "got"))), lambda x: x["got"])).alias("got"))


def segment_texts(docs: DataFrame, model: Unigram, chunk: int = CHUNK) -> DataFrame:
    """(rid long, text) to (rid, got array<string>): the best pieces of a unigram model. Texts without a character give no row."""

    def marked(row: dict) -> tuple[str, int, int]:
        return row["left"] + row["part"] + row["right"], len(row["left"]), len(row["left"]) + len(row["part"])

    def back(m: Unigram, text: str, begin: int, end: int, enter: State, leave: State) -> list[str]:
        return [text[s:e] for s, e, _ in trace(m, text, begin, end, enter, leave)]

    return scan_chunks(split_giants(docs, model.longest, chunk), lambda: model, marked, back, "string")


def encode(docs: DataFrame, path: str, name: str = "ids", chunk: int = CHUNK) -> DataFrame:
    """docs' columns and ``name`` array<int>: the ids that the library gives for the whole text.

    Texts of over ``chunk`` characters go in chunks through the max-plus scan, others are encoded where they are read.

    Defined cases: null or empty text has no ids. Rows stand alone, so null or
    repeated doc_ids don't matter. A column called ``name`` is replaced; other names are free,
    as only the text and a row's number go to Python. An empty table gives no rows.
    """
    docs = docs.select(*(c for c in docs.columns if c != name))
    text = F.coalesce("text", F.lit(""))
    giant = F.length(text) > chunk
    kind = ", ".join(f"c{i} {f.dataType.simpleString()}" for i, f in enumerate(docs.schema.fields))
    own = {f"c{i}": c for i, c in enumerate(docs.columns)}
    at = f"c{docs.columns.index('text')}"
    small = docs.filter(~giant).toDF(*own).mapInArrow(_encode(path, at, "ids"), f"{kind}, ids array<int>")
    if not codec(path).plain:
        return docs.toDF(*own).mapInArrow(_encode(path, at, "ids"), f"{kind}, ids array<int>").toDF(*own.values(), name)
    big = materialize(docs.filter(giant).toDF(*own).withColumn("rid", F.monotonically_increasing_id()), "giants")
    if big.isEmpty():
        discard(big)
        return small.toDF(*own.values(), name)
    longest = codec(path).merging.longest
    unmarked = big.select("rid", F.replace(F.col(at), F.lit(MARK), F.lit(" ")).alias("text"))
    parts = split_giants(unmarked, longest, chunk).repartition("rid", "part_no")
    back = lambda m, text, begin, end, enter, leave: codec(path).trace_ids(text, begin, end, enter, leave)
    whole = scan_chunks(parts, lambda: codec(path).merging, _marked, back, "int")
    return small.union(big.join(whole, "rid").select(*own, "got")).toDF(*own.values(), name)


def _flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values and offsets of a list column; null counts as empty."""
    column = pa.array([x or [] for x in column.to_pylist()], column.type) if column.null_count else column
    offsets = column.offsets.to_numpy()
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.int64), (offsets - offsets[0] if len(offsets) else np.zeros(1)).astype(np.int64)


def _slices(batch: pa.RecordBatch, ids: str) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Runs of whole rows of about SLICE ids, with these and their offsets."""
    values, offsets = _flat(batch.column(ids))
    row = 0
    while row < len(batch):
        to = max(row + 1, int(np.searchsorted(offsets, offsets[row] + SLICE, "right")) - 1)
        yield batch.slice(row, to - row), values[offsets[row] : offsets[to]], offsets[row : to + 1] - offsets[row]
        row = to


def _decode(path: str, ids: str, name: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            for part, values, offsets in _slices(batch, ids):
                yield pa.RecordBatch.from_arrays([*part.columns, c.decode_rows(values, offsets)], names=[*part.schema.names, name])

    return _text.lean(run)


def decode(df: DataFrame, path: str, ids: str = "ids", name: str = "decoded") -> DataFrame:
    """Adds ``name``: the text of an array of ids. Null or empty ids give the empty text; a column called ``name`` is replaced; an empty table gives no rows."""
    df = df.select(*(c for c in df.columns if c != name))
    own = {f"c{i}": c for i, c in enumerate(df.columns)}
    kind = ", ".join(f"c{i} {f.dataType.simpleString()}" for i, f in enumerate(df.schema.fields))
    return df.toDF(*own).mapInArrow(_decode(path, f"c{df.columns.index(ids)}", "decoded"), f"{kind}, decoded string").toDF(*own.values(), name)


def _trip(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            for part, ids, at in _slices(batch, "ids"):
                text = part.column("text")
                exact = pc.equal(c.decode_rows(ids, at), text.cast(pa.string()))
                listed = memoryview(_text.ragged(c.decimal, c.digits_at[ids], c.digits[ids]))
                bound = np.concatenate(([0], np.cumsum(c.digits[ids])))[at].tolist()
                digest = [hashlib.sha256(listed[x : max(x, y - 1)]).hexdigest() for x, y in zip(bound, bound[1:])]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pc.utf8_length(text).cast(pa.int64()), pa.array(np.diff(at)), pa.array(digest, "string"), exact], names=["doc_id", "n_chars", "n_ids", "ids_sha256", "exact"])

    return _text.lean(run)


def round_trip(docs: DataFrame, path: str, chunk: int = CHUNK) -> DataFrame:
    """Per row: doc_id, n_chars, n_ids, ids_sha256 (decimal ids, comma-joined), exact (decoding gives the text back).

    Defined cases: null counts as the empty text; rows stand alone; an empty table gives no rows.
    """
    coded = encode(docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text")), path, chunk=chunk)
    return coded.mapInArrow(_trip(path), "doc_id long, n_chars long, n_ids long, ids_sha256 string, exact boolean")
