"""SentencePiece encoding with seeded merge-dropout, and decoding.

A text's spaces become the space piece, one is put in front, and the text falls
into units at each run of spaces and at line ends, across which no piece of a
model of this kind reaches (checked when the model is read). Within a unit the
best-scored adjacent pair that makes a piece is merged until none is left
(leftmost of equal scores). A candidate merge, known by its unit and its start,
middle and end in it, is skipped for good if its keyed hash falls under the
dropout; so a candidate is skipped or not whatever is computed around it, and
reruns agree. The key holds the seed, the document, the number of its copy and the
unit's place in the text: a word is segmented anew wherever it stands. Equal units
of up to ``SHARED`` symbols whose coins fall alike on every merge that their spans
allow are merged once, and a task keeps what it merged of them and which merges their spans
allow (``Memo``, of bounded size); that changes no result.

Units are merged in step, one merge a round each, in arrays; units of more than
``LONG`` symbols use an agenda (a heap), with the same results. Characters without a piece become
byte pieces, and so does a literal space sign in a text: decoding is lossless.

Defined cases: null and empty texts have no tokens; rows that repeat a doc_id are
encoded each, alike unless a column numbers them; null doc_ids are one document; extra columns are ignored, and
``with_tokens`` keeps them; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from shapesig.llm.common import in_arrow, offsets_of, rows_of
from shapesig.llm.kernels import mixed, ragged, xxh64_spans

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SPACE_SIGN = "▁"
LONG, SHARED, DROPOUT, SEED = 48, 6, 0.1, 20
_U = np.uint64
_K = tuple(_U(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93))


def _slot(key: np.ndarray, slots: int) -> np.ndarray:
    """The first slot of each key among a power of two."""
    with np.errstate(over="ignore"):
        return ((key.astype(np.uint64) * _K[0]) >> _U(64 - slots.bit_length() + 1)).astype(np.int64)


def hashed(keys: np.ndarray) -> np.ndarray:
    """An open table of the places of distinct keys, filled to a quarter at most."""
    slots = np.full(1 << max(4, (4 * len(keys)).bit_length()), -1, np.int32)
    at, rest = _slot(keys, len(slots)), np.arange(len(keys))
    while len(rest):
        free = rest[slots[at[rest]] < 0]
        slots[at[free]] = free
        rest = rest[slots[at[rest]] != rest]
        at[rest] = (at[rest] + 1) & (len(slots) - 1)
    return slots


@dataclass(frozen=True)
class Model:
    """Tables of a model: symbols are pieces, then characters that only longer pieces hold."""

    pieces: int
    of_char: np.ndarray  # code point -> symbol, -1: none
    pairs: np.ndarray  # sorted left * symbols + right
    merged: np.ndarray
    rank: np.ndarray  # smaller merges first
    slots: np.ndarray  # hash table of places in ``pairs``, open addressing, -1: free
    symbols: int
    byte: np.ndarray  # byte -> piece
    text: np.ndarray  # bytes of all pieces as decoded
    text_at: np.ndarray
    space: int

    @staticmethod
    def read(path: str = MODEL) -> Model:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        kind = {i: sp.id_to_piece(i) for i in range(n) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))}
        if any("\n" in p or " " in p or SPACE_SIGN in p.lstrip(SPACE_SIGN) for p in kind.values()):
            raise ValueError("pieces of this model reach across spaces")
        known = {p: i for i, p in kind.items()}
        for c in sorted({c for p in known for c in p} - known.keys()):
            known[c] = n + len(known) - len(kind)
        symbols = n + len(known) - len(kind)
        of_char = np.full(0x110000, -1, np.int32)
        for p, i in known.items():
            if len(p) == 1:
                of_char[ord(p)] = i
        of_char[ord(SPACE_SIGN)] = -1
        of_char[32] = known[SPACE_SIGN]
        rows = sorted((known[p[:k]] * symbols + known[p[k:]], i) for i, p in kind.items() for k in range(1, len(p)) if p[:k] in known and p[k:] in known)
        merged = np.array([i for _, i in rows], np.int32)
        pairs = np.array([k for k, _ in rows], np.int64)
        score = np.array([sp.get_score(i) for i in range(n)])
        byte = np.full(256, -1, np.int32)
        out = [b""] * n
        for i, p in kind.items():
            out[i] = p.replace(SPACE_SIGN, " ").encode()
        for i in range(n):
            if sp.is_byte(i):
                v = int(sp.id_to_piece(i)[1:-1], 16)
                byte[v], out[i] = i, bytes([v])
        # The last of the merged pieces and ranks stand for pairs that make none.
        return Model(n, of_char, pairs, np.append(merged, np.int32(-1)), np.append(np.unique(-score[merged], return_inverse=True)[1], np.inf).astype(np.float32), hashed(pairs), symbols, byte, np.frombuffer(b"".join(out), np.uint8), np.cumsum([0, *map(len, out)]), known[SPACE_SIGN])

    def place(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Places of pairs in ``pairs``, -1 where they make no piece."""
        key = left.astype(np.int64) * self.symbols + right
        key[(left < 0) | (right < 0)] = -1
        if not len(self.pairs):
            return np.full(len(key), -1)
        at = _slot(key, len(self.slots))
        out = self.slots[at]
        here = np.flatnonzero((out >= 0) & (self.pairs[out] != key))
        while len(here):
            at[here] = (at[here] + 1) & (len(self.slots) - 1)
            out[here] = self.slots[at[here]]
            here = here[(out[here] >= 0) & (self.pairs[out[here]] != key[here])]
        return out

    def look(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Merged piece and rank of pairs; rank is infinite where they make none."""
        at = self.place(left, right)
        return self.merged[at], self.rank[at]


class Memo:
    """Values that a task found for keys of 64 bits, one after another; past ``most`` values it starts anew."""

    def __init__(self, rows: int, kind: type, most: int = 4_000_000):
        self.keys, self.begin, self.size, self.most = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), most
        self.values = np.zeros((rows, 0), kind)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Places of keys, -1 where they are unknown."""
        if not len(self.keys):
            return np.full(len(keys), -1)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, at, -1)

    def get(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The values at these places and their numbers."""
        return self.values[:, ragged(self.begin[at], self.size[at])], self.size[at]

    def add(self, keys: np.ndarray, size: np.ndarray, values: np.ndarray) -> None:
        """``keys`` are distinct and unknown."""
        if self.values.shape[1] + values.shape[1] > self.most:
            self.__init__(len(values), self.values.dtype.type, self.most)
            if values.shape[1] > self.most:
                return
        begin = self.values.shape[1] + np.cumsum(size) - size
        keys, begin, size = (np.concatenate(x) for x in ((self.keys, keys), (self.begin, begin), (self.size, size)))
        order = np.argsort(keys, kind="stable")
        self.keys, self.begin, self.size = keys[order], begin[order], size[order]
        self.values = np.concatenate([self.values, values.astype(self.values.dtype)], 1)


def memos() -> tuple[Memo, Memo]:
    """For spans (start, middle, end) by word, and for tokens by word and coins."""
    return Memo(3, np.uint8), Memo(1, np.int32)


def skipped(unit: np.ndarray, start: np.ndarray, middle: np.ndarray, end: np.ndarray, dropout: float) -> np.ndarray:
    """The coin of each candidate merge."""
    if dropout <= 0:
        return np.zeros(len(unit), bool)
    with np.errstate(over="ignore"):
        h = mixed(unit + start.astype(np.uint64) * _K[0] + middle.astype(np.uint64) * _K[1] + end.astype(np.uint64) * _K[2])
    return (h >> _U(11)).astype(np.float64) < dropout * 2.0**53


def merge_by_agenda(symbols: list[int], unit: int, model: Model, dropout: float) -> tuple[list[int], list[int]]:
    """Symbols left in one unit and their starts; candidates wait on a heap."""
    n = len(symbols)
    sym, nxt, prv = list(symbols), list(range(1, n + 1)), list(range(-1, n - 1))
    heap: list[tuple[float, int, int, int, int]] = []

    def offer(lefts: list[int]) -> None:
        lefts = [a for a in lefts if a >= 0 and nxt[a] < n]
        if not lefts:
            return
        rights = [nxt[a] for a in lefts]
        ends = [nxt[b] for b in rights]
        made, rank = model.look(np.array([sym[a] for a in lefts]), np.array([sym[b] for b in rights]))
        drop = skipped(np.full(len(lefts), unit, np.uint64), np.array(lefts), np.array(rights), np.array(ends), dropout)
        for a, b, e, m, r, d in zip(lefts, rights, ends, made.tolist(), rank.tolist(), drop.tolist(), strict=True):
            if r != np.inf and not d:
                heapq.heappush(heap, (r, a, b, e, m))

    offer(list(range(n - 1)))
    alive = [True] * n
    while heap:
        _, a, b, e, m = heapq.heappop(heap)
        if not (alive[a] and b < n and alive[b] and nxt[a] == b and nxt[b] == e):
            continue
        sym[a], nxt[a], alive[b] = m, e, False
        if e < n:
            prv[e] = a
        offer([prv[a], a])
    starts = [i for i in range(n) if alive[i]]
    return [sym[i] for i in starts], starts


def merge_in_step(cells: np.ndarray, sizes: np.ndarray, unit: np.ndarray, model: Model, dropout: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The same for many short units: rows of ``cells`` (padded); returns symbols, starts and counts."""
    n, width = cells.shape
    sym = np.concatenate([cells, np.full((n, 1), -1, cells.dtype)], 1)
    col = np.arange(width + 1)
    start = np.minimum(np.tile(col, (n, 1)), sizes[:, None]).astype(np.int32)
    count = sizes.copy()
    made, rank = np.full((n, width), -1, np.int32), np.full((n, width), np.inf, np.float32)
    row, at = np.nonzero(col[None, : width - 1] < sizes[:, None] - 1) if width > 1 else (np.zeros(0, int), np.zeros(0, int))

    def offer(rows: np.ndarray, a: np.ndarray, s: np.ndarray, st: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        m, r = model.look(s[rows, a], s[rows, a + 1])
        real = np.flatnonzero(r < np.inf)
        rr, aa = rows[real], a[real]
        drop = skipped(key[rr], st[rr, aa], st[rr, aa + 1], st[rr, aa + 2], dropout)
        r[real[drop]] = np.inf
        return m, r

    start = np.concatenate([start, sizes[:, None].astype(np.int32)], 1)
    if len(row):
        made[row, at], rank[row, at] = offer(row, at, sym, start, unit)
    out_sym, out_start, out_count = sym.copy(), start.copy(), count.copy()
    live = np.arange(n)
    while len(live):
        best = rank.argmin(1)
        go = rank[np.arange(len(live)), best] < np.inf
        if not go.all():
            end = ~go
            out_sym[live[end]], out_start[live[end]], out_count[live[end]] = sym[end], start[end], count[end]
            live, sym, start, count, made, rank, best, unit = (x[go] for x in (live, sym, start, count, made, rank, best, unit))
            if not len(live):
                break
        k = np.arange(len(live))
        sym[k, best] = made[k, best]
        # Everything after the merged pair moves one to the left.
        move = col[None, :-1] > best[:, None]
        sym[:, :-1] = np.where(move, sym[:, 1:], sym[:, :-1])
        start[:, :-1] = np.where(np.arange(start.shape[1] - 1)[None] > best[:, None], start[:, 1:], start[:, :-1])
        made[:, :-1] = np.where(move[:, : width - 1], made[:, 1:], made[:, :-1])
        rank[:, :-1] = np.where(move[:, : width - 1], rank[:, 1:], rank[:, :-1])
        rank[:, -1] = np.inf
        count -= 1
        for a in (best - 1, best):
            ok = np.flatnonzero((a >= 0) & (a < count - 1))
            made[k[ok], a[ok]], rank[k[ok], a[ok]] = offer(k[ok], a[ok], sym, start, unit)
            off = np.flatnonzero((a >= 0) & (a >= count - 1) & (a < width))
            rank[k[off], a[off]] = np.inf
    return out_sym[:, :width], out_start[:, :width], out_count


def spans_of(cells: np.ndarray, model: Model) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Every merge that can come up in the rows of ``cells`` (padded by -1): row, start, middle, end."""
    n, width = cells.shape
    sym = {(s, s + 1): cells[:, s] for s in range(width)}
    out = [np.zeros((4, 0), np.int64)]
    for size in range(2, width + 1):
        for s in range(width - size + 1):
            e = s + size
            made = np.full(n, -1, np.int64)
            for m in range(s + 1, e):
                at = np.flatnonzero((sym[s, m] >= 0) & (sym[m, e] >= 0))
                if len(at):
                    got = model.merged[model.place(sym[s, m][at], sym[m, e][at])]
                    at, got = at[got >= 0], got[got >= 0]
                    made[at] = got
                    out.append(np.stack([at, np.full(len(at), s), np.full(len(at), m), np.full(len(at), e)]))
            sym[s, e] = made
    row, start, middle, end = np.concatenate(out, 1)
    order = np.argsort(row, kind="stable")
    return row[order], start[order], middle[order], end[order]


def alike(word: np.ndarray, key: np.ndarray, at: np.ndarray, size: np.ndarray, ids: np.ndarray, model: Model, dropout: float, spans: Memo) -> np.ndarray:
    """Numbers that are equal only for units that are merged alike: the word and its coins, or the unit's own key."""
    if dropout <= 0:
        return word
    out = key.copy()
    low = 0
    for high in (x for x in (4, 6, 8, 12, 16) if x <= SHARED):
        here = np.flatnonzero((size > low) & (size <= high))
        low = high
        if not len(here):
            continue
        words, pick, of = np.unique(word[here], return_index=True, return_inverse=True)
        known = spans.find(words)
        fresh, old = np.flatnonzero(known < 0), np.flatnonzero(known >= 0)
        first, cols = here[pick[fresh]], np.arange(high)
        cells = np.where(cols[None] < size[first, None], ids[np.minimum(at[first, None] + cols, len(ids) - 1)], -1)
        row, *found = spans_of(cells, model)
        got, got_many = spans.get(known[old])
        s, m, e = np.concatenate([np.stack(found), got], 1).astype(np.int64)
        many, begin = np.zeros(len(words), np.int64), np.zeros(len(words), np.int64)
        many[fresh], many[old] = np.bincount(row, minlength=len(fresh)), got_many
        order = np.concatenate([fresh, old])
        begin[order] = np.cumsum(many[order]) - many[order]
        spans.add(words[fresh], many[fresh], np.stack(found))
        for block in np.array_split(np.arange(len(here)), max(1, int(many[of].sum()) // 400_000)):
            block = block[many[of[block]] <= 64]  # a bit for each
            w, unit = of[block], here[block]
            c = ragged(begin[w], many[w])
            whose = np.repeat(np.arange(len(block)), many[w])
            coin = skipped(key[unit][whose], s[c], m[c], e[c], dropout)
            mask = np.zeros(len(block), np.uint64)
            bit = (c - begin[w][whose])[coin].astype(np.uint64)
            np.bitwise_or.at(mask, whose[coin], _U(1) << bit)
            with np.errstate(over="ignore"):
                out[unit] = mixed(word[unit] + mixed(mask + _K[2]))
    return out


def encode_texts(texts: pa.Array, variant: np.ndarray, model: Model, dropout: float = DROPOUT, seed: int = SEED, memo: tuple[Memo, Memo] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of all texts in a row, and each text's number of them; ``variant`` tells documents and copies apart.

    ``memo`` serves calls with one model.
    """
    spans, done = memo or memos()
    texts = pc.fill_null(texts, "")
    off = offsets_of(texts)
    raw = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[off[0] : off[-1]]
    off = off - off[0]
    points = np.frombuffer(raw.tobytes().decode().encode("utf-32-le"), np.uint32)
    place = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])[off]
    n_chars = np.diff(place)
    full = np.flatnonzero(n_chars)
    points = np.insert(points, place[:-1][full], 32)  # the space in front
    n_chars = n_chars + (n_chars > 0)
    first = np.concatenate([[0], np.cumsum(n_chars)])
    if not len(points):
        return np.zeros(0, np.int32), np.zeros(len(texts), np.int64)
    begins = np.zeros(len(points), bool)
    begins[first[:-1][full]] = True
    begins[1:] |= ((points[1:] == 32) & (points[:-1] != 32)) | (points[1:] == 10) | (points[:-1] == 10)
    at = np.flatnonzero(begins)
    size = np.diff(np.append(at, len(points)))
    doc = np.searchsorted(first, at, "right") - 1
    with np.errstate(over="ignore"):
        word = xxh64_spans(np.concatenate([points, np.zeros(2, np.uint32)]).view(np.uint8), at * 4, size * 4, seed)
        place = np.arange(len(at)) - np.searchsorted(doc, doc)
        key = mixed(mixed(word + variant[doc].astype(np.uint64) * _K[0]) + place.astype(np.uint64) * _K[1])
    ids = model.of_char[points]
    numbers, pick, inverse = np.unique(alike(word, key, at, size, ids, model, dropout, spans), return_index=True, return_inverse=True)
    known = done.find(numbers)
    fresh, old = np.flatnonzero(known < 0), np.flatnonzero(known >= 0)
    flat_new, new = merged(points, ids, at[pick[fresh]], size[pick[fresh]], key[pick[fresh]], model, dropout)
    flat_old, said = done.get(known[old])
    # Only a word's number can come again: units that go by their own key can't.
    again = numbers[fresh] != key[pick[fresh]]
    done.add(numbers[fresh][again], new[again], flat_new[None, np.repeat(again, new)])
    per_unit, begin = np.zeros(len(numbers), np.int64), np.zeros(len(numbers), np.int64)
    per_unit[fresh], per_unit[old] = new, said
    order = np.concatenate([fresh, old])
    begin[order] = np.cumsum(per_unit[order]) - per_unit[order]
    flat = np.concatenate([flat_new, flat_old[0]])[ragged(begin[inverse], per_unit[inverse])]
    return flat, np.bincount(doc, per_unit[inverse], len(texts)).astype(np.int64)


def merged(points: np.ndarray, ids: np.ndarray, at_u: np.ndarray, size_u: np.ndarray, key_u: np.ndarray, model: Model, dropout: float) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of units in a row, and each unit's number of them."""
    if not len(at_u):
        return np.zeros(0, np.int32), np.zeros(0, np.int64)
    parts: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []  # unit, symbol, start, end; units in some order
    low = 0
    for high in (*(x for x in (4, 6, 8, 12, 16, 24, 32) if x < LONG), LONG):
        us = np.flatnonzero((size_u > low) & (size_u <= high))
        low = high
        for block in np.array_split(us, max(1, len(us) * high // 250_000)):
            if not len(block):
                continue
            cols = np.arange(high)
            inside = cols[None] < size_u[block, None]
            cells = np.where(inside, ids[np.minimum(at_u[block, None] + cols, len(ids) - 1)], -1)
            s, st, c = merge_in_step(cells, size_u[block], key_u[block], model, dropout)
            keep = cols[None] < c[:, None]
            nxt = np.concatenate([st[:, 1:], size_u[block, None]], 1)
            nxt = np.where(cols[None] == c[:, None] - 1, size_u[block, None], nxt)
            parts.append((np.repeat(block, c), s[keep], st[keep], nxt[keep]))
    for u in np.flatnonzero(size_u > LONG).tolist():
        s, st = merge_by_agenda(ids[at_u[u] : at_u[u] + size_u[u]].tolist(), int(key_u[u]), model, dropout)
        parts.append((np.full(len(s), u), np.array(s), np.array(st), np.array([*st[1:], size_u[u]])))
    unit, sym, st, en = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.argsort(unit, kind="stable")
    unit, sym, st, en = unit[order], sym[order], st[order], en[order]
    # Symbols without a piece become their bytes.
    bare = np.flatnonzero((sym < 0) | (sym >= model.pieces))
    wide = np.ones(len(sym), np.int64)
    char = points[at_u[unit[bare]] + st[bare]]
    utf = 1 + (char > 0x7F).astype(np.int64) + (char > 0x7FF) + (char > 0xFFFF)
    wide[bare] = utf
    tokens = np.repeat(sym, wide).astype(np.int32)
    if len(bare):
        data = np.frombuffer(char.astype("<u4").tobytes().decode("utf-32-le").encode(), np.uint8)
        tokens[ragged((np.cumsum(wide) - wide)[bare], utf)] = model.byte[data]
    return tokens, np.bincount(unit, wide, len(at_u)).astype(np.int64)


def decode_tokens(tokens: np.ndarray, counts: np.ndarray, model: Model) -> list[bytes]:
    """UTF-8 bytes of each text."""
    size = np.diff(model.text_at)[tokens]
    data = model.text[ragged(model.text_at[tokens], size)].tobytes()
    ends = np.cumsum(np.concatenate([[0], size]))[np.concatenate([[0], np.cumsum(counts)])]
    return [data[a + 1 : b] if b > a else b"" for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]


def _drawn(ids: pa.Array, seed: int, copies: pa.Array | None = None) -> np.ndarray:
    """A number for each document and copy."""
    given = np.asarray(ids.fill_null(0)).astype(np.int64).view(np.uint64)
    number = np.zeros(len(ids), np.uint64) if copies is None else np.asarray(copies.fill_null(0)).astype(np.uint64)
    with np.errstate(over="ignore"):
        drawn = np.where(np.asarray(ids.is_null()), _U(0), mixed(given * _K[1] + _U(seed)))
        return mixed(drawn + number * _K[2])


def with_tokens(docs: DataFrame, model_path: str = MODEL, dropout: float = DROPOUT, seed: int = SEED, column: str = "tokens", copy: str | None = None) -> DataFrame:
    """All rows and columns, and the tokens (array of int); ``copy`` names a column that numbers the copies of a document."""
    held = docs.sparkSession.sparkContext.broadcast(Model.read(model_path))  # a vocabulary, of fixed size
    schema = T.StructType([*(f for f in docs.schema.fields if f.name != column), T.StructField(column, T.ArrayType(T.IntegerType()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, memo = held.value, memos()
        for batch in batches:
            for part in rows_of(batch, "text", 1 << 20):
                i, t = (part.schema.get_field_index(c) for c in ("doc_id", "text"))
                flat, counts = encode_texts(part.column(t), _drawn(part.column(i), seed, part.column(part.schema.get_field_index(copy)) if copy else None), model, dropout, seed, memo)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)), pa.array(flat, pa.int32()))
                kept = [f.name for f in part.schema if f.name != column]
                yield pa.RecordBatch.from_arrays([*(part.column(part.schema.get_field_index(c)) for c in kept), lists], [*kept, column])

    return in_arrow(docs, run, schema)


def decode(rows: DataFrame, model_path: str = MODEL, column: str = "tokens") -> DataFrame:
    """(doc_id, text) from tokens."""
    held = rows.sparkSession.sparkContext.broadcast(Model.read(model_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts = np.diff(offsets_of_list(batch.column(1)))
            texts = decode_tokens(np.asarray(batch.column(1).flatten()), counts, held.value)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x.decode() for x in texts], pa.string())], ["doc_id", "text"])

    return rows.select("doc_id", column).mapInArrow(run, "doc_id long, text string")


def offsets_of_list(lists: pa.Array) -> np.ndarray:
    return np.asarray(lists.offsets).astype(np.int64)


def report(docs: DataFrame, model_path: str = MODEL, dropout: float = DROPOUT, seed: int = SEED) -> DataFrame:
    """Per document: tokens, code points, digests of the tokens (32-bit little-endian) and of the decoded text, and whether that is the text."""
    held = docs.sparkSession.sparkContext.broadcast(Model.read(model_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, memo = held.value, memos()
        for batch in batches:
            for part in rows_of(batch, "text", 1 << 20):
                flat, counts = encode_texts(part.column(1), _drawn(part.column(0), seed), model, dropout, seed, memo)
                back = decode_tokens(flat, counts, model)
                ends = np.cumsum(np.concatenate([[0], counts])).tolist()
                texts = [x.as_buffer().to_pybytes() if x.is_valid else b"" for x in part.column(1)]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array(counts), pa.array([len(x.decode()) for x in back], pa.int64()), pa.array([hashlib.sha256(flat[a:b].astype("<i4").tobytes()).hexdigest() for a, b in zip(ends, ends[1:], strict=False)]), pa.array([hashlib.sha256(x).hexdigest() for x in back]), pa.array([x == y for x, y in zip(back, texts, strict=True)])],
                    ["doc_id", "n_tokens", "n_chars", "tokens_sha256", "decoded_sha256", "lossless"],
                )

    return in_arrow(docs.select("doc_id", "text"), run, "doc_id long, n_tokens long, n_chars long, tokens_sha256 string, decoded_sha256 string, lossless boolean")
