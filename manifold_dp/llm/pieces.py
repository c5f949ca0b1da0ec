"""SentencePiece encoding with seeded merge dropout, and decoding.

Encodes with the pieces and ranks of a public BPE model (white space as a piece mark, a
mark before each text, bytes for what has no piece). Candidate merges leave the agenda by
rank, then from the left; with dropout, a candidate is skipped if a keyed hash of (seed,
text id, occurrence, place, piece) falls below the rate, so a text is segmented the same
on every run with one seed and differently with another. Every segmentation decodes to
the same text; with a rate of 0 the result is the library's own encoding.

How it is fast: merges never cross a space mark that begins a word or a character without
piece, so texts part into short segments. Equal segments of a batch begin as one row of a
matrix, whose best candidate is taken in each round. Every occurrence draws by its own key
whether it skips that candidate; where occurrences of a row disagree, the row parts in
two, so those that have skipped the same so far share their work and nothing else.
Segments over ``WIDE`` symbols use a heap, each occurrence by itself. Results are then
laid out for each occurrence, decoded again and compared with the text.

A literal U+2581 in a text is written as its bytes, so that it is not read as a space.

Defined results: null text counts as empty and has no pieces; equal rows get equal
results; a null ``doc_id`` keys like 0; other columns pass through ``encode``; an empty
table gives an empty result.
"""

from __future__ import annotations

import hashlib
import heapq
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from .common import others, table
from .words import U64, mix, trim

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
RATE, SEED, WIDE = 0.1, 20240229, 48
MARK, LITERAL = 0x2581, 0x110000
_NONE = np.iinfo(np.int32).max
_STEP, _STEP_INV = U64(0x9E3779B97F4A7C15), U64(pow(0x9E3779B97F4A7C15, -1, 2**64))
#: Characters that are worked on together.
CHUNK = 1 << 20


class Pieces:
    """Tables of a BPE model."""

    def __init__(self, model: str = MODEL):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model)
        n = self.size = sp.get_piece_size()
        normal = [i for i in range(n) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i) or sp.is_byte(i))]
        ids = {sp.id_to_piece(i): i for i in normal}
        self.byte = np.array([sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)], np.int32)
        scores = np.array([sp.get_score(i) for i in range(n)])
        self.rank = np.unique(-scores, return_inverse=True)[1].astype(np.int32)
        self.of_char = np.full(0x110001, -1, np.int32)
        pairs: dict[tuple[int, int], int] = {}
        text = [b""] * n
        for p, i in ids.items():
            if chr(MARK) in p.lstrip(chr(MARK)):
                raise ValueError(f"the model merges across words: {p}")
            text[i] = p.replace(chr(MARK), " ").encode()
            if len(p) == 1:
                self.of_char[ord(p)] = i
            for k in range(1, len(p)):
                if p[:k] in ids and p[k:] in ids:
                    pairs[ids[p[:k]], ids[p[k:]]] = i
        for b in range(256):
            text[self.byte[b]] = bytes([b])
        self.pairs = pairs
        self.text_len = np.array([len(x) for x in text])
        self.text_at = np.r_[0, np.cumsum(self.text_len)[:-1]]
        self.text = np.frombuffer(b"".join(text), np.uint8)
        self.of_char[LITERAL] = -1
        self.bits = max(4, int(len(pairs) * 4).bit_length())
        self.slot_key, self.slot_id = np.full(1 << self.bits, -1, np.int64), np.full(1 << self.bits, -1, np.int32)
        self.tries = 1
        for (a, b), i in pairs.items():
            k = a * n + b
            s, t = int(self._slot(np.array([k]))[0]), 1
            while self.slot_key[s] >= 0:
                s, t = (s + 1) % (1 << self.bits), t + 1
            self.slot_key[s], self.slot_id[s], self.tries = k, i, max(self.tries, t)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.astype(U64) * _STEP) >> U64(64 - self.bits)).astype(np.int64)

    def merged(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The piece that two neighbours make, or -1."""
        key = a.astype(np.int64) * self.size + b
        key[(a < 0) | (b < 0)] = -2
        out = np.full(key.shape, -1, np.int32)
        slot = self._slot(key)
        left = np.arange(key.size)
        flat, res = key.ravel(), out.ravel()
        s = slot.ravel()
        for _ in range(self.tries):
            found = self.slot_key[s] == flat[left]
            res[left[found]] = self.slot_id[s[found]]
            more = ~found & (self.slot_key[s] >= 0)
            left, s = left[more], (s[more] + 1) % (1 << self.bits)
            if not len(left):
                break
        return res.reshape(key.shape)


@cache
def pieces(model: str = MODEL) -> Pieces:
    return Pieces(model)


def _skipped(key: np.ndarray, place: np.ndarray, piece: np.ndarray, rate: float) -> np.ndarray:
    h = mix(key ^ (place.astype(U64) * U64(0xC2B2AE3D27D4EB4F)) ^ (piece.astype(U64) << U64(40)))
    return (h >> U64(11)).astype(np.float64) < rate * 2.0**53


def _rounds(p: Pieces, sym: np.ndarray, key: np.ndarray, rate: float) -> np.ndarray:
    """Encode rows of symbols (-1 beyond their end), all at once, each with its own key."""
    done, which = _outcomes(p, sym, np.arange(len(sym)), key, rate)
    return done[which]


def _outcomes(p: Pieces, sym: np.ndarray, own: np.ndarray, key: np.ndarray, rate: float) -> tuple[np.ndarray, np.ndarray]:
    """Encode occurrences of rows of symbols: ``own`` their rows, ``key`` their keys. Different results as rows, and the one of each occurrence."""
    n, width = sym.shape
    sym = np.c_[sym, np.full(n, -1, np.int32)]
    done: list[np.ndarray] = []
    known = 0
    which = np.empty(len(own), np.int64)
    who = np.arange(len(own))
    place = np.broadcast_to(np.arange(width + 1, dtype=np.int32), sym.shape).copy()
    made = np.c_[p.merged(sym[:, :-1], sym[:, 1:]), np.full(n, -1, np.int32)]
    cost = np.where(made >= 0, p.rank[made], _NONE)
    col = np.arange(width + 1)[None, :]
    while len(sym):
        j = cost.argmin(1)
        live = cost[np.arange(len(sym)), j] < _NONE
        if not live.all():
            done.append(sym[~live, :width])
            ready = ~live[own]
            which[who[ready]] = known + (np.cumsum(~live) - 1)[own[ready]]
            known += len(done[-1])
            own, who = (np.cumsum(live) - 1)[own[~ready]], who[~ready]
            sym, place, made, cost, j = sym[live], place[live], made[live], cost[live], j[live]
            if not len(sym):
                break
        at = np.arange(len(sym))
        if rate:
            skip = _skipped(key[who], place[at, j][own], made[at, j][own], rate)
            some, others = np.zeros(len(sym), bool), np.zeros(len(sym), bool)
            some[own[skip]] = True
            others[own[~skip]] = True
            both = np.flatnonzero(some & others)
            if len(both):  # a row of their own for those that skip
                to = np.empty(len(sym), np.int64)
                to[both] = len(sym) + np.arange(len(both))
                moved = skip & others[own]
                own[moved] = to[own[moved]]
                apart = cost[both]
                apart[np.arange(len(both)), j[both]] = _NONE
                sym, place, made, cost = np.r_[sym, sym[both]], np.r_[place, place[both]], np.r_[made, made[both]], np.r_[cost, apart]
            only = some & ~others
            cost[at[only], j[only]] = _NONE
            at, j = at[~only], j[~only]
            if not len(at):
                continue
        # the pair at j becomes one symbol, what follows moves left
        sym[at, j] = made[at, j]
        src = np.minimum(col + (col > j[:, None]), width)
        sym[at] = np.take_along_axis(sym[at], src, 1)
        place[at] = np.take_along_axis(place[at], src, 1)
        src = np.minimum(col + (col > j[:, None]), width)
        made[at] = np.take_along_axis(made[at], src, 1)
        cost[at] = np.take_along_axis(cost[at], src, 1)
        right = np.minimum(j + 1, width)
        made[at, j] = m = p.merged(sym[at, j], sym[at, right])
        cost[at, j] = np.where(m >= 0, p.rank[m], _NONE)
        has = j > 0
        a, k = at[has], j[has] - 1
        made[a, k] = m = p.merged(sym[a, k], sym[a, k + 1])
        cost[a, k] = np.where(m >= 0, p.rank[m], _NONE)
    return np.concatenate(done) if done else sym[:, :width], which


def _agenda(p: Pieces, symbols: list[int], key: int, rate: float) -> list[int]:
    """The same for one long segment, with a heap and linked symbols."""
    n = len(symbols)
    sym, left, right = list(symbols), list(range(-1, n - 1)), [*range(1, n), -1]
    heap: list[tuple] = []

    def offer(i: int) -> None:
        j = right[i] if i >= 0 else -1
        if j >= 0 and (m := p.pairs.get((sym[i], sym[j]))) is not None:
            heapq.heappush(heap, (int(p.rank[m]), i, sym[i], sym[j], m))

    for i in range(n):
        offer(i)
    k = np.array([key], U64)
    while heap:
        _, i, a, b, m = heapq.heappop(heap)
        j = right[i]
        if sym[i] != a or j < 0 or sym[j] != b:
            continue
        if rate and _skipped(k, np.array([i]), np.array([m]), rate)[0]:
            continue
        sym[i], sym[j] = m, -1
        right[i] = right[j]
        if right[j] >= 0:
            left[right[j]] = i
        offer(left[i])
        offer(i)
    return [s for s in sym if s >= 0]


def _utf8(cp: int) -> bytes:
    return chr(MARK if cp == LITERAL else cp).encode()


def encode_texts(p: Pieces, texts: list[str], ids: np.ndarray, rate: float = 0.0, seed: int = SEED) -> tuple[np.ndarray, np.ndarray]:
    """Piece ids of all texts one after another, and the number of pieces of each."""
    chars = np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32).astype(np.int64)
    size = np.array([len(t) for t in texts], np.int64)
    chars[chars == MARK] = LITERAL
    chars[chars == 32] = MARK
    full = np.flatnonzero(size)
    chars = np.insert(chars, np.r_[0, np.cumsum(size)[:-1]][full], MARK)
    size = size + (size > 0)
    if not len(chars):
        return np.empty(0, np.int32), np.zeros(len(texts), np.int64)
    first = np.r_[0, np.cumsum(size)[:-1]]
    sym = p.of_char[chars]
    none, mark = sym < 0, chars == MARK
    starts = np.zeros(len(chars), bool)
    starts[first[full]] = True
    starts |= none
    starts[1:] |= none[:-1] | (mark[1:] & ~mark[:-1])
    s = np.flatnonzero(starts)
    n = np.diff(np.r_[s, len(chars)])
    power = np.multiply.accumulate(np.r_[U64(1), np.full(len(chars), _STEP)])
    back = np.multiply.accumulate(np.r_[U64(1), np.full(len(chars), _STEP_INV)])
    total = np.r_[U64(0), np.cumsum(mix(chars.astype(U64) + U64(1)) * power[:-1], dtype=U64)]
    same = mix((total[s + n] - total[s]) * back[s] + n.astype(U64))
    text_of = np.searchsorted(first[full], s, "right") - 1
    key, one, which = np.unique(same, return_index=True, return_inverse=True)
    if rate:  # every occurrence is encoded by a key of its own, else one stands for all
        doc = mix(ids[full].astype(np.int64).view(U64) + U64(seed))
        nth = (np.arange(len(s)) - np.searchsorted(text_of, text_of)).astype(U64)
        drop_key, by = mix(mix(doc[text_of] + nth * _STEP) ^ U64(seed)), which
    else:
        drop_key, by = np.zeros(len(key), U64), np.arange(len(key))
    member = np.argsort(by, kind="stable")  # occurrences by segment
    begin = np.searchsorted(by[member], np.arange(len(key) + 1))
    final = np.empty(len(by), np.int64)  # the result of each occurrence
    known = 0
    us, un = s[one], n[one]
    made: list[tuple[np.ndarray, np.ndarray]] = []  # sizes of results, symbols row by row
    unknown = none[us]
    low = 0
    for high in (4, 6, 8, 10, 12, 16, 24, WIDE):
        some = np.flatnonzero(~unknown & (un > low) & (un <= high))
        low = high
        for part in np.array_split(some, max(1, len(some) // 50_000)):
            if len(part):
                at = us[part][:, None] + np.arange(high)[None, :]
                m = np.where(np.arange(high)[None, :] < un[part][:, None], sym[np.minimum(at, len(sym) - 1)], -1)
                often = begin[part + 1] - begin[part]
                who = _gather(member, begin[part], often)
                out, got = _outcomes(p, m.astype(np.int32), np.repeat(np.arange(len(part)), often), drop_key[who], rate)
                final[who] = known + got
                known += len(out)
                made.append(((out >= 0).sum(1), out[out >= 0]))
    for i in np.flatnonzero(~unknown & (un > WIDE)).tolist():
        symbols = sym[us[i] : us[i] + un[i]].tolist()
        for x in member[begin[i] : begin[i + 1]].tolist():
            out = _agenda(p, symbols, int(drop_key[x]), rate)
            final[x] = known
            known += 1
            made.append((np.array([len(out)]), np.array(out, np.int32)))
    rare = np.flatnonzero(unknown)
    if len(rare):
        spelt = [p.byte[list(_utf8(int(c)))] for c in chars[us[rare]]]
        often = begin[rare + 1] - begin[rare]
        final[_gather(member, begin[rare], often)] = known + np.repeat(np.arange(len(rare)), often)
        made.append((np.array([len(x) for x in spelt]), np.concatenate(spelt)))
    flat = np.concatenate([m[1] for m in made]).astype(np.int32)
    lens = np.concatenate([m[0] for m in made])
    at = np.r_[0, np.cumsum(lens)[:-1]]
    which = final if rate else final[which]
    out = _gather(flat, at[which], lens[which])
    count = np.zeros(len(texts), np.int64)
    count[full] = np.add.reduceat(lens[which], np.searchsorted(text_of, np.arange(len(full))))
    return out, count


def _gather(flat: np.ndarray, at: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Stretches of ``flat`` one after another."""
    return flat[np.repeat(at - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum())]


def decode_ids(p: Pieces, ids: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts one after another without the mark before each, and their bounds."""
    data = _gather(p.text, p.text_at[ids], p.text_len[ids])
    end = np.r_[0, np.cumsum(p.text_len[ids])][np.r_[0, np.cumsum(count)]]
    keep = np.ones(len(data), bool)
    keep[end[:-1][count > 0]] = False
    return data[keep], end - np.r_[0, np.cumsum(count > 0)]


def _groups(texts: list[str]) -> Iterator[tuple[int, int]]:
    i, n = 0, 0
    for j, t in enumerate(texts):
        n += len(t)
        if n >= CHUNK:
            yield i, j + 1
            i, n = j + 1, 0
    if i < len(texts):
        yield i, len(texts)


def _coder(names: list[str], text: str, key: str, rate: float, seed: int, model: str, digest: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = pieces(model)
        for b in batches:
            texts = [t or "" for t in b.column(b.schema.get_field_index(text)).to_pylist()]
            keys = b.column(b.schema.get_field_index(key)).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
            for i, j in _groups(texts):
                ids, count = encode_texts(p, texts[i:j], keys[i:j], rate, seed)
                data, end = decode_ids(p, ids, count)
                whole = data.tobytes()
                back = [whole[a:z] for a, z in zip(end[:-1].tolist(), end[1:].tolist(), strict=True)]
                lossless = [x == t.encode() for x, t in zip(back, texts[i:j], strict=True)]
                bound = np.r_[0, np.cumsum(count)]
                own = [b.column(b.schema.get_field_index(n)).slice(i, j - i) for n in names]
                if digest:
                    raw = np.ascontiguousarray(ids, "<i4")
                    hashed = [hashlib.sha256(raw[a:z].tobytes()).hexdigest() for a, z in zip(bound[:-1].tolist(), bound[1:].tolist(), strict=True)]
                    yield pa.RecordBatch.from_arrays([*own, pa.array(count), pa.array(hashed), pa.array([hashlib.sha256(x).hexdigest() for x in back]), pa.array(lossless)], [*names, "n_pieces", "pieces_sha256", "decoded_sha256", "lossless"])
                elif not all(lossless):
                    raise ValueError("a text was not decoded to itself")
                else:
                    yield pa.RecordBatch.from_arrays([*own, pa.array(count), pa.ListArray.from_arrays(pa.array(bound, pa.int32()), pa.array(ids, pa.int32()))], [*names, "n_pieces", "pieces"])
            trim()

    return run


def encode(docs: DataFrame, rate: float = RATE, seed: int = SEED, model: str = MODEL) -> DataFrame:
    """``docs`` with ``n_pieces`` and ``pieces``; columns of these names are replaced."""
    names = others(docs.columns, "n_pieces", "pieces")
    schema = T.StructType([*(docs.schema[c] for c in names), T.StructField("n_pieces", T.LongType()), T.StructField("pieces", T.ArrayType(T.IntegerType()))])
    return docs.select(*names).mapInArrow(_coder(names, "text", "doc_id", rate, seed, model, False), schema)


def decode(encoded: DataFrame, model: str = MODEL) -> DataFrame:
    """``encoded`` with ``decoded``, the text of its ``pieces``."""
    names = others(encoded.columns, "decoded")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = pieces(model)
        for b in batches:
            lists = b.column(names.index("pieces"))
            count = pa.compute.list_value_length(lists).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
            data, end = decode_ids(p, lists.flatten().to_numpy(zero_copy_only=False), count)
            whole = data.tobytes()
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([whole[a:z].decode() for a, z in zip(end[:-1].tolist(), end[1:].tolist(), strict=True)], pa.string())], [*names, "decoded"])

    return encoded.select(*names).mapInArrow(run, T.StructType([*(encoded.schema[c] for c in names), T.StructField("decoded", T.StringType())]))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return docs.mapInArrow(_coder(["doc_id"], "text", "doc_id", RATE, SEED, MODEL, True), "doc_id long, n_pieces long, pieces_sha256 string, decoded_sha256 string, lossless boolean")
