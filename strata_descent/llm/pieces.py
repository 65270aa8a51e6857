"""SentencePiece encoding and decoding: sampled segmentations over the piece lattice.

A text is cut where a space starts, so a chunk is a word led by its space; pieces of the vocabulary
that match inside a chunk span its lattice, and bytes stand in for characters that no piece has.
Forward filtering sums, for each place of a chunk, the weights exp(temperature * score) of all
segmentations up to it; backward sampling then walks from the chunk's end, taking each piece with its
share of that sum.  Random numbers are a hash of seed, row key and place, so a row gets the same
segmentation wherever and however often it is computed.  All chunks of a batch walk together.  The
lattice takes pieces of every length that the vocabulary has, and chunks of every length: a text without
spaces is one lattice, whose memory is in proportion to its bytes.

Decoding joins the pieces, a space for each leading mark and a byte for each byte piece: it gives back
every text exactly, marks that the text itself holds included, as those are encoded as bytes.

Null and empty texts have no pieces.  Rows that repeat a key and text get the same pieces; rows without a
doc_id share a key.  Columns that are not named are not looked at.  Nothing is normalised.  An empty table
gives an empty result.  The vocabulary file is a parameter.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import words as kernel
from .common import documents, table

VOCABULARY = "/opt/tokenizers/piece_bpe_32k.model"
TEMPERATURE = 0.01
SEED = 4711
DENSE = 12  # pieces of up to so many bytes have a column of the lattice each; longer ones touch few places and are listed
TABLE_BITS = 16
MARK = "▁"
STEP_BYTES = 1 << 21  # of texts that walk together: words that several of them have are one chunk of the lattice
U64 = np.uint64
_PRIME = U64(0x100000001B3)


def _places(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two places of a hash in a table of 2**TABLE_BITS."""
    with np.errstate(over="ignore"):
        g = (h ^ h >> U64(31)) * U64(0x9E3779B97F4A7C15)
        return (g >> U64(64 - TABLE_BITS)).astype(np.int64), (g * U64(0xD6E8FEB86659FD93) >> U64(64 - TABLE_BITS)).astype(np.int64)


@dataclass(frozen=True)
class Vocabulary:
    """pieces: the bytes each id stands for, with the leading mark as a space; None: never in a lattice."""

    pieces: tuple[bytes | None, ...]
    scores: np.ndarray
    byte_ids: np.ndarray
    temperature: float

    @staticmethod
    def read(path: str = VOCABULARY, temperature: float = TEMPERATURE) -> Vocabulary:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces: list[bytes | None] = []
        byte_ids = np.zeros(256, dtype=np.int32)
        for i in range(model.get_piece_size()):
            if model.is_byte(i):
                byte_ids[int(model.id_to_piece(i)[3:5], 16)] = i
            text = model.id_to_piece(i)
            plain = not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i) or model.is_byte(i))
            inner = text.removeprefix(MARK) if plain else ""
            # a mark inside a piece stands for a space that starts another chunk
            ok = plain and MARK not in inner
            pieces.append(((" " if text.startswith(MARK) else "") + inner).encode() if ok else None)
        scores = np.array([model.get_score(i) for i in range(len(pieces))], dtype=np.float64)
        return Vocabulary(tuple(pieces), scores, byte_ids, temperature)

    @cached_property
    def longest(self) -> int:
        """Bytes of the longest piece."""
        return max((len(p) for p in self.pieces if p is not None), default=0)

    @cached_property
    def index(self) -> list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray] | None]:
        """By length, from 1 to the longest: a table of two places per hash, and by its entries hashes, ids and log weights."""
        out = []
        for n in range(1, self.longest + 1):
            ids = np.array([i for i, p in enumerate(self.pieces) if p is not None and len(p) == n], dtype=np.int32)
            if not len(ids):
                out.append(None)
                continue
            data = np.frombuffer(b"".join(self.pieces[i] for i in ids), dtype=np.uint8).reshape(len(ids), n)
            h = np.zeros(len(ids), dtype=U64)
            with np.errstate(over="ignore"):
                for j in range(n):
                    h = (h + data[:, j].astype(U64) + U64(1)) * _PRIME
            places = np.full(1 << TABLE_BITS, 0, dtype=np.int32)
            taken: dict[int, int] = {}
            options = np.stack(_places(h), axis=1).tolist()
            for i in range(len(ids)):
                at, place = i, options[i][0]
                for _ in range(64):  # an entry in the way moves to its other place
                    if place not in taken:
                        taken[place] = at
                        break
                    taken[place], at = at, taken[place]
                    place = options[at][1] if place == options[at][0] else options[at][0]
                else:
                    raise ValueError("the piece table is too full")
            places[list(taken)] = list(taken.values())
            out.append((places, h, ids, self.temperature * self.scores[ids]))
        return out

    @cached_property
    def byte_weight(self) -> float:
        """Log weight of a byte piece: below every piece, so that bytes are used where nothing else fits."""
        used = [self.scores[i] for i, p in enumerate(self.pieces) if p is not None and self.scores[i] > -1e8]
        return self.temperature * float(min(used)) - 20.0

    @cached_property
    def values(self) -> tuple[np.ndarray, np.ndarray]:
        """All pieces' bytes one after the other, and their bounds."""
        each = [p or b"" for p in self.pieces]
        for b, i in enumerate(self.byte_ids):
            each[i] = bytes([b])
        return np.frombuffer(b"".join(each), dtype=np.uint8), np.cumsum([0, *map(len, each)])

    def decode(self, ids: np.ndarray, rows: np.ndarray) -> tuple[bytes, np.ndarray]:
        """The bytes of all rows one after the other, and each row's bounds; rows: bounds of the rows in ids."""
        data, at = self.values
        length = (at[1:] - at[:-1])[ids]
        ends = np.cumsum(length)
        source = np.repeat(at[:-1][ids] - (ends - length), length) + np.arange(ends[-1] if len(ends) else 0)
        return data[source].tobytes(), np.concatenate([[0], ends])[rows]


def _chunks(data: np.ndarray, row_bytes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bounds of the chunks: a row's start, and every space or line break."""
    cut = (data == 0x20) | (data == 0x0A)
    after = np.zeros(len(data), dtype=bool)
    after[1:] = data[:-1] == 0x0A
    cut |= after
    inner = row_bytes[:-1][row_bytes[:-1] < row_bytes[1:]]
    cut[inner] = True
    starts = np.flatnonzero(cut)
    return starts, np.append(starts[1:], len(data))


def _distinct(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(a chunk of each kind, kind of each chunk)."""
    w = kernel.Words(data, starts, ends, np.array([0, len(starts)]), np.array([0, len(data)]))
    _, first, kind = np.unique(w.hashes(), return_index=True, return_inverse=True)
    return first, kind


@dataclass
class Long:
    """Pieces of more than DENSE bytes in a lattice, by the byte end they end at and by size; share: cumulative, after the dense ones."""

    end: np.ndarray
    size: np.ndarray
    ids: np.ndarray
    share: np.ndarray

    def draw(self, end: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(size, id) of the piece that u falls on at each of some byte ends that have long pieces."""
        k, stop = np.searchsorted(self.end, end, side="left"), np.searchsorted(self.end, end, side="right")
        while True:
            on = (k + 1 < stop) & (self.share[k] <= u)
            if not on.any():
                return self.size[k], self.ids[k]
            k[on] += 1


def _lattice(vocabulary: Vocabulary, data: np.ndarray, at: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray, Long]:
    """For each byte end of the distinct chunks: cumulative shares and ids of the pieces that end there, by length; those of long pieces.

    data: the chunks one after the other; at: their bounds; last: each byte's place in its chunk, from 0.
    """
    n = len(data)
    weight = np.full((n, DENSE), -np.inf, dtype=np.float32)
    ids = np.zeros((n, DENSE), dtype=np.int32)
    listed = [(np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int32), np.zeros(0))]
    wide = data.astype(U64) + U64(1)
    h = np.zeros(n, dtype=U64)  # after each round: hashes of the so many bytes from here
    end = np.arange(n)
    for size in range(1, vocabulary.longest + 1):
        if size > 1:
            end = end[last[end] >= size - 1]
        if not len(end):
            break
        begin = end - (size - 1)
        with np.errstate(over="ignore"):
            here = (h[begin] + wide[end]) * _PRIME
        h[begin] = here
        known = vocabulary.index[size - 1]
        if known is None:
            continue
        places, hashes, which, logs = known
        first, second = _places(here)
        found = places[first]
        hit = hashes[found] == here
        miss = np.flatnonzero(~hit)
        other = places[second[miss]]
        again = hashes[other] == here[miss]
        found[miss[again]] = other[again]
        hit[miss[again]] = True
        if size > DENSE:
            listed.append((end[hit], np.full(int(hit.sum()), size), which[found[hit]], logs[found[hit]]))
            continue
        weight[end[hit], size - 1] = logs[found[hit]]
        ids[end[hit], size - 1] = which[found[hit]]
    none = weight[:, 0] == -np.inf
    weight[none, 0] = vocabulary.byte_weight
    ids[none, 0] = vocabulary.byte_ids[data[none]]
    long_end, long_size, long_ids, long_logs = (np.concatenate(x) for x in zip(*listed, strict=True))
    by = np.lexsort((long_size, long_end))
    long = Long(long_end[by], long_size[by], long_ids[by], np.zeros(len(by), dtype=np.float32))
    long_logs = long_logs[by].astype(np.float32)
    long_order = np.argsort(last[long.end], kind="stable")
    # forward filtering, one byte of all chunks at a time; total has a 0 in front of each chunk's first byte
    chunks = len(at) - 1
    shifted = np.arange(n) + np.repeat(np.arange(chunks), np.diff(at)) + 1
    total = np.zeros(n + chunks)  # only differences of near ones are used, so a long chunk loses no digits
    shares = np.full((n, DENSE), 2.0, dtype=np.float32)
    order = np.argsort(last, kind="stable")
    bounds = np.searchsorted(last[order], np.arange(int(last.max(initial=-1)) + 2))
    long_bounds = np.searchsorted(last[long.end[long_order]], np.arange(len(bounds)))
    for place in range(len(bounds) - 1):
        here = order[bounds[place] : bounds[place + 1]]
        sizes = min(place + 1, DENSE)
        at_end = shifted[here]
        before_end = total[at_end - 1]
        logs = weight[here, :sizes]
        if sizes > 1:
            logs[:, 1:] += total[at_end[:, None] - np.arange(2, sizes + 1)] - before_end[:, None]
        most = logs.max(axis=1)
        more = long_order[long_bounds[place] : long_bounds[place + 1]]
        if len(more):
            ends = long.end[more]
            rows = np.searchsorted(here, ends)
            more_logs = long_logs[more] + (total[shifted[ends] - long.size[more]] - before_end[rows]).astype(np.float32)
            np.maximum.at(most, rows, more_logs)
        share = np.exp(logs - most[:, None])
        sums = np.cumsum(share, axis=1)
        whole = sums[:, -1]
        if len(more):
            more_share = np.exp(more_logs - most[rows])
            before = np.concatenate([[0], np.cumsum(more_share, dtype=np.float64)])
            upto = whole[rows] + before[1:] - before[np.searchsorted(rows, rows)]
            whole = whole.copy()
            np.add.at(whole, rows, more_share)
            long.share[more] = upto / whole[rows]
        total[at_end] = before_end + most + np.log(whole)
        shares[here, :sizes] = sums / whole[:, None]
    return shares, ids, long


def encode_rows(vocabulary: Vocabulary, data: np.ndarray, row_bytes: np.ndarray, keys: np.ndarray, seed: int = SEED) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all rows one after the other, bounds of the rows)."""
    rows = len(row_bytes) - 1
    if not len(data):
        return np.zeros(0, dtype=np.int32), np.zeros(rows + 1, dtype=np.int64)
    starts, ends = _chunks(data, row_bytes)
    first, kind = _distinct(data, starts, ends)
    length = (ends - starts)[first]
    at = np.concatenate([[0], np.cumsum(length)])
    last = np.arange(at[-1]) - np.repeat(at[:-1], length)
    shares, ids, long = _lattice(vocabulary, data[np.repeat(starts[first], length) + last], at, last)
    row = np.searchsorted(row_bytes, starts, side="right") - 1
    random = kernel.mix(keys[row] ^ kernel.mix((starts - row_bytes[row]).astype(U64), seed))
    end = at[1:][kind] - 1  # last byte not yet covered, among the distinct chunks
    begin = at[:-1][kind]
    live = np.arange(len(starts))
    who, where, got = [], [], []
    while len(live):
        random[live] = kernel.mix(random[live], 1)
        u = ((random[live] >> U64(40)).astype(np.float32) + np.float32(0.5)) / np.float32(1 << 24)
        u = np.minimum(u, np.nextafter(np.float32(1), np.float32(0)))  # it may be rounded to 1, past the last piece
        size = (shares[end[live]] <= u[:, None]).sum(axis=1)
        past = np.flatnonzero(size == DENSE)
        size[past] = 0
        piece = ids[end[live], size]
        if len(past):
            drawn, piece[past] = long.draw(end[live[past]], u[past])
            size[past] = drawn - 1
        got.append(piece)
        who.append(live)
        end[live] -= size + 1
        where.append(end[live] - begin[live])
        live = live[end[live] >= begin[live]]
    who_all, where_all, got_all = np.concatenate(who), np.concatenate(where), np.concatenate(got)
    order = np.argsort(starts[who_all] + where_all + 1, kind="stable")
    counts = np.bincount(row[who_all], minlength=rows)
    return got_all[order], np.concatenate([[0], np.cumsum(counts)])


def sample_pieces(docs: DataFrame, *more: str, path: str = VOCABULARY, temperature: float = TEMPERATURE, seed: int = SEED) -> DataFrame:
    """doc_id, the named columns, pieces (ids), n_pieces, decoded_sha256 (of the text decoded from pieces)."""
    kept = documents(docs, *more)
    names = ["doc_id", *more]
    keyed = kept.select(*names, "text", F.xxhash64(F.col("doc_id").cast("string")).alias("row_key"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema if f.name in names)

    def encoded(batches):
        vocabulary = Vocabulary.read(path, temperature)
        for batch in batches:
            data, at = kernel._bytes_of(batch.column(len(names)))
            keys = batch.column(len(names) + 1).to_numpy().view(U64)
            begin = 0
            while begin < len(keys):
                stop = min(max(int(np.searchsorted(at, at[begin] + STEP_BYTES, side="right")) - 1, begin + 1), len(keys))
                here = at[begin : stop + 1] - at[begin]
                ids, rows = encode_rows(vocabulary, data[at[begin] : at[stop]], here, keys[begin:stop], seed)
                text, bounds = vocabulary.decode(ids, rows)
                digests = [hashlib.sha256(text[a:z]).hexdigest() for a, z in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                part = batch.slice(begin, stop - begin)
                pieces = pa.ListArray.from_arrays(pa.array(rows.astype(np.int32)), pa.array(ids))
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(names))), pieces, pa.array(np.diff(rows).astype(np.int64)), pa.array(digests, pa.string())], [*names, "pieces", "n_pieces", "decoded_sha256"])
                begin = stop

    return keyed.mapInArrow(encoded, f"{schema}, pieces array<int>, n_pieces bigint, decoded_sha256 string")


def op7_pieces(spark, sf_dir: str) -> DataFrame:
    return sample_pieces(table(spark, sf_dir, "documents"))


QUERIES = {"op7_pieces": op7_pieces}
ORACLES: dict[str, str] = {}
