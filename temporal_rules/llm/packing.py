"""Pattern packing: few-document length patterns fitted to the length histogram.

Only the histogram of piece lengths (at most ``size`` numbers) reaches the driver.  There,
all ways to fill a sequence exactly with at most ``parts`` pieces are the columns of a
non-negative least-squares problem whose right side is the histogram; the fitted repeat
counts are rounded down, checked against what is left of each length, and what no pattern took is packed best fit,
longest first, on the histogram as well.  The plan says for every length which run of ranks
lies where, so each machine places its pieces alone.
"""

from __future__ import annotations

import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import numbered, reach_workers, staged

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, salt long"


def piece_table(docs: DataFrame, tokenizer: str, end_id: int, size: int, text: str = "text", doc_id: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """Pieces of all documents: ids of the text (null: empty), then ``end_id``; only a document of more
    than ``size`` ids is cut, and only its first piece may be shorter.  Repeated doc_ids stay apart by their rows."""
    from .tokens import by_bytes, encoder

    reach_workers(docs.sparkSession, 10_000)  # large batches: a word met twice in one is looked up once

    def cut(batches):
        enc = encoder(tokenizer)
        for batch in batches:
            for part in by_bytes(batch, 1):
                ids, off = enc.encode(part.column(1))
                n = np.diff(off) + 1
                wide = np.full(int(n.sum()), end_id, "<u4")
                ends = np.cumsum(n)
                keep = np.ones(len(wide), bool)
                keep[ends - 1] = False
                wide[keep] = ids
                k = -(-n // size)
                doc = np.repeat(np.arange(len(n)), k)
                piece = np.arange(len(doc)) - np.repeat(np.cumsum(k) - k, k)
                first = n - (k - 1) * size
                start = np.where(piece == 0, 0, first[doc] + (piece - 1) * size)
                length = np.where(piece == 0, first[doc], size)
                at = (ends - n)[doc] + start
                view = memoryview(wide).cast("B")
                spans = list(zip((at * 4).tolist(), ((at + length) * 4).tolist()))
                crc = np.array([zlib.crc32(view[a:b]) for a, b in spans], np.int64)
                out = [part.column(0).take(pa.array(doc)), pa.array(piece, pa.int32()), pa.array(start), pa.array(length), pa.array(crc)]
                names = ["doc_id", "piece", "start", "length", "ids_crc32"]
                if with_ids:
                    out.append(pa.array([wide[a // 4 : b // 4].tolist() for a, b in spans], pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.record_batch(out, names)

    kind = "doc_id long, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if with_ids else "")
    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(cut, kind).withColumn("salt", F.xxhash64("doc_id", "piece", "ids_crc32"))


def patterns(lengths: np.ndarray, size: int, parts: int) -> list[tuple[int, ...]]:
    """All ways to fill ``size`` exactly with 1..``parts`` (at most 3) of the given lengths, longest piece first."""
    have = np.zeros(size + 1, bool)
    have[lengths] = True
    out: list[tuple[int, ...]] = [(size,)] if have[size] else []
    long_first = sorted(map(int, lengths), reverse=True)
    for a in long_first:
        b = size - a
        if parts >= 2 and 0 < b <= a and have[b]:
            out.append((a, b))
    if parts >= 3:
        for a in long_first:
            rest = size - a
            for b in range(min(a, rest - 1), (rest + 1) // 2 - 1, -1):
                if have[b] and 0 < rest - b <= b and have[rest - b]:
                    out.append((a, b, rest - b))
    return out


def fit(columns: list[tuple[int, ...]], histogram: np.ndarray, sweeps: int = 12) -> list[float]:
    """Non-negative least squares by cyclic coordinate descent from zero.  A length's row weighs as its ids do,
    so what stays unfitted is mostly short and fills gaps later."""
    left = histogram.astype(float).tolist()
    weight = [(k + 1) / len(left) for k in range(len(left))]
    x = [0.0] * len(columns)
    counts = [[(k, c.count(k) * weight[k]) for k in dict.fromkeys(c)] for c in columns]
    times = [[(k, c.count(k)) for k in dict.fromkeys(c)] for c in columns]
    norm = [sum(m * c.count(k) for k, m in w) for c, w in zip(columns, counts)]
    active = range(len(columns))
    for turn in range(sweeps):
        moved, rest = 0.0, []
        for j in active:
            g = 0.0
            for k, m in counts[j]:
                g += m * left[k]
            step = g / norm[j]
            if step < -x[j]:
                step = -x[j]
            if step:
                x[j] += step
                for k, m in times[j]:
                    left[k] -= m * step
                moved = max(moved, abs(step))
            if x[j] > 0 or g > 0:
                rest.append(j)
        active = rest if turn % 4 else range(len(columns))
        if moved < 0.05:
            break
    return x


def plan(histogram: np.ndarray, size: int, parts: int = 3) -> list[tuple[tuple[int, ...], int]]:
    """(lengths in order, number of such sequences) which hold every piece of the histogram once."""
    left = histogram.astype(np.int64).copy()
    made: list[tuple[tuple[int, ...], int]] = []
    if left[size]:
        made.append(((size,), int(left[size])))
        left[size] = 0
    lengths = np.flatnonzero(left)
    columns = patterns(lengths, size, parts)
    times = fit(columns, left)
    remaining = left.tolist()
    for j in sorted(range(len(columns)), key=lambda j: -times[j]):
        want = int(times[j])
        for k in dict.fromkeys(columns[j]):
            want = min(want, remaining[k] // columns[j].count(k))
        if want > 0:
            made.append((columns[j], want))
            for k in columns[j]:
                remaining[k] -= want
    made += best_fit(remaining, size)
    return made


def best_fit(left: list[int], size: int) -> list[tuple[tuple[int, ...], int]]:
    """Best fit, longest first, on counts: equal open sequences are one entry, filled to the brim one after the other."""
    room_of: dict[int, list[list]] = defaultdict(list)
    for length in range(size, 0, -1):
        n = int(left[length])
        while n > 0:
            room = next((r for r in range(length, size) if room_of.get(r)), size)
            what, have = room_of[room].pop() if room < size else ((), n)
            each = room // length
            whole = min(have, n // each)
            if whole:
                room_of[room - each * length].append([what + (length,) * each, whole])
                n -= whole * each
            if whole < have and 0 < n < each:
                room_of[room - n * length].append([what + (length,) * n, 1])
                whole, n = whole + 1, 0
            if room < size and whole < have:
                room_of[room].append([what, have - whole])
    return [(what, n) for kinds in room_of.values() for what, n in kinds]


def placement(made: list[tuple[tuple[int, ...], int]]) -> dict[str, np.ndarray]:
    """For every length its runs of ranks: first rank, first sequence and offset of each run."""
    rows, ranks, sequence = [], defaultdict(int), 0
    for what, n in made:
        at = 0
        for length in what:
            rows.append((length, ranks[length], sequence, at))
            ranks[length] += n
            at += length
        sequence += n
    table = np.array(sorted(rows), np.int64).reshape(-1, 4)
    return {"key": (table[:, 0] << 44) | table[:, 1], "rank": table[:, 1], "sequence": table[:, 2], "offset": table[:, 3]}


def pack_pieces(pieces: DataFrame, size: int, parts: int = 3) -> DataFrame:
    """Adds sequence_id and offset to a staged table of pieces; columns beyond PIECES are carried along."""
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    histogram = np.zeros(size + 1, np.int64)
    for k, n in counts.items():
        histogram[k] = n
    where = placement(plan(histogram, size, parts))
    ranked = numbered(pieces, ["length"], "salt", ["doc_id", "piece", "start", "ids_crc32"], None, "__rank")
    spot = pieces.sparkSession.sparkContext.broadcast(where)  # at most one run for each place of a pattern or best-fit entry: a function of size

    def place(batches):
        w = spot.value
        for batch in batches:
            length = batch.column("length").to_numpy()
            rank = batch.column("__rank").to_numpy()
            run = np.searchsorted(w["key"], (length << 44) | rank, side="right") - 1
            keep = [i for i, n in enumerate(batch.schema.names) if n not in ("__rank", "salt")]
            arrays = [batch.column(i) for i in keep] + [pa.array(w["sequence"][run] + rank - w["rank"][run]), pa.array(w["offset"][run])]
            yield pa.record_batch(arrays, [batch.schema.names[i] for i in keep] + ["sequence_id", "offset"])

    kept = [f"`{f.name}` {f.dataType.simpleString()}" for f in ranked.schema if f.name not in ("__rank", "salt")]
    return ranked.mapInArrow(place, ", ".join([*kept, "sequence_id long", "offset long"]))


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int = 2, size: int = 1024, parts: int = 3, with_ids: bool = False) -> DataFrame:
    """All documents in sequences of at most ``size`` ids, one row for each piece.

    Null text is empty (its piece is the end id alone); null and repeated doc_ids are packed
    like others; an empty table gives no rows; other columns are ignored.
    """
    pieces = staged(piece_table(docs, tokenizer, end_id, size, with_ids=with_ids), "pieces")
    return pack_pieces(pieces, size, parts)
