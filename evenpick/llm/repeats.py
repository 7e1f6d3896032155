"""Removal of long repeated byte strings: Burrows-Wheeler transforms of shards merged by interleave refinement.

Every byte that lies in a 200-byte string which also starts elsewhere (in another text or the same one) is removed. Three lossless
reductions come first, so that transforms only hold what repeats can lie in:

* equal texts are handled as one (a text with a copy is covered whole if it has 200 bytes);
* every 200-byte window picks one 64-byte anchor inside itself by content alone, so equal windows pick equal anchors at equal places;
  only anchors that occur twice matter, and windows can only be equal inside one anchor's group;
* equal neighbourhoods of an anchor are one segment with a count.

Segments of anchors with different neighbourhoods are then dealt by anchor; a crowded anchor's group is cut into parts by the place of the anchor in
the window and what the windows of that place share, so no group goes to one task whole. A task's segments form shards, each with its own
transform (``Transform``: bytes before its suffixes in suffix order, and the rank steps). ``Interleave`` merges the transforms: an
interleave of their rows is refined by rank steps, one byte deeper each time, without comparing or sorting suffixes across shards. Where blocks split
tells the common prefixes; blocks that are still whole at depth 200 are the repeated intervals.

Defined results: null is the empty text; texts under 200 bytes lose nothing; repeated rows are copies of each other; offsets are UTF-8 bytes, so kept bytes
may cut a character; an empty table gives no rows; columns other than ``doc_id`` and ``text`` are ignored; texts of any length are
read in overlapping pieces.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenpick.llm.textbits import U, bounded_slices, prefix_hash, span_hash, utf8_buffer
from evenpick.plans.durable import maybe_broadcast, ship_package, shuffle_width, staged

LENGTH, ANCHOR = 200, 64
SLICE, PIECE, SLAB, SHARDS = 500_000, 4_000_000, 1_500_000, 4
#: Segments of one anchor that one task merges; more are cut into parts of so many places, step by step.
GROUP, PART_WIDTHS = 512, (8, 1)
BROADCAST_HASHES, BROADCAST_TEXTS = 1_000_000, 300_000
_PLACE = U((1 << 28) - 1)


def anchors(buf: np.ndarray, off: np.ndarray, length: int = LENGTH, width: int = ANCHOR, piece: int = PIECE):
    """(document, place, hash, first window, last window) of the anchors picked by all windows; offsets are into ``buf``.

    A window picks the least hashed ``width``-byte string in it, the rightmost of equals; windows that pick one anchor are neighbours.
    Long buffers are read in pieces that overlap by a window, so memory is bounded and a run of windows may come in two parts.
    """
    if len(buf) <= piece + length:
        return _anchors(buf, off, length, width)
    parts = []
    for s in range(0, len(buf) - length + 1, piece):
        e = min(s + piece + length - 1, len(buf))
        doc, place, h, first, last = _anchors(buf[s:e], np.clip(off, s, e) - s, length, width)
        parts.append((doc, place + s, h, first + s, last + s))
    return tuple(np.concatenate(x) for x in zip(*parts))


def _anchors(buf: np.ndarray, off: np.ndarray, length: int, width: int):
    none = np.zeros(0, np.int64)
    if len(buf) < length:
        return none, none, np.zeros(0, U), none, none
    prefix = prefix_hash(buf)
    at = np.arange(len(buf) - width + 1)
    h = span_hash(prefix, at, at + width)
    low = (h & ~_PLACE) | (_PLACE - at.astype(U))
    span, reach = length - width + 1, 1
    while reach * 2 <= span:
        low = np.minimum(low[:-reach], low[reach:])
        reach *= 2
    if reach < span:
        low = np.minimum(low[: len(low) - (span - reach)], low[span - reach :])
    starts = off[:-1][np.diff(off) >= length]
    stops = off[1:][np.diff(off) >= length] - length + 1
    docs = np.flatnonzero(np.diff(off) >= length)
    sizes = stops - starts
    if not len(sizes):
        return none, none, np.zeros(0, U), none, none
    base = np.repeat(starts - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes)
    window = base + np.arange(sizes.sum())
    doc = np.repeat(docs, sizes)
    place = (_PLACE - (low[window] & _PLACE)).astype(np.int64)
    fresh = np.ones(len(place), bool)
    fresh[1:] = (place[1:] != place[:-1]) | (doc[1:] != doc[:-1])
    first = np.flatnonzero(fresh)
    last = np.append(first[1:], len(place)) - 1
    return doc[first], place[first], h[place[first]], window[first], window[last]


class Transform:
    """The Burrows-Wheeler transform of one shard of segments, each ended by a mark of its own (marks sort first, in segment order).

    ``before`` holds the byte before every suffix in suffix order, ``head`` marks suffixes that are whole segments, and ``step`` is the
    rank step: the row of the suffix that is one byte longer. ``row_of`` finds the row of a position (segments laid out with their marks).
    """

    def __init__(self, segments: list[bytes]):
        size = np.array([len(s) + 1 for s in segments], np.int64)
        self.start = np.cumsum(size) - size
        n, self.segments = int(size.sum()), len(segments)
        marks = self.start + size - 1
        text = np.zeros(n, np.uint8)
        text[np.repeat(self.start, size - 1) + np.arange(n - len(size)) - np.repeat(self.start - np.arange(len(size)), size - 1)] = np.frombuffer(b"".join(segments), np.uint8)
        order = self._sorted(text, np.repeat(marks, size) - np.arange(n))
        self.row_of = np.empty(n, np.int64)
        self.row_of[order] = np.arange(n)
        self.before = text[order - 1]
        self.head = np.zeros(n, bool)
        self.head[self.row_of[self.start]] = True
        inner = np.flatnonzero(~self.head)
        self.step = np.full(n, -1, np.int64)
        self.step[inner[np.argsort(self.before[inner], kind="stable")]] = self.segments + np.arange(len(inner))

    @staticmethod
    def _sorted(text: np.ndarray, left: np.ndarray) -> np.ndarray:
        """Positions in suffix order, by doubling the compared length inside this shard; ``left`` counts the bytes before the mark."""
        reached = 7
        rank = np.zeros(len(text), np.int64)
        for j in range(reached):
            rank <<= 9
            rank[: len(text) - j] |= np.where(left[: len(text) - j] > j, text[j:].astype(np.int64) + 1, 0)
        order = np.argsort(rank, kind="stable")
        by_rank = rank[order]
        new = left[order] < reached  # such suffixes differ by their marks, whose order is that of the positions
        new[:1] = True
        new[1:] |= by_rank[1:] != by_rank[:-1]
        while not new.all():
            group = np.cumsum(new) - 1
            rank[order] = group
            tied = np.flatnonzero(~(new & np.append(new[1:], True)))
            at = order[tied]
            key = group[tied] * len(text) + rank[at + reached]
            by = np.argsort(key)
            key, order[tied] = key[by], at[by]
            new[tied[1:]] = key[1:] != key[:-1]
            reached *= 2
        return order


class Interleave:
    """The transforms of several shards merged by refining an interleave of their rows.

    A state lists rows in order and where its blocks begin: rows of one block agree so far. One refinement goes through the rows in
    order and sends each by its transform's rank step to the row one byte longer, dealt stably by that byte: blocks then agree one byte
    further. Nothing is compared but the bytes of the transforms, and rows of one shard keep their shard's order.
    """

    def __init__(self, shards: list[Transform]):
        origin = np.cumsum([0, *(len(s.before) for s in shards)])
        self.shards, self.origin = shards, origin
        self.before = np.concatenate([s.before for s in shards])
        self.head = np.concatenate([s.head for s in shards])
        self.step = np.concatenate([s.step + o for s, o in zip(shards, origin)])
        self.marks = np.concatenate([o + np.arange(s.segments) for s, o in zip(shards, origin)])

    @staticmethod
    def refine(new: np.ndarray, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(order, block beginnings) of rows dealt stably by the symbol before them."""
        by = np.argsort(symbol, kind="stable")
        block, symbol = np.cumsum(new)[by], symbol[by]
        fresh = np.ones(len(by), bool)
        fresh[1:] = (symbol[1:] != symbol[:-1]) | (block[1:] != block[:-1])
        return by, fresh

    def merged(self) -> tuple[np.ndarray, np.ndarray]:
        """(rows in merged order, common prefix of each row with the one before): refined until the blocks hold still."""
        row = np.arange(len(self.before))
        new = np.zeros(len(row), bool)
        new[:1] = True
        common, reached = np.zeros(len(row), np.int64), 0
        while True:
            inner = ~self.head[row]
            block = np.cumsum(new)[inner]
            by, fresh = self.refine(np.diff(block, prepend=0) > 0, self.before[row[inner]])
            after, fresh = np.concatenate([self.marks, self.step[row[inner][by]]]), np.concatenate([np.ones(len(self.marks), bool), fresh])
            common[fresh & ~new] = reached
            if (fresh == new).all() and (after == row).all():
                return row, common
            row, new, reached = after, fresh, reached + 1

    def repeated(self, ends: np.ndarray, depth: int) -> np.ndarray:
        """Which of the strings of ``depth`` bytes that end before the rows ``ends`` occur twice: blocks of one row leave as they arise.

        Two rank steps are taken at a time while two bytes are left to go.
        """
        which = np.arange(len(ends))
        by = np.argsort(ends, kind="stable")
        row, which, new = ends[by], which[by], np.zeros(len(ends), bool)
        new[:1] = True
        twice = np.where(self.head | self.head[self.step], -1, self.step[self.step])
        pair = self.before.astype(np.uint16) | (self.before[self.step].astype(np.uint16) << np.uint16(8))
        while depth and len(row):
            wide = depth > 1
            symbol, step = (pair, twice) if wide else (self.before, self.step)
            by, fresh = self.refine(new, symbol[row])
            keep = ~(fresh & np.append(fresh[1:], True))
            by, new = by[keep], fresh[keep]
            row, which = step[row[by]], which[by]
            depth -= 1 + wide
        out = np.zeros(len(ends), bool)
        out[which] = True
        return out


def repeated_windows(segments: list[bytes], length: int = LENGTH, shards: int = SHARDS) -> list[list[int]]:
    """For each segment the ranges [first, last, ...] of the starts of ``length``-byte strings that also start elsewhere."""
    step = -(-len(segments) // shards)
    merge = Interleave([Transform(segments[i : i + step]) for i in range(0, len(segments), step)])
    windows = np.array([max(len(s) - length + 1, 0) for s in segments], np.int64)
    first = np.concatenate([s.start + o for s, o in zip(merge.shards, merge.origin)]) + length
    row_of = np.concatenate([s.row_of + o for s, o in zip(merge.shards, merge.origin)])
    bounds = np.concatenate([[0], np.cumsum(windows)])
    ends = row_of[np.repeat(first - bounds[:-1], windows) + np.arange(bounds[-1])]
    hit = merge.repeated(ends, length)
    out = []
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
        edge = np.flatnonzero(np.diff(np.concatenate([[False], hit[a:b], [False]]).astype(np.int8)))
        edge[1::2] -= 1
        out.append(edge.tolist())
    return out


def _anchor_rows(batches):
    for b in bounded_slices(batches, limit=SLICE):
        buf, off = utf8_buffer(b.column(1))
        doc, place, h, _, _ = anchors(buf, off)
        yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), b.column(0).take(pa.array(doc)), pa.array((place - off[doc]).astype(np.int32))], names=["hash", "tid", "place"])


def _print(data: bytes, size: int = 16) -> bytes:
    return hashlib.blake2b(data, digest_size=size).digest()


def _segment_rows(batches):
    for b in bounded_slices(batches, limit=SLICE):
        buf, off = utf8_buffer(b.column(1))
        doc, place, h, first, last = anchors(buf, off)
        wanted = [np.asarray(x.as_py(), np.int64) for x in b.column(2)]
        key = np.concatenate([*(w + off[i] for i, w in enumerate(wanted)), np.zeros(0, np.int64)])
        keep = np.flatnonzero(np.isin(place, key))
        data = buf.tobytes()
        segs = [data[a : z + LENGTH] for a, z in zip(first[keep].tolist(), last[keep].tolist())]
        i32 = lambda x: pa.array(x[keep].astype(np.int32))
        yield pa.RecordBatch.from_arrays(
            [pa.array(h[keep].view(np.int64)), pa.array([_print(s) for s in segs], pa.binary()), pa.array(segs, pa.binary()), b.column(0).take(pa.array(doc[keep])), i32(first - off[doc]), i32(last - first), i32(place - first)],
            names=["hash", "print", "segment", "tid", "first", "more", "lead"],
        )


def _interval_rows(batches):
    """Slabs of whole groups; the input is dealt by ``hash`` and ordered by it, and no group has more than ``GROUP`` segments."""

    def slab(rows):
        spans = repeated_windows([r[2] for r in rows])
        kept = [(r[0], r[1], s) for r, s in zip(rows, spans) if s and r[3] == 1]
        h, p, s = zip(*kept) if kept else ((), (), ())
        return pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(p, pa.binary()), pa.array(s, pa.list_(pa.int32()))], names=["hash", "print", "spans"])

    held, size, last = [], 0, None
    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns)):
            if size >= SLAB and row[0] != last:
                yield slab(held)
                held, size = [], 0
            held.append(row)
            size, last = size + len(row[2]), row[0]
    if held:
        yield slab(held)


def _part_rows(width: int):
    """Segments of a crowded group cut into parts by where their windows hold the anchor, ``width`` places to a part.

    What all possible windows of a part have in common (``LENGTH`` + 1 - ``width`` bytes) is its new group: equal windows hold the anchor
    at the same place, so they meet there.
    """

    def run(batches):
        for batch in batches:
            out = []
            for h, name, segment, n, lead in zip(*(c.to_pylist() for c in batch.columns)):
                more = len(segment) - LENGTH
                for i in range((lead - more) // width, lead // width + 1):
                    a, z = max(0, lead - i * width - width + 1), min(more, lead - i * width)
                    inner = segment[lead - i * width : lead - i * width - width + 1 + LENGTH]
                    group = int.from_bytes(_print(h.to_bytes(8, "big", signed=True) + bytes([i]) + inner, 8), "big", signed=True)
                    part = segment[a : z + LENGTH]
                    out.append((h, name, group, _print(part), a, part, n, lead - a))
            if out:
                h, name, group, prints, a, part, n, lead = zip(*out)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(h, pa.int64()), pa.array(name, pa.binary()), pa.array(group, pa.int64()), pa.array(prints, pa.binary()), pa.array(a, pa.int32()), pa.array(part, pa.binary()), pa.array(n, pa.int64()), pa.array(lead, pa.int32())],
                    names=["whole_hash", "whole_print", "hash", "print", "shift", "segment", "n", "lead"],
                )

    return run


def _whole(segments: DataFrame) -> DataFrame:
    """(hash, print, spans) of segments that occur more than once: all their windows."""
    return segments.where("n > 1").select("hash", "print", F.array(F.lit(0), F.length("segment") - LENGTH).alias("spans"))


def interval_spans(unlike: DataFrame, widths: tuple[int, ...] = PART_WIDTHS) -> DataFrame:
    """(hash, print, spans) of segments ``(hash, print, segment, n, lead)`` that occur once and hold windows that others of their group hold.

    A group of more than ``GROUP`` segments is cut into parts by ``widths`` in turn, so no task gets one whole; in parts of
    width 1 windows that are equal are one row.
    """
    size = unlike.groupBy("hash").agg(F.count("*").alias("kinds"))
    crowded = staged(size.where(F.col("kinds") > GROUP).select("hash"), "crowded")
    cool = unlike.join(maybe_broadcast(crowded, BROADCAST_HASHES), "hash", "left_anti").select("hash", "print", "segment", "n")
    cool = cool.repartition(shuffle_width(unlike.sparkSession), "hash").sortWithinPartitions("hash", "print")
    spans = cool.mapInArrow(_interval_rows, "hash long, print binary, spans array<int>")
    if not widths or crowded.isEmpty():
        return spans
    hot = unlike.join(maybe_broadcast(crowded, BROADCAST_HASHES), "hash", "left_semi").select("hash", "print", "segment", "n", "lead")
    parts = staged(hot.mapInArrow(_part_rows(widths[0]), "whole_hash long, whole_print binary, hash long, print binary, shift int, segment binary, n long, lead int"), "anchor-parts", "zstd")
    kinds = staged(parts.groupBy("hash", "print").agg(F.sum("n").alias("n"), F.first("segment").alias("segment"), F.first("lead").alias("lead")), "part-kinds", "zstd")
    mixed = kinds.groupBy("hash").agg(F.count("*").alias("kinds")).where("kinds > 1").select("hash")
    found = _whole(kinds).unionByName(interval_spans(kinds.join(mixed, "hash", "left_semi"), widths[1:]))
    back = parts.where("n = 1").join(found, ["hash", "print"]).select(F.col("whole_hash").alias("hash"), F.col("whole_print").alias("print"), F.transform("spans", lambda x: x + F.col("shift")).alias("spans"))
    return spans.unionByName(back.groupBy("hash", "print").agg(F.flatten(F.collect_list("spans")).alias("spans")))


def removed_runs(windows: list[tuple[int, int]], length: int = LENGTH) -> list[tuple[int, int]]:
    """Maximal byte runs [from, to) covered by windows whose starts lie in the given ranges."""
    out: list[tuple[int, int]] = []
    for a, z in sorted(windows):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], z + length))
        else:
            out.append((a, z + length))
    return out


def _cut_rows(batches):
    for b in bounded_slices(batches, limit=SLICE):
        out = []
        for tid, text, windows in zip(*(c.to_pylist() for c in b.columns)):
            data = text.encode()
            runs = removed_runs([(w["a"], w["z"]) for w in windows])
            kept, at = hashlib.sha256(), 0
            for a, z in runs:
                kept.update(data[at:a])
                at = z
            kept.update(data[at:])
            out.append((tid, sum(z - a for a, z in runs), len(runs), kept.hexdigest(), [{"start": a, "stop": z} for a, z in runs]))
        tids, removed, spans, sha, runs = zip(*out)
        yield pa.RecordBatch.from_arrays(
            [pa.array(tids, pa.binary()), pa.array(removed, pa.int64()), pa.array(spans, pa.int64()), pa.array(sha), pa.array(runs, pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())])))],
            names=["tid", "n_removed", "n_spans", "kept_sha256", "runs"],
        )


def remove_repeats(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, runs): what repeats take from every document, judged on the whole input."""
    spark = docs.sparkSession
    ship_package(spark)
    text = F.coalesce("text", F.lit(""))
    rows = docs.select("doc_id", text.alias("text"), F.unhex(F.md5(text.cast("binary"))).alias("tid"), F.octet_length(text).cast("long").alias("n_bytes"))
    summary = staged(rows.select("doc_id", "tid", "n_bytes", F.sha2(F.col("text").cast("binary"), 256).alias("whole_sha")), "texts-summary")
    copies = summary.groupBy("tid").agg(F.count("*").alias("copies"))
    long_rows = rows.where(F.col("n_bytes") >= LENGTH)

    places = staged(long_rows.select("tid", "text").mapInArrow(_anchor_rows, "hash long, tid binary, place int"), "anchors", "zstd")
    mark = F.xxhash64("tid", "place")
    twice = places.groupBy("hash").agg(F.min(mark).alias("a"), F.max(mark).alias("b")).where("a <> b").select("hash")
    twice = staged(twice, "anchors-twice")
    wanted = places.join(maybe_broadcast(twice, BROADCAST_HASHES), "hash").groupBy("tid").agg(F.sort_array(F.collect_set("place")).alias("places"))
    wanted = staged(wanted, "anchor-places", "zstd")
    some = long_rows.select("tid", "text").join(maybe_broadcast(wanted.select("tid"), BROADCAST_TEXTS), "tid", "left_semi")
    texts = staged(some.groupBy("tid").agg(F.first("text").alias("text")).join(wanted, "tid").select("tid", "text", "places"), "anchor-texts", "zstd")

    segs = staged(texts.mapInArrow(_segment_rows, "hash long, print binary, segment binary, tid binary, first int, more int, lead int"), "segments", "zstd")
    kinds = staged(segs.groupBy("hash", "print").agg(F.count("*").alias("n"), F.min(F.struct("tid", "first")).alias("one")), "segment-kinds")
    mixed = kinds.groupBy("hash").agg(F.count("*").alias("kinds")).where("kinds > 1").select("hash")
    unlike = kinds.join(mixed, "hash").select("hash", "print", "n", F.col("one.tid").alias("tid"), F.col("one.first").alias("first"))
    unlike = segs.select("hash", "print", "segment", "lead", "tid", "first").join(unlike, ["hash", "print", "tid", "first"]).select("hash", "print", "segment", "n", "lead")
    spans = interval_spans(staged(unlike, "unlike", "zstd"))

    found = segs.select("hash", "print", "tid", "first", "more")
    whole = kinds.where("n > 1").select("hash", "print", F.lit(None).cast("array<int>").alias("spans"))
    found = found.join(whole.union(spans), ["hash", "print"])
    ends = F.when(F.col("spans").isNull(), F.array(F.struct(F.lit(0).alias("a"), F.col("more").alias("z")))).otherwise(
        F.transform(F.sequence(F.lit(0), F.shiftright(F.size("spans"), 1) - 1), lambda i: F.struct(F.get("spans", 2 * i).alias("a"), F.get("spans", 2 * i + 1).alias("z")))
    )
    windows = found.select("tid", F.explode(ends).alias("w"), "first").select("tid", F.struct((F.col("w.a") + F.col("first")).alias("a"), (F.col("w.z") + F.col("first")).alias("z")).alias("w"))
    windows = windows.groupBy("tid").agg(F.collect_list("w").alias("windows"))
    cut = texts.select("tid", "text").join(windows, "tid").mapInArrow(_cut_rows, "tid binary, n_removed long, n_spans long, kept_sha256 string, runs array<struct<start: long, stop: long>>")

    gone = (F.col("copies") > 1) & (F.col("n_bytes") >= LENGTH)
    out = summary.join(copies, "tid").join(cut, "tid", "left")
    nothing = F.array().cast("array<struct<start: bigint, stop: bigint>>")
    return out.select(
        "doc_id",
        "n_bytes",
        F.when(gone, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0))).alias("n_removed"),
        F.when(gone, F.lit(1)).otherwise(F.coalesce("n_spans", F.lit(0))).cast("long").alias("n_spans"),
        F.when(gone, F.sha2(F.lit("").cast("binary"), 256)).otherwise(F.coalesce("kept_sha256", "whole_sha")).alias("kept_sha256"),
        F.when(gone, F.array(F.struct(F.lit(0).cast("long").alias("start"), F.col("n_bytes").alias("stop")))).otherwise(F.coalesce("runs", nothing)).alias("runs"),
    )
