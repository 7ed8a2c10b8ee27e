"""Substring dedup: remove the words of every fixed-length window that also starts earlier.

Rabin-Karp hashes of all windows of ``width`` words are counted in Spark. To shuffle
little, windows are first grouped by the least hash of their ``gram``-word runs: equal
windows share it, and neighbours mostly share one, so a run of up to 32 windows is one
row. Only runs whose least hash occurs twice go on with their window hashes; there,
64 bits of the run's key and 64 bits of the window decide equality. Repeats inside one
slice of a task are settled on the spot and one of them goes on, so a passage that a
third of all documents hold makes a row per slice and not one per document.

Defined results: null or empty text has no words; fewer words than ``width`` means no
window; an exactly repeated row (same id and text) counts as one document and each of
its rows gets the same result; rows of one id with different texts are ordered by a
hash of the text, a null id comes last. Extra columns are not read.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import words as W
from .shared import null_last

#: Windows in one row at most; they are bits of a long.
RUN = 32
#: Bytes of text (of compressed text half as many) that a worker handles at once.
SLICE = 2 << 20


def _runs(windows: W.Words, width: int, gram: int) -> tuple[np.ndarray, ...]:
    """key, document row, first window and number of windows of each run, and 2 if its key occurs in it more than once."""
    h = windows.hashes()
    n = len(h) - width + 1
    empty = np.zeros(0, np.int64)
    if n <= 0:
        return np.zeros(0, np.uint64), empty, empty, empty, empty
    g = W.rolling(h, gram)
    least = g[:n].copy()
    for j in range(1, width - gram + 1):
        np.minimum(least, g[j : n + j], out=least)
    whole = windows.doc[:n] == windows.doc[width - 1 :]
    begin = whole.copy()
    begin[1:] &= ~whole[:-1] | (least[1:] != least[:-1]) | (windows.doc[1:n] != windows.doc[: n - 1])
    at = np.flatnonzero(whole)
    begun = np.flatnonzero(begin)
    begin[at] |= (at - begun[np.searchsorted(begun, at, "right") - 1]) % RUN == 0
    begun = np.flatnonzero(begin)
    length = np.bincount(np.searchsorted(begun, at, "right") - 1, minlength=len(begun))
    doc = windows.doc[begun]
    # a run may repeat windows of its own if its least hash occurs in it twice
    key, own = least[begun], np.zeros(len(begun), np.int64)
    for j in range(int(length.max(initial=0)) + width - gram):
        own += (j < length + width - gram) & (g[np.minimum(begun + j, len(g) - 1)] == key)
    return key, doc, begun - windows.first[doc], length, np.minimum(own, 2)


def _salted(key: np.ndarray, *of: np.ndarray) -> np.ndarray:
    for x in of:
        key = W.mix(key ^ (x.astype(np.uint64) * W.BASE))
    return key


def find_runs(width: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in W.pieces(batches, "text", SLICE):
            key, doc, first, length, own = _runs(W.split(*W.utf8(part.column(2))), width, gram)
            if not len(key):
                continue
            _, where, times = np.unique(key, return_index=True, return_counts=True)
            count = np.zeros(len(key), np.int64)
            count[where] = np.maximum(times, 1)
            local = count == 0
            count = np.maximum(count, own)
            rows = pa.array(doc)
            yield pa.RecordBatch.from_arrays(
                [pa.array(W.signed(np.where(local, _salted(key, doc, first), key))), part.column(0).take(rows), part.column(1).take(rows), pa.array(first << 6 | length), pa.array(np.where(local, 2, count))],
                ["key", "ord", "th", "run", "times"],
            )

    return run


def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts travel compressed; what they are joined with comes back to Python anyway."""
    for batch in W.pieces(batches, "text", SLICE):
        at = batch.schema.get_field_index("text")
        packed = [None if x is None else zlib.compress(x, 1) for x in batch.column(at).cast(pa.binary()).to_pylist()]
        yield batch.set_column(at, "text", pa.array(packed, pa.binary()))


def unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in W.pieces(batches, "text", SLICE // 2):
        at = batch.schema.get_field_index("text")
        texts = [None if x is None else zlib.decompress(x) for x in batch.column(at).to_pylist()]
        yield batch.set_column(at, "text", pa.array(texts, pa.large_binary()))


def hash_runs(width: int, gram: int):
    """For the runs that may repeat: their window hashes, and a mask of windows with an earlier equal one in this slice."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in W.pieces(unpacked(batches), "text", SLICE):
            text = W.split(*W.utf8(part.column(2)))
            h = text.hashes()
            if len(h) < width:
                continue
            window = W.rolling(h, width)
            g = W.rolling(h, gram)
            flat = part.column(3)
            runs = np.asarray(flat.flatten(), np.int64)
            doc = np.repeat(np.arange(part.num_rows), np.asarray(flat.value_lengths(), np.int64))
            first, length = runs >> 6, runs & 63
            at = np.cumsum(length) - length
            row = np.repeat(np.arange(len(runs)), length)
            place = np.arange(len(row)) - at[row]
            index = (text.first[doc] + first)[row] + place
            key = g[index[at]].copy()
            for j in range(1, width - gram + 1):
                np.minimum(key, g[index[at] + j], out=key)
            ids, hashes = np.asarray(part.column(0), np.int64), np.asarray(part.column(1), np.int64)
            rank = np.empty(part.num_rows, np.int64)
            order = np.lexsort((hashes, ids))
            changed = np.r_[False, (ids[order][1:] != ids[order][:-1]) | (hashes[order][1:] != hashes[order][:-1])] if len(order) else order
            rank[order] = np.cumsum(changed)
            start = first[row] + place
            by = np.lexsort((start, rank[doc[row]], window[index], key[row]))
            same = (window[index][by][1:] == window[index][by][:-1]) & (key[row][by][1:] == key[row][by][:-1])
            twin = same & (rank[doc[row]][by][1:] == rank[doc[row]][by][:-1]) & (start[by][1:] == start[by][:-1])
            group = np.cumsum(np.r_[True, ~same])
            lead = np.flatnonzero(np.r_[True, ~same])
            later = np.ones(len(by), bool)
            later[lead] = False
            # an exactly repeated row is its own first occurrence
            chain = np.cumsum(np.r_[0, ~twin])
            later &= chain != chain[lead][group - 1]
            known = np.zeros(len(row), bool)
            known[by] = later
            mask = np.add.reduceat(known.astype(np.int64) << place, at)
            done = mask == (np.int64(1) << length) - 1
            keep = ~done[row]
            rows = pa.array(doc)
            yield pa.RecordBatch.from_arrays(
                [pa.array(W.signed(np.where(done, _salted(key, doc, first), key))), part.column(0).take(rows), part.column(1).take(rows), pa.array(runs), pa.array(mask), W.lists(pa.array(W.signed(window[index])[keep]), np.where(done, 0, length))],
                ["key", "ord", "th", "run", "known", "windows"],
            )

    return run


def _covered(runs: np.ndarray, masks: np.ndarray, n: int, width: int) -> list[tuple[int, int]]:
    """Maximal intervals of words under the marked windows."""
    edge = np.zeros(n + 1, np.int32)
    for b in range(RUN):
        at = (runs >> 6)[(masks >> b) & 1 == 1] + b
        np.add.at(edge, at, 1)
        np.add.at(edge, at + width, -1)
    inside = np.cumsum(edge[:n]) > 0
    turn = np.flatnonzero(np.diff(np.r_[False, inside, False].astype(np.int8)))
    return list(zip(turn[::2].tolist(), turn[1::2].tolist(), strict=True))


def cut(width: int, with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # the texts are compressed
        for batch in W.pieces(batches, "text", W.CHUNK_BYTES // 2):
            n_words, n_removed, digest, kept_text, spans = [], [], [], [], []
            for text, runs, masks in zip(*(batch.column(k).to_pylist() for k in (1, 2, 3)), strict=True):
                text = zlib.decompress(text) if text is not None else None
                words = (text or b"").split()
                found = _covered(np.array(runs), np.array(masks), len(words), width) if runs else []
                if found:
                    kept, at = [], 0
                    for a, b in found:
                        kept += words[at:a]
                        at = b
                    kept += words[at:]
                else:
                    kept = words
                joined = b" ".join(kept)
                n_words.append(len(words))
                n_removed.append(len(words) - len(kept))
                digest.append(hashlib.sha256(joined).hexdigest())
                if with_text:
                    kept_text.append(joined.decode() if found else None if text is None else text.decode())
                    spans.append([{"first": a, "last": b - 1} for a, b in found])
            out = [batch.column(0), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(digest, pa.string())]
            names = ["doc_id", "n_words", "n_removed", "kept_sha256"]
            if with_text:
                out += [pa.array(kept_text, pa.string()), pa.array(spans, pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64())]))), *batch.columns[4:]]
                names += ["kept_text", "removed", *batch.schema.names[4:]]
            yield pa.RecordBatch.from_arrays(out, names)

    return run


def substring_dedup(docs: DataFrame, width: int = 20, gram: int = 8, id_col: str = "doc_id", text_col: str = "text", carry: tuple[str, ...] = (), with_text: bool = True) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, and with_text: kept_text (the text itself where nothing goes, else the kept words joined by one space), removed (first and last word of each maximal interval), then the carried columns."""
    text: Column = F.col(text_col)
    order = null_last(F.col(id_col).cast("long"))
    # tells apart rows of one id, and all rows without one
    th = F.when(F.col(id_col).isNull(), F.xxhash64(text)).otherwise(F.hash(text).cast("long"))
    base = docs.select(order.alias("ord"), th.alias("th"), text.alias("text"))
    runs = base.mapInArrow(find_runs(width, gram), "key long, ord long, th long, run long, times long")
    total = F.expr("sum(times) over (partition by key)")
    maybe = runs.repartition("key").withColumn("total", total).where("total > 1").groupBy("ord", "th").agg(F.collect_list("run").alias("runs"))
    hashed = base.mapInArrow(pack, "ord long, th long, text binary").join(maybe, ["ord", "th"]).select("ord", "th", "text", "runs").mapInArrow(hash_runs(width, gram), "key long, ord long, th long, run long, known long, windows array<long>")
    place = F.struct("ord", "th", (F.shiftrightunsigned("run", 6) + F.col("at")).alias("start"))
    each = hashed.repartition("key").select("key", "ord", "th", "run", "known", F.posexplode_outer(F.when(F.size("windows") > 0, F.col("windows"))).alias("at", "window"))
    each = each.where("at is null or shiftright(known, at) & 1 = 0").withColumn("place", place)
    each = each.withColumn("first", F.expr("min(place) over (partition by key, window)"))
    bit = F.when(F.col("at").isNotNull() & (F.col("place") != F.col("first")), F.expr("shiftleft(1L, at)")).otherwise(F.lit(0))
    marks = each.groupBy("key", "ord", "th", "run").agg(F.bit_or(bit.bitwiseOR(F.col("known"))).alias("mask")).where("mask <> 0")
    marks = marks.groupBy("ord", "th").agg(F.collect_list("run").alias("runs"), F.collect_list("mask").alias("masks"))
    whole = docs.select(F.col(id_col).cast("long").alias("_id"), text.alias("text"), order.alias("ord"), th.alias("th"), *(F.col(c).alias(f"_c{i}") for i, c in enumerate(carry)))
    packed = "_id long, text binary, ord long, th long" + "".join(f", _c{i} {dict(docs.dtypes)[c]}" for i, c in enumerate(carry))
    whole = whole.mapInArrow(pack, packed).join(marks, ["ord", "th"], "left").select("_id", "text", "runs", "masks", *(f"_c{i}" for i in range(len(carry))))
    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string"
    if with_text:
        kinds = dict(docs.dtypes)
        schema += ", kept_text string, removed array<struct<first: long, last: long>>" + "".join(f", _c{i} {kinds[c]}" for i, c in enumerate(carry))
    out = whole.mapInArrow(cut(width, with_text), schema)
    return out.withColumnsRenamed({f"_c{i}": c for i, c in enumerate(carry)})
