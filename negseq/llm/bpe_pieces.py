"""SentencePiece merge-type encoding by backtracking, and decoding.

A vocabulary with scores defines an encoding by merges: the pair whose joined piece has
the highest score, the leftmost first. The same result is found left to right: an
Aho-Corasick automaton gives the pieces that begin at each place, the longest is tried
first, a piece may follow another only if merging the two texts anew yields exactly
these two, and a bit for each place remembers that no valid rest begins there.

White space becomes a mark, and no piece holds the mark after another character, so
text falls into independent segments at each mark; a character that no piece holds
also ends a segment and is written as its bytes. Runs of two or more marks have equal
scores, where the compatibility of neighbours does not decide; such segments are
merged directly.

The first try of the search is the automaton's longest matches from left to right; only
where two of them do not fit does it go back. A worker remembers the ids of segments it
has seen and which pieces may follow which, both of bounded size, and takes texts in
slices of bounded bytes. The decoded text of a segment is made from its ids once; where
it is the segment itself, as in all sound text, the memory need not hold it.

Defined results: null and empty text encode to the end id alone and decode to the empty
text; very long texts are a stream of segments; repeated rows each get their ids; extra
columns are not read.
"""

from __future__ import annotations

import hashlib
import heapq
import sys
import types
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import words as W

MARK = "▁"
#: Segments of each of two generations that a worker remembers, of at most LONGEST characters (about 200 bytes each with its ids), and pairs of pieces (about 90 bytes each).
MEMO, LONGEST, PAIRS = 150_000, 40, 200_000
#: Bytes of text handled at once.
SLICE = 1 << 20
#: Up to this length a text is merged by scanning its pairs; beyond it by a queue.
SCANNED = 64
NEVER = float("-inf")


class Vocabulary:
    """Pieces of a merge-type model with byte fallback."""

    def __init__(self, pieces: list[tuple[str, float, str]], end: int, add_prefix: bool):
        self.pieces, self.end, self.add_prefix = pieces, end, add_prefix
        self.id = {p: i for i, (p, _, kind) in enumerate(pieces) if kind == "normal"}
        self.score = {p: s for p, s, kind in pieces if kind == "normal"}
        self.byte = {int(p[3:5], 16): i for i, (p, _, kind) in enumerate(pieces) if kind == "byte"}
        self.chars = {c for p in self.id for c in p}
        if any(MARK in p.lstrip(MARK) for p in self.id):
            raise ValueError("a piece holds the white-space mark after another character")

    def ids_of(self, piece: str) -> list[int]:
        """One id, or those of the bytes of a character that is no piece by itself."""
        i = self.id.get(piece)
        return [i] if i is not None else [self.byte[b] for b in piece.encode()]

    @classmethod
    def read(cls, path: str) -> Vocabulary:
        from sentencepiece import sentencepiece_model_pb2 as pb

        model = pb.ModelProto()
        with open(path, "rb") as f:
            model.ParseFromString(f.read())
        spec = model.normalizer_spec
        if model.trainer_spec.model_type != 2 or spec.precompiled_charsmap or spec.remove_extra_whitespaces:
            raise ValueError("only merge-type models without normalisation are supported")
        kinds = {1: "normal", 4: "normal", 6: "byte"}
        pieces = [(p.piece, p.score, kinds.get(p.type, "special")) for p in model.pieces]
        return cls(pieces, model.trainer_spec.eos_id, spec.add_dummy_prefix)


class Encoder:
    def __init__(self, vocabulary: Vocabulary):
        import ahocorasick

        self.v = vocabulary
        self.names = [p for p, *_ in vocabulary.pieces]
        self.automaton = ahocorasick.Automaton()
        for p, i in vocabulary.id.items():
            self.automaton.add_word(p, i)
        self.automaton.make_automaton()
        self.size = [len(p) for p in self.names]
        #: The longest piece that begins a piece and is not all of it, or -1.
        self.shorter = [next((i for k in range(len(p) - 1, 0, -1) if (i := vocabulary.id.get(p[:k])) is not None), -1) for p in self.names]
        self.sure: dict[int, bool] = {}
        self.memo: dict[str, str] = {}
        self.older: dict[str, str] = {}
        self.plain = True

    def merged(self, text: str) -> list[str]:
        """Direct merging: the pair of highest score first, of equal ones the leftmost."""
        if len(text) > SCANNED:
            return self.merged_by_queue(text)
        parts, score = list(text), self.v.score
        pairs = [score.get(a + b, NEVER) for a, b in zip(parts, parts[1:], strict=False)]
        while pairs and (best := max(pairs)) > NEVER:
            i = pairs.index(best)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del pairs[i]
            if i:
                pairs[i - 1] = score.get(parts[i - 1] + parts[i], NEVER)
            if i < len(pairs):
                pairs[i] = score.get(parts[i] + parts[i + 1], NEVER)
        return parts

    def merged_by_queue(self, text: str) -> list[str]:
        """The same with a queue of pairs by score and place."""
        parts: list[str | None] = list(text)
        left, right = list(range(-1, len(parts) - 1)), list(range(1, len(parts) + 1))
        queue: list[tuple[float, int, str, int]] = []

        def offer(i: int) -> None:
            j = right[i] if i >= 0 else len(parts)
            if i >= 0 and j < len(parts) and (s := self.v.score.get(parts[i] + parts[j])) is not None:
                heapq.heappush(queue, (-s, i, parts[i] + parts[j], j))

        for i in range(len(parts) - 1):
            offer(i)
        while queue:
            _, i, piece, j = heapq.heappop(queue)
            if parts[i] is None or parts[j] is None or right[i] != j or parts[i] + parts[j] != piece:
                continue
            parts[i], parts[j] = piece, None
            right[i] = right[j]
            if right[i] < len(parts):
                left[right[i]] = i
            offer(left[i])
            offer(i)
        return [p for p in parts if p is not None]

    def follows(self, a: int, b: int) -> bool:
        """Whether merging both texts anew gives these two pieces; a is -1 at the beginning."""
        pair = (a + 1) * len(self.names) + b
        found = self.sure.get(pair)
        if found is None:
            if len(self.sure) >= PAIRS:
                self.sure.clear()
            left, right = self.names[a] if a >= 0 else "", self.names[b]
            found = self.sure[pair] = self.merged(left + right) == ([left, right] if left else [right])
        return found

    def longest(self, text: str, at: int) -> int:
        """The longest piece that begins at this place."""
        last, piece = next(self.automaton.iter_long(text, at), (-1, -1))
        return piece if last + 1 - self.size[piece] == at else -1

    def backtracked(self, text: str) -> list[int]:
        n, size, shorter, sure, width = len(text), self.size, self.shorter, self.sure, len(self.names)
        good = (1 << (n + 1)) - 1
        out: list[int] = []
        at, before = 0, -1
        piece = self.longest(text, 0)
        while True:
            while piece >= 0:
                stop = at + size[piece]
                if good >> stop & 1:
                    fits = sure.get((before + 1) * width + piece)
                    if self.follows(before, piece) if fits is None else fits:
                        break
                piece = shorter[piece]
            if piece >= 0:
                out.append(piece)
                if stop == n:
                    return out
                at, before = stop, piece
                piece = self.longest(text, at)
            elif out:
                good &= ~(1 << at)
                piece = out.pop()
                at -= size[piece]
                before = out[-1] if out else -1
                piece = shorter[piece]
            else:
                return self.merged_ids(text)

    def merged_ids(self, text: str) -> list[int]:
        return [i for p in self.merged(text) for i in self.v.ids_of(p)]

    def segment(self, text: str) -> list[int]:
        """Ids of a segment: marks, then other characters."""
        v = self.v
        if v.chars.issuperset(text) and not text.startswith(MARK * 2):
            return self.backtracked(text)
        out, run = [], ""
        for c in [*text, None]:
            if c is not None and c in v.chars:
                run += c
                continue
            if run:
                out += self.merged_ids(run) if run.startswith(MARK * 2) else self.backtracked(run)
                run = ""
            if c is not None:
                out += [v.byte[b] for b in c.encode("utf-8", "surrogatepass")]
        return out

    def surface(self, ids: list[int]) -> str:
        """Text of ids without the treatment of the first mark."""
        out, pending = [], bytearray()
        for i in ids:
            piece, _, kind = self.v.pieces[i]
            if kind == "byte":
                pending.append(int(piece[3:5], 16))
                continue
            if pending:
                out.append(pending.decode("utf-8", "replace"))
                pending = bytearray()
            if kind == "normal":
                out.append(piece.replace(MARK, " "))
        if pending:
            out.append(pending.decode("utf-8", "replace"))
        return "".join(out)

    def decode(self, ids: list[int]) -> str:
        text = self.surface(ids)
        first = next((self.v.pieces[i] for i in ids if self.v.pieces[i][2] != "special"), None)
        return text[1:] if self.v.add_prefix and first and first[2] == "normal" and first[0].startswith(MARK) else text

    def segments(self, text: str) -> list[str]:
        """Independent segments. A line break is in no piece, so it begins one."""
        if not text:
            return []
        parts = text.replace(MARK, " ").replace("\n", " \n").split(" ")
        if "\n" not in self.v.chars and "" not in parts and (self.v.add_prefix or len(parts) == 1) and parts[0][0] != "\n":
            return [p if p[0] == "\n" else MARK + p for p in parts]
        out, marks = [], 0
        for k, p in enumerate(parts):
            if p.startswith("\n"):
                if k == 0:
                    pass
                if marks:
                    out.append(MARK * marks)
                    marks = 0
                out.append(p)
                continue
            if k or self.v.add_prefix:
                marks += 1
            if p:
                out.append(MARK * marks + p)
                marks = 0
        if marks:
            out.append(MARK * marks)
        return out

    def written(self, segment: str) -> str:
        """The ids of a segment as text. A segment that begins with one mark is remembered without it, one that begins with a line break as it is."""
        one = segment[0] == MARK and segment[1:2] != MARK
        key = segment[1:] if one else segment
        kept = 0 < len(key) <= LONGEST and (one or segment[0] in "\n" + MARK)
        found = (self.memo.get(key) or self.older.get(key)) if kept else None
        if found is None:
            ids = self.segment(segment)
            found = " ".join(map(str, ids))
            if "".join([self.names[i] for i in ids]) != segment and self.surface(ids) != segment.replace(MARK, " "):
                self.plain = kept = False
        if kept:
            if len(self.memo) >= MEMO:
                # what is in use comes back from the older generation
                self.older, self.memo = self.memo, {}
            self.memo[key] = found
        return found

    def listed(self, text: str) -> tuple[str, str]:
        """The ids of a text, without the end, as text; the decoded text."""
        if not text:
            return "", ""
        v = self.v
        self.plain = True
        parts = text.replace(MARK, " ").replace("\n", " \n").split(" ")
        if v.add_prefix and "\n" not in v.chars and parts[0][:1] != "\n" and "" not in parts:
            found = [self.memo.get(p) or self.written(p if p[0] == "\n" else MARK + p) for p in parts]
            whole = text.replace(MARK, " ")
        else:
            segments = self.segments(text)
            found = [self.written(s) for s in segments]
            whole = "".join(segments).replace(MARK, " ")
            whole = whole[1:] if v.add_prefix and segments[0][0] == MARK else whole
        ids = " ".join(found)
        # each segment has been decoded from its ids; only where one is not itself again all are
        return ids, whole if self.plain else self.decode([int(i) for i in ids.split(" ")])

    def encode(self, text: str, end: bool = True) -> list[int]:
        ids = [i for s in self.segments(text or "") for i in self.segment(s)]
        return [*ids, self.v.end] if end else ids


def worker_state() -> dict:
    """A dict that lives as long as the worker process."""
    return sys.modules.setdefault("_negseq_worker", types.ModuleType("_negseq_worker")).__dict__


def digests(vocabulary, with_ids: bool = False):
    """vocabulary: a broadcast Vocabulary."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # a worker keeps its encoder, and what it remembers, from one task to the next
        kept = worker_state()
        if kept.get("vocabulary") is not vocabulary.value:
            kept["vocabulary"], kept["encoder"] = vocabulary.value, Encoder(vocabulary.value)
        encoder = kept["encoder"]
        end = str(encoder.v.end)
        for part in W.pieces(batches, "text", SLICE):
            n, ids, decoded, flat = [], [], [], []
            for text in part.column(1):
                listed, whole = encoder.listed(text.as_py() or "")
                listed = f"{listed} {end}" if listed else end
                n.append(listed.count(" ") + 1)
                ids.append(hashlib.sha256(listed.encode()).hexdigest())
                decoded.append(hashlib.sha256(whole.encode("utf-8", "surrogatepass")).hexdigest())
                if with_ids:
                    flat.append(np.fromstring(listed, np.int32, sep=" "))
            out = [part.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(decoded, pa.string())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if with_ids:
                out.append(W.lists(pa.array(np.concatenate(flat)), np.array(n)))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(out, names)

    return run


def encode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 and, with_ids, ids. The model is read on the driver; its pieces (about 1 MB) are broadcast."""
    shared = docs.sparkSession.sparkContext.broadcast(Vocabulary.read(model_path))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(digests(shared, with_ids), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>" if with_ids else ""))
