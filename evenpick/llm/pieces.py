"""SentencePiece (merge type) encoding by a table of each prefix's unique last token, and decoding.

A merge-type tokenizer leaves, for every prefix of a chunk, one possible last token: the longest vocabulary match that ends there and
whose boundary with the last token before it survives all merges. An automaton lists the matches, a pair test that undoes merges in
falling order decides boundaries, and the ids are read off backwards. Chunks end where no vocabulary piece can cross.

Defined results: null and empty texts have no ids and decode to the empty text; very long texts and texts without spaces are linear in
length; repeated rows repeat; an empty table gives no rows; other columns are ignored (``encode_documents`` carries them along).
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from evenpick.llm.textbits import MEMORIES, bounded_slices
from evenpick.plans.durable import ship_package

SPACE_MARK = "▁"
#: Chunks that a worker remembers in each of two generations (about 220 bytes each).
CACHED_CHUNKS = 180_000
#: Pair tests that a worker keeps when it forgets its chunks.
TESTED_PAIRS = 300_000
_NEVER = 1 << 60


class PieceTable:
    """What the pair test needs of a vocabulary; built once on the driver and shipped to the workers."""

    def __init__(self, model: bytes):
        from sentencepiece import sentencepiece_model_pb2 as pb

        proto = pb.ModelProto()
        proto.ParseFromString(model)
        norm, train = proto.normalizer_spec, proto.trainer_spec
        plain = norm.name == "identity" and norm.add_dummy_prefix and not norm.remove_extra_whitespaces and norm.escape_whitespaces
        if train.model_type != 2 or not plain or train.treat_whitespace_as_suffix or any(p.type == 4 for p in proto.pieces):
            raise ValueError("only merge-type models with identity normalisation, a leading space mark and no user symbols are supported")
        self.model, self.unknown = model, next(i for i, p in enumerate(proto.pieces) if p.type == 2)
        self.byte_ids = {int(p.piece[3:5], 16): i for i, p in enumerate(proto.pieces) if p.type == 6}
        kept = [(i, p.piece.replace(SPACE_MARK, " "), p.score) for i, p in enumerate(proto.pieces) if p.type in (1, 5)]
        by_score = {s: r for r, s in enumerate(sorted({s for *_, s in kept}, reverse=True))}
        self.rank = {piece: by_score[s] for _, piece, s in kept}
        self.ids = {piece: i for i, piece, _ in kept}
        letters = {c for piece in self.rank for c in piece}
        if any(" " in piece.lstrip(" ") for piece in self.rank):
            raise ValueError("a piece crosses a space")
        self.hard = "\n" not in letters
        self.split: dict[str, tuple[str, str] | None] = {c: None for c in letters}
        self.ordered: dict[str, bool] = dict.fromkeys(letters, True)
        for piece in sorted(self.rank, key=len):
            if len(piece) > 1:
                parts, last = self.merge(piece)
                if len(parts) == 1:
                    a, b = self.split[piece] = last
                    low = max((self.rank[x] for x in last if len(x) > 1), default=-1)
                    self.ordered[piece] = self.rank[piece] > low and self.ordered.get(a, False) and self.ordered.get(b, False)

    def merge(self, text: str) -> tuple[list[str], tuple[str, str] | None]:
        """Merges applied one by one, best rank first and leftmost first; the parts left, and the last pair merged."""
        parts, last = list(text), None
        while True:
            best, at = _NEVER, -1
            for i in range(len(parts) - 1):
                r = self.rank.get(parts[i] + parts[i + 1], _NEVER)
                if r < best:
                    best, at = r, i
            if at < 0:
                return parts, last
            last = (parts[at], parts[at + 1])
            parts[at : at + 2] = [parts[at] + parts[at + 1]]

    def survives(self, a: str, b: str) -> bool:
        """Whether the boundary between tokens ``a`` and ``b`` outlasts all merges of their joint text."""
        if not (self.ordered.get(a, False) and self.ordered.get(b, False)):
            return self.merge(a + b)[0] == [a, b]
        rank, split, limit = self.rank, self.split, _NEVER
        while True:
            if rank.get(a + b, _NEVER) < limit:
                return False
            sa, sb = split[a], split[b]
            if sa is None and sb is None:
                return True
            if sb is None or (sa is not None and rank[a] > rank[b]):
                limit, a = rank[a], sa[1]
            else:
                limit, b = rank[b] + 1, sb[0]


class PieceCodec:
    """Encoder and decoder of one worker: automaton, remembered pair tests, remembered chunks."""

    def __init__(self, table: PieceTable):
        import ahocorasick
        from sentencepiece import SentencePieceProcessor

        self.table, self.key = table, hashlib.sha256(table.model).hexdigest()
        self.processor = SentencePieceProcessor(model_proto=table.model)
        self.automaton = ahocorasick.Automaton()
        #: With each token: its length, the tokens that may stand before it, and those that may not, as far as tested.
        self.tested = 0
        for piece in table.split:
            self.automaton.add_word(piece, (piece, len(piece), {""}, set()))
        self.automaton.make_automaton()
        self.young: dict[str, tuple[int, ...]] = {}
        self.old: dict[str, tuple[int, ...]] = {}
        self.decimal = [str(i) for i in range(self.processor.get_piece_size())]
        self.chunks = re.compile(r" +[^ \n]*|[^ \n]+|\n" if table.hard else r" +[^ ]*|[^ ]+").findall

    def _ids(self, token: str) -> list[int]:
        if token in self.table.ids:
            return [self.table.ids[token]]
        data = token.encode("utf-8", "surrogatepass")
        return [self.table.byte_ids[b] for b in data] if self.table.byte_ids else [self.table.unknown]

    def _may_follow(self, before: str, token: str, good: set[str], bad: set[str]) -> bool:
        """The pair test, remembered with the token; a character outside the vocabulary never merges."""
        ok = before not in self.table.split or self.table.survives(before, token)
        (good if ok else bad).add(before)
        self.tested += 1
        return ok

    def last_tokens(self, chunk: str) -> list[str]:
        """For each prefix, the last token of its encoding (a character outside the vocabulary stands for itself)."""
        last: list[str | None] = [None] * (len(chunk) + 1)
        last[0] = ""
        for end, (token, size, good, bad) in self.automaton.iter(chunk):
            end += 1
            if last[end] is not None:
                continue
            before = last[end - size]
            if before in good:
                last[end] = token
            elif before in bad:
                continue
            elif before is None:  # characters outside the vocabulary stand right before
                at = end - size
                while last[at] is None:
                    at -= 1
                last[at + 1 : end - size + 1] = chunk[at : end - size]
                if self._may_follow(last[end - size], token, good, bad):
                    last[end] = token
            elif self._may_follow(before, token, good, bad):
                last[end] = token
        if None in last:
            last = [chunk[i - 1] if t is None else t for i, t in enumerate(last)]
        return last

    def encode_chunk(self, chunk: str) -> tuple[int, ...]:
        last, at, ids, tokens = self.last_tokens(chunk), len(chunk), self.table.ids, []
        while at:
            token = last[at]
            tokens.append(token)
            at -= len(token)
        tokens.reverse()
        try:
            return tuple([ids[t] for t in tokens])
        except KeyError:
            return tuple([i for t in tokens for i in self._ids(t)])

    def encode(self, text: str | None) -> list[int]:
        """Ids of a whole text."""
        if not text:
            return []
        ids: list[int] = []
        young, old = self.young, self.old
        for chunk in self.chunks(" " + text.replace(SPACE_MARK, " ")):
            got = young.get(chunk)
            if got is None:
                got = old.get(chunk) or self.encode_chunk(chunk)
                if len(chunk) <= 64:
                    if len(young) >= CACHED_CHUNKS:
                        self.old, self.young = old, young = young, {}
                    young[chunk] = got
            ids += got
        return ids

    def digest(self, ids: list[int]) -> str:
        """SHA-256 of the decimal ids joined by commas."""
        decimal = self.decimal
        return hashlib.sha256(",".join([decimal[i] for i in ids]).encode()).hexdigest()

    def forget(self) -> None:
        self.young, self.old = {}, {}
        if self.tested > TESTED_PAIRS:
            for _, _, good, bad in self.automaton.values():
                good.clear(), bad.clear()
                good.add("")
            self.tested = 0

    def decode(self, ids: list[int]) -> str:
        return self.processor.decode(ids) if ids else ""


_CODECS: dict[str, PieceCodec] = {}
_TABLES: dict[str, PieceTable] = {}


def _codec(table: PieceTable) -> PieceCodec:
    key = hashlib.sha256(table.model).hexdigest()
    if key not in _CODECS:
        _CODECS[key] = PieceCodec(table)
    MEMORIES[key] = _CODECS[key].forget
    return _CODECS[key]


def piece_table(model_path: str) -> PieceTable:
    """Read a model on the driver; the executors need no file."""
    with open(model_path, "rb") as f:
        model = f.read()
    key = hashlib.sha256(model).hexdigest()
    if key not in _TABLES:
        _TABLES[key] = PieceTable(model)
    return _TABLES[key]


def _shared(docs: DataFrame, model_path: str):
    ship_package(docs.sparkSession)
    return docs.sparkSession.sparkContext.broadcast(piece_table(model_path))


def encode_documents(docs: DataFrame, model_path: str, text: str = "text", into: str = "ids") -> DataFrame:
    """``docs`` with one more column ``into``: the token ids of ``text`` (a column of that name is replaced)."""
    shared = _shared(docs, model_path)
    kept = docs.drop(into)
    at = kept.columns.index(text)

    def run(batches):
        codec = _codec(shared.value)
        for b in bounded_slices(batches, text, owner=codec.key):
            ids = [codec.encode(t) for t in b.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(ids, pa.list_(pa.int32()))], names=[*b.schema.names, into])

    return kept.mapInArrow(run, T.StructType([*kept.schema.fields, T.StructField(into, T.ArrayType(T.IntegerType()))]))


def decode_ids(encoded: DataFrame, model_path: str, ids: str = "ids", into: str = "decoded") -> DataFrame:
    """``encoded`` with one more column ``into``: the text of the ids, as the library decodes them."""
    shared = _shared(encoded, model_path)
    kept = encoded.drop(into)
    at = kept.columns.index(ids)

    def run(batches):
        codec = _codec(shared.value)
        for batch in batches:
            for i in range(0, batch.num_rows, 500):
                b = batch.slice(i, 500)
                texts = [codec.decode(x or []) for x in b.column(at).to_pylist()]
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(texts, pa.string())], names=[*b.schema.names, into])

    return kept.mapInArrow(run, T.StructType([*kept.schema.fields, T.StructField(into, T.StringType())]))


def piece_digest(docs: DataFrame, model_path: str) -> DataFrame:
    """Per document: number of ids, digest of the ids, digest of the text decoded from them. Ids stay in the worker."""
    shared = _shared(docs, model_path)

    def run(batches):
        codec = _codec(shared.value)
        for b in bounded_slices(batches, owner=codec.key):
            n, a, d = [], [], []
            for t in b.column(1).to_pylist():
                ids = codec.encode(t)
                n.append(len(ids))
                a.append(codec.digest(ids))
                d.append(hashlib.sha256(codec.decode(ids).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(a), pa.array(d)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
