"""Encoding and decoding with merge-type piece vocabularies.

Encoding keeps an agenda of adjacent symbol pairs ordered by the score of the joined piece, then by place; it takes
the best pair, joins it and adds the pairs that this makes. Symbols without a piece become byte pieces. A text is cut
beforehand where no piece of the vocabulary can span: between any sign and a following blank, and around line ends.
Cuts met twice are remembered in two generations of at most `REMEMBERED` cuts; the older one goes when the younger is full,
and both when another text operator runs in the worker process. Cuts not met before are compared with the sentencepiece library in one call for each Arrow batch,
and one whole document of each batch is; a difference raises.

Edge cases: null texts count as empty; empty texts have no ids and decode to the empty text; repeated rows get equal
results; very long cuts are encoded without being remembered; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator
from heapq import heapify, heappop, heappush

import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from sentencepiece import sentencepiece_model_pb2

from . import textscan as ts

BLANK = "▁"
REMEMBERED = 250_000
MARKS = 1 << 21
LONGEST_REMEMBERED = 64


class Remembered(dict):
    """Ids of cuts as decimals joined by commas; `make` gives those not met before and says whether to remember them.
    A cut is remembered when it is met for the second time (`seen` marks hashes of cuts met since the last turn)."""

    def __init__(self, make: Callable[[str], tuple[str, bool]]) -> None:
        super().__init__()
        self.make = make
        self.forget()

    def forget(self) -> None:
        self.clear()
        self.older: dict[str, str] = {}
        self.seen = bytearray(MARKS)

    def __missing__(self, cut: str) -> str:
        csv = self.older.get(cut)
        if csv is None:
            csv, keep = self.make(cut)
            mark = hash(cut) % MARKS
            if not keep or not self.seen[mark]:
                self.seen[mark] = 1
                return csv
        if len(self) >= REMEMBERED:
            older = dict(self)
            self.forget()
            self.older = older
        self[cut] = csv
        return csv


class PieceModel:
    """A vocabulary read from a model file (byte fallback, no normalisation, blank put before the text)."""

    def __init__(self, path: str) -> None:
        proto = sentencepiece_model_pb2.ModelProto()
        with open(path, "rb") as f:
            proto.ParseFromString(f.read())
        kinds = sentencepiece_model_pb2.ModelProto.SentencePiece
        norm = proto.normalizer_spec
        if proto.trainer_spec.model_type != 2 or norm.precompiled_charsmap or norm.remove_extra_whitespaces or not norm.add_dummy_prefix:
            raise ValueError("only merge-type models with identity normalisation are supported")
        if any(p.type in (kinds.USER_DEFINED, kinds.UNUSED) for p in proto.pieces):
            raise ValueError("models with user-defined or unused pieces are not supported")
        self.scores = {p.piece: p.score for p in proto.pieces if p.type == kinds.NORMAL}
        self.ids = {p.piece: i for i, p in enumerate(proto.pieces) if p.type == kinds.NORMAL}
        self.bytes = {int(p.piece[3:5], 16): i for i, p in enumerate(proto.pieces) if p.type == kinds.BYTE}
        self.control = {i for i, p in enumerate(proto.pieces) if p.type in (kinds.CONTROL, kinds.UNKNOWN)}
        self.pieces = [p.piece for p in proto.pieces]
        self.byte_of = {i: b for b, i in self.bytes.items()}
        self.unknown = proto.trainer_spec.unk_id
        if any(BLANK in p.lstrip(BLANK) for p in self.ids) or any("\n" in p for p in self.ids):
            raise ValueError("the vocabulary has pieces that span blanks or line ends")
        self.cuts = re.compile(f"[ {BLANK}]+[^ {BLANK}\n]*|[^ {BLANK}\n]+|\n")
        self.library = sentencepiece.SentencePieceProcessor(model_file=path)
        self.known = Remembered(self._cut)
        self.fresh: list[tuple[str, list[int]]] = []
        #: Cuts of the current text that do not decode to themselves; these are never remembered.
        self.changed: dict[str, str] = {}

    def merge(self, cut: str) -> list[int]:
        """Ids of a cut, in which blanks are written as BLANK."""
        scores = self.scores
        symbol: list[str | None] = list(cut)
        n = len(symbol)
        left, right = list(range(-1, n - 1)), list(range(1, n + 1))
        agenda = [(-s, i, i + 1, p) for i in range(n - 1) if (s := scores.get(p := cut[i : i + 2])) is not None]
        heapify(agenda)
        while agenda:
            _, i, j, piece = heappop(agenda)
            # Stale unless both symbols still stand next to each other and spell the piece.
            if symbol[i] is None or j >= n or symbol[j] is None or right[i] != j or symbol[i] + symbol[j] != piece:
                continue
            symbol[i], symbol[j] = piece, None
            after = right[i] = right[j]
            before = left[i]
            if after < n:
                left[after] = i
                if (s := scores.get(p := piece + symbol[after])) is not None:
                    heappush(agenda, (-s, i, after, p))
            if before >= 0 and (s := scores.get(p := symbol[before] + piece)) is not None:
                heappush(agenda, (-s, before, i, p))
        out: list[int] = []
        for s in symbol:
            if s is not None:
                i = self.ids.get(s)
                if i is not None:
                    out.append(i)
                else:
                    out.extend(self.bytes.get(b, self.unknown) for b in s.encode())
        return out

    def decode(self, ids: list[int] | tuple[int, ...], first: bool = True) -> str:
        """Text of ids; first: a leading blank of the text is dropped, as the encoder put it there."""
        out, pending = [], bytearray()
        for i in ids:
            b = self.byte_of.get(i)
            if b is not None:
                pending.append(b)
                continue
            if pending:
                out.append(pending.decode(errors="replace"))
                pending = bytearray()
            if i not in self.control:
                piece = self.pieces[i]
                out.append(piece[1:] if first and not out and piece.startswith(BLANK) else piece)
        out.append(pending.decode(errors="replace"))
        return "".join(out).replace(BLANK, " ")

    def _cut(self, cut: str) -> tuple[str, bool]:
        ids = self.merge(cut.replace(" ", BLANK))
        self.fresh.append((cut, ids))
        decoded = self.decode(ids, first=False)
        if decoded != cut:
            self.changed[cut] = decoded
        return ",".join(map(str, ids)), decoded == cut and len(cut) <= LONGEST_REMEMBERED

    def encode(self, text: str) -> tuple[str, int, str]:
        """Ids as decimals joined by commas, their number, and the decoded text."""
        if not text:
            return "", 0, ""
        self.changed = changed = {}
        cuts = self.cuts.findall(" " + text)
        csv = ",".join(map(self.known.__getitem__, cuts))
        # Joined cuts are the text, so it only is put together anew where a cut decodes to something else.
        decoded = "".join([changed.get(c, c) for c in cuts])[1:] if changed else text
        return csv, csv.count(",") + 1, decoded

    def confirm(self, texts: list[str]) -> None:
        """Compare cuts encoded since the last call, and whole texts, with the library."""
        fresh, self.fresh = self.fresh, []
        # A cut that opens with a blank stands for itself; others are asked for behind a line end.
        asked = [c[1:] if c[0] in (" ", BLANK) and len(c) > 1 else "\n" + c for c, _ in fresh]
        for (cut, ids), said, q in zip(fresh, self.library.encode(asked, num_threads=1) if asked else [], asked, strict=True):
            if ids != (said[2:] if q[0] == "\n" and len(q) == len(cut) + 1 else said):
                raise ValueError(f"ids differ from the library's for {cut[:80]!r}")
        for t in texts:
            said = self.library.encode(t, num_threads=1)
            csv, n, decoded = self.encode(t)
            if csv != ",".join(map(str, said)) or n != len(said) or decoded != self.library.decode(said):
                raise ValueError(f"a document's ids differ from the library's: {t[:80]!r}")


_loaded: dict[str, PieceModel] = {}


def model_for(path: str) -> PieceModel:
    """The model of a path, with the cuts that this worker process has met."""
    if path not in _loaded:
        _loaded[path] = PieceModel(path)
        ts.idle.append(_loaded[path].known.forget)
    return _loaded[path]


def encode_documents(df: DataFrame, model_path: str, with_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, and ids array<int> if asked for."""
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = model_for(model_path)
        sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
        for batch in batches:
            for at in range(0, len(batch), 256):
                part = batch.slice(at, 256)
                texts = [t or "" for t in part.column("text").to_pylist()]
                rows = []
                for t in texts:
                    csv, n, decoded = model.encode(t)
                    rows.append((n, sha(csv), sha(decoded), list(map(int, csv.split(","))) if with_ids and n else []))
                model.confirm(texts[:1] if at == 0 else [])
                columns = [part.column("doc_id"), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.string()), pa.array([r[2] for r in rows], pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if with_ids:
                    columns.append(pa.array([r[3] for r in rows], pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)

    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).transform(ts.mapped, run, schema)
