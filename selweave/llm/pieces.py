"""Exact encoding and decoding with merge-type (BPE) piece models.

Method: Aho-Corasick finds the longest piece at every position; the text is
then covered left to right by backtracking. A piece may follow another only if
re-merging the two texts gives back exactly these two pieces, and positions
from which no cover exists are remembered in a bitfield. The result equals the
usual score-ordered merging without ever building a merge queue over the text.

Pieces never hold the space mark after another character, so a text falls
apart before each run of marks; the encodings of such chunks are memoised in a
bounded table. Models for which that doesn't hold are encoded in one chunk.

Edge cases: a null text is an empty one and has no ids; an empty table gives an
empty result; repeated rows are encoded alike; other columns are dropped.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import plain_documents, slices

MARK = "▁"
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


class PieceModel:
    """Pieces, scores and kinds of a trained model; encodes and decodes with them."""

    def __init__(self, path: str, memo: int = 400_000) -> None:
        import sentencepiece

        self.memo = memo
        file = sentencepiece.SentencePieceProcessor(model_file=path)
        n = file.vocab_size()
        self.pieces = [file.id_to_piece(i) for i in range(n)]
        byte = {i: int(self.pieces[i][3:5], 16) for i in range(n) if file.is_byte(i)}
        special = {i for i in range(n) if file.is_control(i) or file.is_unknown(i) or file.is_unused(i)} | set(byte)
        self.unknown = file.unk_id()
        self.ids = {p: i for i, p in enumerate(self.pieces) if i not in special}
        self.scores = {p: file.get_score(i) for p, i in self.ids.items()}
        self.byte_value = byte
        self.byte_id = {v: i for i, v in byte.items()}
        self.known = {p for p in self.ids if len(p) == 1}
        self.spelled = [""] * n
        for p, i in self.ids.items():
            self.spelled[i] = p.replace(MARK, " ")
        self.spelled[self.unknown] = " ⁇ "
        self.printed = [str(i) for i in range(n)]
        #: Chunks are independent if a mark only ever opens a piece.
        self.splits = not any(MARK in p.lstrip(MARK) for p in self.ids)
        self.newline_splits = self.splits and not any("\n" in p for p in self.ids)
        self.first_byte, self.last_byte = (min(byte), max(byte)) if byte else (n, -1)
        self.fits: dict[tuple[int, int], bool] = {}
        self.shorter: dict[int, int] = {}
        self.table = _Memo(self)
        self.automaton = ahocorasick.Automaton()
        for p, i in self.ids.items():
            self.automaton.add_word(p, (len(p) - 1, i))
        self.automaton.make_automaton()

    def remerge(self, text: str) -> list[int]:
        """Merge a short text from its characters by best score, leftmost first on ties."""
        parts = list(text)
        scores = self.scores
        while len(parts) > 1:
            found, at = None, -1
            for k in range(len(parts) - 1):
                s = scores.get(parts[k] + parts[k + 1])
                if s is not None and (found is None or s > found):
                    found, at = s, k
            if found is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [self.ids[p] for p in parts]

    def compatible(self, left: int, right: int) -> bool:
        """Whether the pieces stay as they are side by side; left -1: whether the piece stands alone."""
        key = (left, right)
        known = self.fits.get(key)
        if known is None:
            if len(self.fits) > 500_000:
                self.fits.clear()
            pieces = self.pieces
            known = self.fits[key] = self.remerge(pieces[right]) == [right] if left < 0 else self.remerge(pieces[left] + pieces[right]) == [left, right]
        return known

    def shorter_piece(self, piece: int) -> int:
        """The longest piece that is a proper prefix, or -1."""
        known = self.shorter.get(piece)
        if known is None:
            text = self.pieces[piece]
            known = self.shorter[piece] = next((self.ids[text[:k]] for k in range(len(text) - 1, 0, -1) if text[:k] in self.ids), -1)
        return known

    def cover(self, text: str) -> list[int]:
        """Backtracking cover of a text whose characters are all pieces."""
        n = len(text)
        longest = [0] * n
        for end, (back, piece) in self.automaton.iter(text):
            longest[end - back] = piece  # ends only grow, so the longest stays
        pieces, fits = self.pieces, self.fits
        out: list[int] = []
        failed = bytearray((n >> 3) + 1)
        at, piece = 0, longest[0]
        while at < n:
            left = out[-1] if out else -1
            while True:
                end = at + len(pieces[piece])
                if not failed[end >> 3] >> (end & 7) & 1:
                    ok = fits.get((left, piece))
                    if ok or (ok is None and self.compatible(left, piece)):
                        out.append(piece)
                        at = end
                        if at < n:
                            piece = longest[at]
                        break
                piece = self.shorter_piece(piece)
                if piece < 0:
                    failed[at >> 3] |= 1 << (at & 7)
                    if not out:
                        raise ValueError("no cover: a character is no piece")
                    back = out.pop()
                    at -= len(pieces[back])
                    piece, left = back, out[-1] if out else -1
                    piece = self.shorter_piece(piece)
                    while piece < 0:
                        failed[at >> 3] |= 1 << (at & 7)
                        back = out.pop()
                        at -= len(pieces[back])
                        left = out[-1] if out else -1
                        piece = self.shorter_piece(back)
        return out

    def encode_chunk(self, text: str) -> list[int]:
        """Cover what is known; spell other characters by bytes."""
        if self.known.issuperset(text):
            return self.cover(text) if text else []
        out: list[int] = []
        run: list[str] = []
        for c in text:
            if c in self.known:
                run.append(c)
                continue
            if run:
                out += self.cover("".join(run))
                run = []
            if self.byte_id:
                out += [self.byte_id[b] for b in c.encode("utf-8", "surrogatepass")]
            else:
                out.append(self.unknown)
        return out + self.cover("".join(run)) if run else out

    def encode(self, text: str) -> np.ndarray:
        """Ids of a whole text, with the leading mark that the library adds."""
        if not text:
            return np.zeros(0, np.uint16)
        table = self.table
        if self.splits and "  " not in text and MARK not in text and text[0] != " ":
            words = (text.replace("\n", " \n") if self.newline_splits else text).split(" ")
            if self.newline_splits and words[0] == "" and text[0] == "\n":
                words[0] = " "
            ids = b"".join(map(table.__getitem__, words))
        else:
            marked = MARK + text.replace(" ", MARK)
            chunks = re.findall(f"{MARK}+[^{MARK}]*", marked) if self.splits else [marked]
            ids = b"".join(np.asarray(self.encode_chunk(c), table.kind).tobytes() for c in chunks)
        return np.frombuffer(ids, table.kind)

    def decode(self, ids: list[int]) -> str:
        """Text of ids, without the leading mark; bytes that form no character give U+FFFD each."""
        spelled, first, last = self.spelled, self.first_byte, self.last_byte
        if not ids:
            return ""
        if min(ids) > last:
            text = "".join(map(spelled.__getitem__, ids))
        else:
            parts: list[str] = []
            run = bytearray()
            for i in ids:
                if first <= i <= last:
                    run.append(self.byte_value[i])
                    continue
                if run:
                    parts.append(_spell(bytes(run)))
                    run.clear()
                parts.append(spelled[i])
            if run:
                parts.append(_spell(bytes(run)))
            text = "".join(parts)
        first_piece = next((i for i in ids if i not in (1, 2)), ids[0])
        return text[1:] if self.pieces[first_piece].startswith(MARK) else text


class _Memo(dict):
    """Word -> packed ids. A key is a word after one space, or a newline and the word after it."""

    def __init__(self, model: PieceModel) -> None:
        self.model = model
        self.kind = np.uint16 if len(model.pieces) <= 1 << 16 else np.uint32

    def __missing__(self, word: str) -> bytes:
        model = self.model
        if word == " ":  # the leading mark of a text that opens with a newline
            ids = model.encode_chunk(MARK)
        elif model.newline_splits and word[:1] == "\n":
            ids = model.encode_chunk(word)
        else:
            ids = model.encode_chunk(MARK + word)
        packed = np.asarray(ids, self.kind).tobytes()
        if len(word) <= 40:
            if len(self) >= model.memo:
                self.clear()
            self[word] = packed
        return packed


def _spell(raw: bytes) -> str:
    try:
        return raw.decode()
    except UnicodeDecodeError:
        out, k = [], 0
        while k < len(raw):
            for size in (1, 2, 3, 4):
                try:
                    out.append(raw[k : k + size].decode())
                    k += size
                    break
                except UnicodeDecodeError:
                    continue
            else:
                out.append("�")
                k += 1
        return "".join(out)


@lru_cache(maxsize=2)
def load(path: str) -> PieceModel:
    """One model a worker process."""
    return PieceModel(path)


def round_trip(docs: DataFrame, model_path: str) -> DataFrame:
    """Per document: number of ids, and digests of the ids and of the decoded text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = load(model_path)
        printed, sha = model.printed, hashlib.sha256
        for batch in slices(batches, "text"):
            counts, ids_sha, text_sha = [], [], []
            for text in batch.column(1).to_pylist():
                ids = model.encode(text or "").tolist()
                counts.append(len(ids))
                ids_sha.append(sha(",".join(map(printed.__getitem__, ids)).encode()).hexdigest())
                text_sha.append(sha(model.decode(ids).encode("utf-8", "surrogatepass")).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(counts, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return plain_documents(docs).mapInArrow(run, SCHEMA)


def encode_documents(docs: DataFrame, model_path: str) -> DataFrame:
    """Per document its ids, for writers of token files."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = load(model_path)
        for batch in slices(batches, "text"):
            ids = [model.encode(t or "").astype(np.int32) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return plain_documents(docs).mapInArrow(run, "doc_id long, ids array<int>")
