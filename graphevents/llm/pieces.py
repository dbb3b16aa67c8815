"""SentencePiece encoding and decoding by a Viterbi pass over a trie of words.

The model merges pairs of pieces, so the best segmentation is not the one with the largest sum of scores. It is still found by
one forward pass: a sequence of pieces is the model's segmentation exactly when every two neighbours are, by themselves,
segmented into just those two. So the lattice of a word has at each place the pieces that end there, a step between two pieces
is allowed when the pair is stable, and exactly one path survives; the forward state of a prefix is its last piece.

A marked word is a run of the blank mark and the characters up to the next one; no piece crosses into a mark, so marked words
are segmented on their own. The distinct ones of a batch are sorted, which lays out their trie in depth-first order: the
forward states of a common prefix stay on the stack from one word to the next and are not computed again.

Scale: a narrow map over the rows, in pieces of about 2 MB of text. Each Python worker keeps the words it has met, with their ids as
bytes, in a table of bounded size; what it holds does not change results. The model's file is read by path on every executor
(its path is a parameter; ``PIECE_MODEL`` in the environment of the driver sets the default).
"""

from __future__ import annotations

import functools
import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import document, slices, table, texts_of, with_text

MODEL = os.environ.get("PIECE_MODEL", "/opt/tokenizers/piece_bpe_32k.model")
#: Bytes of words (with their ids) and number of pairs that a worker remembers; bytes of text it takes at a time.
REMEMBERED, PAIRS, PIECE_BYTES = 48 << 20, 250_000, 2 << 20
#: Bytes that an entry of the word table takes besides its characters and ids.
ENTRY = 200
MARK = "▁"
MARKED = re.compile(f"{MARK}+[^{MARK}]*|[^{MARK}]+")


class Pieces:
    """The pieces of a model: ids, byte pieces, and which pairs are stable."""

    def __init__(self, path: str) -> None:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.text = [sp.id_to_piece(i) for i in range(n)]
        normal = [i for i in range(n) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))]
        self.id = {self.text[i]: i for i in normal}
        self.rank = {self.text[i]: -sp.get_score(i) for i in normal}
        self.byte = [sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.of_byte = {i: b for b, i in enumerate(self.byte)}
        self.special = {i for i in range(n) if sp.is_control(i) or sp.is_unknown(i)}
        #: Lengths of the pieces that end in three characters, longest first.
        lengths: dict[str, set[int]] = {}
        for t in self.id:
            if len(t) > 2:
                lengths.setdefault(t[-3:], set()).add(len(t))
        self.lengths = {tail: (*sorted(found, reverse=True), 2) for tail, found in lengths.items()}
        # What each id decodes to alone; bytes above 127 are parts of characters, special pieces decode to nothing.
        self.alone = ["" if i in self.special else chr(self.of_byte[i]) if i in self.of_byte else t.replace(MARK, " ") for i, t in enumerate(self.text)]
        self.parts_of_characters = {i for i, b in self.of_byte.items() if b > 127}
        self.pairs: dict[tuple[str, str], bool] = {}
        self.packed = {t: i.to_bytes(4, "little") for t, i in self.id.items()}
        self.known: dict[str, bytes] = {}
        self.often: set[str] = set()
        self.held = 0
        crossing = [t for t in self.id if re.search(f"[^{MARK}]{MARK}", t)]
        if crossing:
            raise ValueError(f"pieces that cross a blank, such as {crossing[0]!r}: marked words cannot be segmented on their own")

    def merged(self, parts: list[str]) -> list[str]:
        """What the model's merges make of ``parts``: the best-ranked neighbouring pair first, leftmost on ties."""
        parts = list(parts)
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                r = self.rank.get(parts[i] + parts[i + 1])
                if r is not None and (best is None or r < best):
                    best, at = r, i
            if best is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def stable(self, left: str, right: str) -> bool:
        key = (left, right)
        ok = self.pairs.get(key)
        if ok is None:
            if len(self.pairs) > PAIRS:
                self.pairs.clear()
            ok = self.pairs[key] = self.merged([*left, *right]) == ([left, right] if left else [right])
        return ok

    def forward(self, word: str, upto: int, last: list[str | None]) -> None:
        """Extend the forward states ``last`` (last piece of each prefix, from length 0) from ``upto`` to the whole word: at each end
        the longest piece that may follow the state it starts from. No other is possible than the one found; a single
        character is what remains when no longer piece fits."""
        del last[upto + 1 :]
        known, lengths, pairs, other = self.id, self.lengths, self.pairs, (2,)
        for end in range(upto + 1, len(word) + 1):
            found = word[end - 1]
            for n in lengths.get(word[end - 3 : end], other) if end > 2 else other:
                if n > end:
                    continue
                piece = word[end - n : end]
                if piece in known:
                    key = (last[end - n], piece)
                    ok = pairs.get(key)
                    if self.stable(*key) if ok is None else ok:
                        found = piece
                        break
            last.append(found)

    def ids_of(self, word: str, last: list[str | None]) -> bytes:
        """Back from the end over the forward states, as 32-bit ids; characters without a piece become their bytes."""
        out: list[bytes] = []
        at, packed = len(word), self.packed
        while at:
            piece = last[at]
            ids = packed.get(piece)
            out.append(ids if ids is not None else b"".join([self.byte[b].to_bytes(4, "little") for b in piece.encode("utf-8")]))
            at -= len(piece)
        out.reverse()
        return b"".join(out)

    def learn(self, words: set[str]) -> None:
        """Segment all words that are not known, in trie order. A word is given with its marks, or plain where it has one."""
        if self.held > REMEMBERED:  # what was asked for again stays
            self.known = {w: self.known[w] for w in self.often}
            self.often = set()
            self.held = sum(2 * len(w) + len(x) + ENTRY for w, x in self.known.items())
        new = words - self.known.keys()
        if len(self.often) * ENTRY < REMEMBERED // 2:
            self.often |= words - new
        last: list[str | None] = [""]
        before = ""
        for word in sorted(new):
            whole = word if word[0] == MARK else MARK + word
            upto, most = 0, min(len(before), len(whole))
            while upto < most and before[upto] == whole[upto]:
                upto += 1
            self.forward(whole, upto, last)
            ids = self.known[word] = self.ids_of(whole, last)
            self.held += 2 * len(word) + len(ids) + ENTRY
            before = whole

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text: the blank mark in front of a text that is not empty and in place of every space."""
        split = []
        for t in texts:
            if MARK in t or "  " in t or t[:1] == " " or t[-1:] == " ":
                split.append(MARKED.findall(MARK + t.replace(" ", MARK)))
            else:  # every space stands between two words
                split.append(t.split(" ") if t else [])
        self.learn(set().union(*split) if split else set())
        known = self.known
        return [np.frombuffer(b"".join(map(known.__getitem__, words)), "<i4") for words in split]

    def decode(self, ids: list[int]) -> str:
        """The text of ids: byte pieces are put together, marks become spaces, the mark in front goes."""
        if self.parts_of_characters.isdisjoint(ids):
            text = "".join(map(self.alone.__getitem__, ids))
            return text[1:] if text.startswith(" ") else text
        parts, raw = [], bytearray()
        for i in ids:
            if i in self.of_byte:
                raw.append(self.of_byte[i])
                continue
            if raw:
                parts.append(raw.decode("utf-8", "replace"))
                raw.clear()
            parts.append(self.alone[i])
        if raw:
            parts.append(raw.decode("utf-8", "replace"))
        text = "".join(parts)
        return text[1:] if text.startswith(" ") else text


@functools.lru_cache(maxsize=2)
def pieces(path: str = MODEL) -> Pieces:
    return Pieces(path)


def encoded_rows(rows: DataFrame, place: str, path: str) -> DataFrame:
    """``row`` and the text at ``place`` -> row, ids, n_ids, round_trip."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = pieces(path)
        for b in slices(batches, place, PIECE_BYTES):
            texts = texts_of(b, place).to_pylist()
            got = model.encode([t or "" for t in texts])
            back = [None if t is None else model.decode(g.tolist()) == t for t, g in zip(texts, got, strict=True)]
            sizes = np.array([len(g) for g in got], np.int32)
            gone = pa.array([t is None for t in texts], pa.bool_())
            ids = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), pa.array(np.concatenate(got), pa.int32()), mask=gone)
            yield pa.RecordBatch.from_arrays([b.column("row"), ids, pa.array(sizes), pa.array(back, pa.bool_())], ["row", "ids", "n_ids", "round_trip"])

    return rows.mapInArrow(run, f"row {rows.schema['row'].dataType.simpleString()}, ids array<int>, n_ids int, round_trip boolean")


def encoded(docs: DataFrame, path: str = MODEL) -> DataFrame:
    """The columns of ``docs`` with ids (array of int), n_ids and round_trip (decoding gives the text back).

    Null text has null ids and a null round trip; an empty text has none. A text that itself holds the blank mark decodes with a space in
    its place; round_trip is false then. Columns of ``docs`` that are named like the new ones are replaced by them.
    """
    rows, place = with_text(docs, [document(docs.drop("ids", "n_ids", "round_trip"))], whole=True)
    return encoded_rows(rows, place, path).select("row.document.*", "ids", "n_ids", "round_trip")


def decoded(rows: DataFrame, path: str = MODEL) -> DataFrame:
    """The columns of ``rows`` with ``text`` made from ``ids`` (null from null)."""

    @F.pandas_udf("string")
    def back(ids):
        model = pieces(path)
        return ids.map(lambda x: None if x is None else model.decode(list(x)))

    return rows.withColumn("text", back("ids"))


def op4(spark, sf_dir: str) -> DataFrame:
    """One row a document: doc_id, n_ids, ids, round_trip, over every whole text."""
    rows, place = with_text(table(spark, sf_dir, "documents"), [F.col("doc_id").alias("doc_id")], whole=False)
    return encoded_rows(rows, place, MODEL).select("row.doc_id", "n_ids", "ids", "round_trip")
