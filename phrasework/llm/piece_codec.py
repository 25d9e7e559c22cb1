"""SentencePiece encoding and decoding over a trie of distinct marked words.

Spaces become marks and a text falls into marked words, which no piece crosses. The distinct
words of a batch are sorted, which lists the paths of their trie depth-first: a word keeps the
forward state of the prefix it shares with the word before it and goes on from there.

The state of a prefix is the last piece of its best encoding. For unigram models that is the
Viterbi step, the largest sum of scores. Merge (BPE) models have no such sum; there the last
piece is the one that stays apart from the best encoding of what precedes it, which pairs of
pieces decide, so that ids equal those of the merge order (see :meth:`Merges.apart`).
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phrasework.llm.textbytes import slices

MARK = "▁"
#: Distinct words in each of the two generations that a worker remembers, and pairs of pieces.
REMEMBERED, PAIRS = 300_000, 1_000_000
#: Bytes of text whose words share a trie.
TOGETHER = 6 << 20
#: Characters of neighbouring words that are compared for their shared prefix.
SHARED = 24
#: Added to the lowest score for a character outside the vocabulary.
UNKNOWN_PENALTY = 10.0


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def _fields(raw: bytes, at: int, end: int) -> Iterator[tuple[int, int, int]]:
    """Fields of a serialised message: (number, value, next) of a number, (number, start, end) of bytes."""

    def number(at: int) -> tuple[int, int]:
        value = shift = 0
        while True:
            value |= (raw[at] & 127) << shift
            shift += 7
            at += 1
            if raw[at - 1] < 128:
                return value, at

    while at < end:
        tag, at = number(at)
        if tag & 7 == 0:
            value, at = number(at)
            yield tag >> 3, value, at
        elif tag & 7 == 2:
            size, at = number(at)
            yield tag >> 3, at, at + size
            at += size
        else:
            at += 4 if tag & 7 == 5 else 8
            yield tag >> 3, at, at


def _settings(raw: bytes, part: int) -> dict[int, tuple[int, int]]:
    """The fields of one part of a serialised model by number, last ones winning."""
    found: dict[int, tuple[int, int]] = {}
    for field, start, end in _fields(raw, 0, len(raw)):
        if field == part:
            found |= {inner: (value, after) for inner, value, after in _fields(raw, start, end)}
    return found


def is_merge_model(raw: bytes) -> bool:
    """Whether a serialised model says that it was made by merging (field 3 of its trainer part)."""
    return _settings(raw, 2).get(3, (1, 0))[0] == 2


def check_normaliser(raw: bytes) -> None:
    """Refuse a model whose texts are changed before they are cut in a way that is not done here.

    Handled is what leaves a text as it is but for a mark in front and marks for spaces: no character map,
    the front mark, spaces kept and escaped, marks ahead of words (fields of the normaliser and trainer parts).
    """
    settings, trainer = _settings(raw, 3), _settings(raw, 2)
    start, end = settings.get(2, (0, 0))
    wrong = []
    if end > start:
        wrong.append("a character map")
    for field, name, handled, default in ((3, "add_dummy_prefix", 1, 1), (4, "remove_extra_whitespaces", 0, 1), (5, "escape_whitespaces", 1, 1)):
        if settings.get(field, (default, 0))[0] != handled:
            wrong.append(f"{name}={bool(1 - handled)}")
    if trainer.get(24, (0, 0))[0]:
        wrong.append("treat_whitespace_as_suffix=True")
    if wrong:
        raise ValueError(f"the model's normaliser is not handled: {', '.join(wrong)}")


class Merges:
    """Which pieces a merge model makes, and which stay apart side by side."""

    def __init__(self, scores: dict[str, float]):
        self.scores = scores
        self.history: dict[str, list[tuple[float, str | None, str | None]] | None] = {}

    def encode(self, text: str) -> tuple[list[str], list[tuple[float, str | None, str | None]]]:
        """Merge the best-scored neighbours, leftmost first, until none is a piece.

        Also lists each merge as (score, new last symbol or None, new first symbol or None).
        """
        symbols, steps = list(text), []
        while len(symbols) > 1:
            best, at = None, -1
            for i in range(len(symbols) - 1):
                score = self.scores.get(symbols[i] + symbols[i + 1])
                if score is not None and (best is None or score > best):
                    best, at = score, i
            if best is None:
                break
            symbols[at : at + 2] = [symbols[at] + symbols[at + 1]]
            steps.append((best, symbols[-1] if at == len(symbols) - 1 else None, symbols[0] if at == 0 else None))
        return symbols, steps

    def made(self, piece: str) -> list | None:
        """The merges that make a piece from its characters, or None if they end elsewhere."""
        if piece not in self.history:
            symbols, steps = self.encode(piece)
            self.history[piece] = steps if len(symbols) == 1 else None
        return self.history[piece]

    def apart(self, a: str, b: str) -> bool:
        """Whether merging ``a`` and ``b`` as one text ends with the two pieces as they are.

        Both sides merge as they do alone until a merge over the border is the best on offer.
        """
        left, right = self.made(a), self.made(b)
        if left is None or right is None:
            return False
        i = j = 0
        last, first = a[-1], b[0]
        over = self.scores.get(last + first)
        low = float("-inf")
        while True:
            x = left[i][0] if i < len(left) else low
            y = right[j][0] if j < len(right) else low
            if over is not None and over > x and over >= y:
                return False
            if x == low and y == low:
                return True
            if x >= y:
                changed, i = left[i][1], i + 1
                last = changed or last
            else:
                changed, j = right[j][2], j + 1
                first = changed or first
            if changed:
                over = self.scores.get(last + first)


class PieceCodec:
    """Encoder and decoder of one model file's contents."""

    def __init__(self, raw: bytes):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_proto=raw)
        size = model.get_piece_size()
        self.pieces = [model.id_to_piece(i) for i in range(size)]
        special = [model.is_control(i) or model.is_unknown(i) or model.is_byte(i) for i in range(size)]
        self.ids = {p: i for i, p in enumerate(self.pieces) if not special[i]}
        self.scores = {p: model.get_score(i) for p, i in self.ids.items()}
        self.bytes = {int(p[3:5], 16): i for i, p in enumerate(self.pieces) if model.is_byte(i)}
        self.unknown = model.unk_id()
        #: Lengths of the pieces with a given ending of up to three characters, longest first.
        self.lengths: dict[str, tuple[int, ...]] = {}
        for p in self.ids:
            self.lengths[p[-3:]] = (*self.lengths.get(p[-3:], ()), len(p))
        for ending in sorted(self.lengths, key=len, reverse=True):
            self.lengths[ending] = tuple(sorted(set(self.lengths[ending]), reverse=True))
        check_normaliser(raw)
        self.merges = Merges(self.scores) if is_merge_model(raw) else None
        self.floor = min(self.scores.values()) - UNKNOWN_PENALTY
        if any(MARK in p.lstrip(MARK) for p in self.ids):
            raise ValueError("a piece crosses a word's mark")
        #: Characters that no longer piece has: a text can be cut around them.
        joined = {c for p in self.ids if len(p) > 1 for c in p}
        alone = "".join(re.escape(c) for c in "\n\t\r" if c not in joined)
        self.words = re.compile(f"{MARK}+[^{MARK}{alone}]*|[^{MARK}{alone}]+" + (f"|[{alone}]" if alone else ""))
        self.memory: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.pairs: dict[int, bool] = {}
        self.sizes = list(map(len, self.pieces))
        self.codes = [i.to_bytes(4, "little") for i in range(size)]
        self.surface = np.array([b"" if special[i] and i not in self.bytes.values() else p.replace(MARK, " ").encode() for i, p in enumerate(self.pieces)], object)
        for value, i in self.bytes.items():
            self.surface[i] = bytes([value])
        self.surface[self.unknown] = " ⁇ ".encode()

    def split(self, text: str) -> list[str]:
        """Marked words of a text."""
        return self.words.findall(MARK + text.replace(" ", MARK)) if text else []

    def encode_words(self, words: list[str]) -> dict[str, bytes]:
        """Ids of distinct words as little-endian 32-bit numbers, depth-first over their trie."""
        words = sorted(words)
        heads = np.array(words, dtype=f"U{SHARED}").view(np.uint32).reshape(len(words), SHARED)
        same = (heads[1:] == heads[:-1]) & (heads[1:] != 0)
        shared = [0, *np.logical_and.accumulate(same, axis=1).sum(axis=1).tolist()]
        out, codes, sizes = {}, self.codes, self.sizes
        last: list[int] = [0]
        best: list[float] = [0.0]
        steps = self._merge_steps if self.merges else self._score_steps
        for word, n in zip(words, shared):
            del last[n + 1 :], best[n + 1 :]
            steps(word, n, last, best)
            found, at = [], len(word)
            while at:
                own = last[at]
                if own < 0:
                    at -= 1
                    found.append(self._unknown_code(word[at]))
                else:
                    at -= sizes[own]
                    found.append(codes[own])
            found.reverse()
            out[word] = b"".join(found)
        return out

    def _endings(self, word: str, end: int) -> Iterator[int]:
        """Where pieces that end at ``end`` can begin, the longest piece first."""
        for size in (3, 2, 1):
            if size <= end:
                for n in self.lengths.get(word[end - size : end], ()):
                    if (n == size or size == 3) and n <= end:
                        yield end - n

    def _merge_steps(self, word: str, start: int, last: list[int], best: list[float]) -> None:
        ids, lengths, pairs = self.ids.get, self.lengths.get, self.pairs.get
        for end in range(start + 1, len(word) + 1):
            choice = None
            if end > 2:
                for n in lengths(word[end - 3 : end], ()):
                    begin = end - n
                    if begin >= 0:
                        piece = ids(word[begin:end])
                        if piece is not None:
                            before = last[begin] if begin else -1
                            known = pairs((before << 20) | piece)
                            if known or (known is None and self._apart(before, piece)):
                                choice = piece
                                break
            if choice is None and end > 1:
                piece = ids(word[end - 2 : end])
                if piece is not None and self._apart(last[end - 2] if end > 2 else -1, piece):
                    choice = piece
            last.append(ids(word[end - 1], -1) if choice is None else choice)

    def _apart(self, before: int, piece: int) -> bool:
        """Whether a piece can follow another one, or (-1) a border that nothing merges over."""
        key = (before << 20) | piece
        known = self.pairs.get(key)
        if known is None:
            if len(self.pairs) >= PAIRS:
                self.pairs.clear()
            text = self.pieces[piece]
            known = self.pairs[key] = self.merges.made(text) is not None if before < 0 else self.merges.apart(self.pieces[before], text)
        return known

    def _score_steps(self, word: str, start: int, last: list[int], best: list[float]) -> None:
        scores, ids = self.scores, self.ids
        for end in range(start + 1, len(word) + 1):
            choice = word[end - 1]
            top = best[end - 1] + scores.get(choice, self.floor)
            for begin in self._endings(word, end):
                score = scores.get(word[begin:end])
                if score is not None and best[begin] + score > top:
                    choice, top = word[begin:end], best[begin] + score
            last.append(ids.get(choice, -1))
            best.append(top)

    def _unknown_code(self, char: str) -> bytes:
        """Code of a character outside the vocabulary: its bytes' pieces, or the unknown piece."""
        if len(self.bytes) == 256:
            return b"".join(self.codes[self.bytes[b]] for b in char.encode())
        return self.codes[self.unknown]

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text; words met before come from memory.

        Memory has two generations: when the younger is full it becomes the older, and words
        still in use come back from there.
        """
        split = [self.split(t) for t in texts]
        words = set().union(*split)
        new = words.difference(self.memory)
        if len(self.memory) + len(new) > REMEMBERED:
            self.older, self.memory, new = self.memory, {}, words
        older = self.older
        known = new.intersection(older) if older else set()
        self.memory.update((w, older[w]) for w in known)
        new = new.difference(known)
        if new:
            self.memory.update(self.encode_words(list(new)))
        get = self.memory.__getitem__
        return [np.frombuffer(b"".join(map(get, words)), "<i4") for words in split]

    def decode(self, ids: np.ndarray) -> str:
        """The text of ids; byte pieces join to characters, the mark before the first word goes."""
        text = b"".join(self.surface[ids].tolist()).decode("utf-8", "replace")
        return text[1:] if text.startswith(" ") else text


@lru_cache(maxsize=1)
def codec(raw: bytes) -> PieceCodec:
    return PieceCodec(raw)


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))


def model_bytes(path: str | None = None) -> bytes:
    with open(path or default_path(), "rb") as f:
        return f.read()


def encode_texts(docs: DataFrame, raw: bytes | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids) of each whole text; null and empty texts have no ids, null ids and repeats stay."""
    model = docs.sparkSession.sparkContext.broadcast(raw or model_bytes())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model.value)
        for whole in batches:
            for batch in slices(whole, limit=TOGETHER):
                ids = own.encode([t or "" for t in batch.column("text").to_pylist()])
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(ids, pa.list_(pa.int32()))], names=["id", "ids"])

    return _rows(docs, id_col, text_col).mapInArrow(run, "id bigint, ids array<int>")


def decode_ids(encoded: DataFrame, raw: bytes | None = None, id_col: str = "id", ids_col: str = "ids") -> DataFrame:
    """(id, text) of each list of ids; a null list gives a null text, bad bytes U+FFFD."""
    model = encoded.sparkSession.sparkContext.broadcast(raw or model_bytes())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model.value)
        for batch in batches:
            texts = [None if ids is None else own.decode(np.array(ids, np.int64)) for ids in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(texts, pa.string())], names=["id", "text"])

    return encoded.select(F.col(id_col).alias("id"), F.col(ids_col).alias("ids")).mapInArrow(run, "id bigint, text string")


DIGESTS = "id bigint, n_ids bigint, ids_crc32 bigint, decoded_crc32 bigint, round_trip boolean"


def codec_digests(docs: DataFrame, raw: bytes | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode and decode each whole text where it lies and return digests of both.

    ``round_trip`` tells whether decoding gave the text back; a null text counts as empty.
    """
    model = docs.sparkSession.sparkContext.broadcast(raw or model_bytes())
    names = [x.split()[0] for x in DIGESTS.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model.value)
        for whole in batches:
            for batch in slices(whole, limit=TOGETHER):
                texts = [t or "" for t in batch.column("text").to_pylist()]
                ids = own.encode(texts)
                back = [own.decode(x) for x in ids]
                columns = [[len(x) for x in ids], [zlib.crc32(x.astype("<i4").tobytes()) for x in ids], [zlib.crc32(t.encode()) for t in back], [a == b for a, b in zip(texts, back)]]
                yield pa.RecordBatch.from_arrays([batch.column("id"), *map(pa.array, columns)], names=names)

    return _rows(docs, id_col, text_col).mapInArrow(run, DIGESTS)
