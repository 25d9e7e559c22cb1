"""Language by segmentation-marginalised unigrams over a fixed piece vocabulary.

A word, marked at its start and lower-cased, may be cut into vocabulary pieces in many ways.
Each language has a probability for every piece; a word's likelihood is the sum over all its
segmentations, by the forward algorithm, and a text's is the product over its words. Piece
probabilities are fitted by expectation-maximisation over the same sums. Distinct words of a
batch are scored once, all languages side by side.
"""

from __future__ import annotations

import re
import unicodedata
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phrasework.llm.textbytes import U64, Words, mix, slices, utf8
from phrasework.llm.toxicity import held_out

#: About so many documents of each language are fitted on; more than so many languages are an error.
FIT_PER_LANGUAGE, MAX_LANGUAGES = 300, 256
ROUNDS, SMOOTHING = 3, 0.05
MARK = "▁"
UNDETERMINED = "und"
#: Distinct words in each of the two generations that a worker remembers the scores of.
REMEMBERED = 100_000
BASE = 0x9E3779B97F4A7C15
FILTER_BITS = 22
#: Letters that are scored as one word; a longer unbroken run counts as words of this length, one after the other.
RUN = 64
#: Bytes up to which a word's scores are remembered, and cells of a lattice that are worked on at a time.
REMEMBERED_BYTES, LATTICE_CELLS = 64, 1 << 19
_SPACES = re.compile(r"[\x20\x09-\x0D]+")


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


@lru_cache(maxsize=1)
def vocabulary(path: str) -> list[str]:
    """Pieces of a public vocabulary that a marked lower-case word can contain."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = (model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_byte(i) or model.is_unknown(i)))
    return sorted({p for p in pieces if p == p.lower() and (p.removeprefix(MARK).isalpha() or p == MARK)})


def letters_of(word: str) -> str:
    """The word's letters in lower case; combining marks join the letter before them."""
    word = unicodedata.normalize("NFC", word).lower() if not word.isascii() else word.lower()
    return word if word.isalpha() else "".join(c for c in word if c.isalpha())


def pieces_of_run(letters: str) -> list[str]:
    """A word's letters in stretches of at most ``RUN``."""
    return [letters[k : k + RUN] for k in range(0, len(letters), RUN)] if len(letters) > RUN else [letters]


def _powers(n: int, base: int) -> np.ndarray:
    out = np.full(n, base, U64)
    out[0] = 1
    return np.multiply.accumulate(out)


class Lattice:
    """All pieces that occur in a list of words, by their start and end."""

    def __init__(self, pieces: list[str]):
        self.longest = max(map(len, pieces))
        keys = np.array([self._hash(p) for p in pieces], U64)
        self.order = np.argsort(keys)
        self.keys = keys[self.order]
        if len(np.unique(keys)) < len(keys):
            raise ValueError("two pieces share a hash")
        self.filter = np.zeros(1 << FILTER_BITS, bool)
        self.filter[keys >> U64(64 - FILTER_BITS)] = True
        self.unknown = len(pieces)

    @staticmethod
    def _hash(piece: str) -> int:
        codes = np.array([ord(c) for c in piece], U64)
        return int(mix((mix(codes + U64(1)) * _powers(len(codes) + 1, BASE)[:-1]).sum(keepdims=True))[0])

    def spans(self, words: list[str]):
        """(codes' hash sums, powers back, lengths) of marked words, one row a word."""
        marked = [MARK + w for w in words]
        size = np.array([len(w) for w in marked])
        codes = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), "<u4")
        width = int(size.max())
        inside = np.arange(width) < size[:, None]
        table = np.zeros(inside.shape, U64)
        table[inside] = mix(codes.astype(U64) + U64(1))
        sums = np.zeros((len(words), width + 1), U64)
        np.cumsum(table * _powers(width + 1, BASE)[:-1], axis=1, out=sums[:, 1:])
        return sums, _powers(width + 1, pow(BASE, -1, 1 << 64)), size

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Indexes that hit a piece, and the pieces."""
        hit = np.flatnonzero(self.filter[keys >> U64(64 - FILTER_BITS)])
        at = np.searchsorted(self.keys, keys[hit])
        ok = at < len(self.keys)
        hit, at = hit[ok], at[ok]
        ok = self.keys[at] == keys[hit]
        return hit[ok], self.order[at[ok]]

    def edges(self, words: list[str]):
        """For each end position: list of (start, rows, pieces), single unknown characters included."""
        sums, back, size = self.spans(words)
        for end in range(1, sums.shape[1]):
            live = np.flatnonzero(size >= end)
            got = []
            for start in range(max(0, end - self.longest), end):
                hit, piece = self.find(mix((sums[live, end] - sums[live, start]) * back[start]))
                rows = live[hit]
                if start == end - 1 and len(hit) < len(live):
                    missing = np.ones(len(live), bool)
                    missing[hit] = False
                    rows = np.concatenate([rows, live[missing]])
                    piece = np.concatenate([piece, np.full(int(missing.sum()), self.unknown)])
                if len(rows):
                    got.append((start, rows, piece))
            yield end, got


def word_scores(lattice: Lattice, chances: np.ndarray, words: list[str]) -> np.ndarray:
    """Log-likelihood of each word, a column a language: forward sums over segmentations.

    Words of like length go together, as many as a lattice of bounded size takes; a running scale keeps long words from vanishing.
    """
    out = np.zeros((len(words), chances.shape[1]))
    sizes = np.array([len(w) for w in words])
    order = np.argsort(sizes, kind="stable")
    groups, k = [], 0
    while k < len(order):
        step = 1 << 13
        while step > 1 and step * (int(sizes[order[min(k + step, len(order)) - 1]]) + 1) > LATTICE_CELLS:
            step //= 2
        groups.append(order[k : k + step])
        k += step
    for part in groups:
        own = [words[i] for i in part]
        ring: dict[int, np.ndarray] = {0: np.ones((len(own), chances.shape[1]))}
        scale = np.zeros(out[part].shape)
        size = np.array([len(w) for w in own]) + 1
        for end, got in lattice.edges(own):
            now = np.zeros((len(own), chances.shape[1]))
            for start, rows, piece in got:
                now[rows] += ring[start][rows] * chances[piece]
            ring[end] = now
            ring.pop(end - lattice.longest, None)
            done = np.flatnonzero(size == end)
            if len(done):
                out[part[done]] = np.log(now[done]) + scale[done]
            if end % 8 == 0:
                top = np.where(now > 0, now, 1.0)
                scale += np.log(top)
                for values in ring.values():
                    values /= top
    return out


def fit_pieces(lattice: Lattice, counts: list[Counter], rounds: int = ROUNDS) -> np.ndarray:
    """Piece probabilities (pieces + unknown, languages) by expectation-maximisation on word counts."""
    chances = np.ones((lattice.unknown + 1, len(counts)))
    for column, count in enumerate(counts):
        words = sorted(count)
        if not words:
            chances[:, column] = 1 / (lattice.unknown + 1)
            continue
        weight = np.array([count[w] for w in words], float)
        prob = np.full(lattice.unknown + 1, 1 / (lattice.unknown + 1))
        everything = list(lattice.edges(words))
        size = np.array([len(w) for w in words]) + 1
        width = int(size.max())
        for _ in range(rounds):
            ahead = np.zeros((width + 1, len(words)))
            ahead[0] = 1
            for end, got in everything:
                for start, rows, piece in got:
                    ahead[end, rows] += ahead[start, rows] * prob[piece]
            total = ahead[size, np.arange(len(words))]
            behind = np.zeros((width + 1, len(words)))
            behind[size, np.arange(len(words))] = weight / total
            expected = np.zeros(lattice.unknown + 1)
            for end, got in reversed(everything):
                for start, rows, piece in got:
                    flow = behind[end, rows] * prob[piece]
                    behind[start, rows] += flow
                    expected += np.bincount(piece, flow * ahead[start, rows], minlength=len(expected))
            prob = (expected + SMOOTHING) / (expected.sum() + SMOOTHING * len(expected))
        chances[:, column] = prob
    return chances


@dataclass
class Model:
    path: str
    languages: list[str]
    chances: np.ndarray

    def lattice(self) -> Lattice:
        return _lattice(self.path)


@lru_cache(maxsize=1)
def _lattice(path: str) -> Lattice:
    return Lattice(vocabulary(path))


def word_counts(texts: list[str]) -> Counter:
    """How often each word, or stretch of a long run, occurs; words end at ASCII white space, as in scoring."""
    count = Counter(w for text in texts for w in _SPACES.split(text))
    out: Counter = Counter()
    for word, n in count.items():
        if letters := letters_of(word):
            for piece in pieces_of_run(letters):
                out[piece] += n
    return out


def fit_on(docs: DataFrame, path: str | None = None, per_language: int = FIT_PER_LANGUAGE, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """Fit on a hash-picked sample of about ``per_language`` documents of each language outside the test fold."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"))
    rows = rows.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("id").isNotNull() & ~held_out(F.col("id"), 4, 2))
    sizes = {r[0]: r[1] for r in rows.groupBy("lang").count().orderBy("lang").limit(MAX_LANGUAGES + 1).collect()}
    if len(sizes) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages")
    share = F.lit(0.0)
    for lang, n in sizes.items():
        share = F.when(F.col("lang") == lang, F.lit(per_language / n)).otherwise(share)
    picked = rows.where(F.pmod(F.xxhash64("id", F.lit("fit")), F.lit(1 << 20)) < share * (1 << 20)).limit(2 * per_language * max(1, len(sizes)))
    texts: dict[str, list[str]] = {lang: [] for lang in sizes}
    for row in picked.select("lang", "text").toArrow().to_pylist():
        texts[row["lang"]].append(row["text"])
    return fit(texts, path)


def fit(texts: dict[str, list[str]], path: str | None = None) -> Model:
    """Fit on texts by language; languages come in sorted order."""
    path = path or default_path()
    languages = sorted(texts)
    counts = [word_counts(texts[lang]) for lang in languages]
    lattice = _lattice(path)
    return Model(path, languages, fit_pieces(lattice, counts) if languages else np.ones((lattice.unknown + 1, 0)))


class WordMemory:
    """Scores of words met before, in tables of bounded size; NaN for words without a letter.

    When the younger generation is full it becomes the older one, from which words still in use
    come back.
    """

    def __init__(self, kinds: int, limit: int = REMEMBERED):
        self.limit, self.kinds = limit, kinds
        self.row, self.table = {}, np.zeros((limit, kinds))
        self.old_row, self.old_table = {}, np.zeros((0, kinds))

    def scores(self, model: Model, distinct: list[bytes]) -> np.ndarray:
        """One row a word; words too long to be remembered are scored anew each time."""
        long = [i for i, w in enumerate(distinct) if len(w) > REMEMBERED_BYTES]
        if not long:
            return self._remembered(model, distinct)
        out = np.empty((len(distinct), self.kinds))
        short = np.setdiff1d(np.arange(len(distinct)), long)
        out[short] = self._remembered(model, [distinct[i] for i in short.tolist()])
        out[long] = self._fresh(model, [distinct[i] for i in long])
        return out

    def _fresh(self, model: Model, words: list[bytes]) -> np.ndarray:
        got, owner, runs = np.full((len(words), self.kinds), np.nan), [], []
        for i, word in enumerate(words):
            if letters := letters_of(word.decode()):
                pieces = pieces_of_run(letters)
                owner += [i] * len(pieces)
                runs += pieces
        if runs:
            got[owner] = 0.0
            distinct, which = np.unique(np.array(runs, object), return_inverse=True)
            np.add.at(got, owner, word_scores(model.lattice(), model.chances, distinct.tolist())[which])
        return got

    def _remembered(self, model: Model, distinct: list[bytes]) -> np.ndarray:
        new = [w for w in distinct if w not in self.row]
        if new and len(self.row) + len(new) > self.limit:
            self.old_row, self.old_table = self.row, self.table
            self.row, self.table, new = {}, np.zeros((max(self.limit, len(distinct)), self.kinds)), distinct
        if new:
            back = [w for w in new if w in self.old_row]
            fresh = [w for w in new if w not in self.old_row]
            got = self._fresh(model, fresh)
            at = len(self.row)
            self.row.update(zip(back + fresh, range(at, at + len(new))))
            self.table[at : at + len(back)] = self.old_table[[self.old_row[w] for w in back]]
            self.table[at + len(back) : at + len(new)] = got
        return self.table[[self.row[w] for w in distinct]]


def batch_scores(model: Model, raw: np.ndarray, at: np.ndarray, memory: WordMemory | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Summed log-likelihoods (row, language) and number of words with a letter of each row."""
    words = Words(raw, at)
    kinds = len(model.languages)
    memory = memory or WordMemory(kinds)
    if not len(words):
        return np.zeros((len(at) - 1, kinds)), np.zeros(len(at) - 1, np.int64)
    inside = np.zeros(len(words.text) + 1, np.int64)
    np.add.at(inside, words.starts, 1)
    np.add.at(inside, words.ends, -1)
    buffer = words.text[np.cumsum(inside[:-1]) > 0]
    offsets = np.concatenate([[0], np.cumsum(words.ends - words.starts)])
    column = pa.Array.from_buffers(pa.large_binary(), len(words), [None, pa.py_buffer(offsets.astype(np.int64)), pa.py_buffer(buffer)])
    coded = column.dictionary_encode()
    table = memory.scores(model, coded.dictionary.to_pylist())
    real = ~np.isnan(table[:, 0]) if kinds else np.zeros(len(table), bool)
    codes = coded.indices.to_numpy()
    each, counted = np.where(real[:, None], table, 0.0)[codes], real[codes].astype(np.int64)
    total, n = np.zeros((len(at) - 1, kinds)), np.zeros(len(at) - 1, np.int64)
    full = np.flatnonzero(words.counts)
    total[full] = np.add.reduceat(each, words.rows[full], axis=0)
    n[full] = np.add.reduceat(counted, words.rows[full])
    return total, n


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, lang_pred, score, words) of each whole text.

    ``score`` is the predicted language's share of the likelihood, all languages counting alike
    beforehand. An unbroken run of more than ``RUN`` letters is scored as words of ``RUN`` letters. Null texts, texts without a letter, and every text if no language was learned
    get ``und`` and score 0. Equal likelihoods go to the first language by name. Null ids and
    repeated rows stay; an empty table gives no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        names = np.array([*model.languages, UNDETERMINED], object)
        memory = WordMemory(len(model.languages))
        for whole in batches:
            for batch in slices(whole):
                total, n = batch_scores(model, *utf8(batch.column("text")), memory)
                known = (n > 0) & (len(model.languages) > 0)
                if len(model.languages):
                    best = np.where(known, total.argmax(axis=1), len(model.languages))
                    top = total.max(axis=1)
                    score = np.where(known, 1 / np.exp(total - top[:, None]).sum(axis=1), 0.0)
                else:
                    best, score = np.zeros(len(n), np.int64), np.zeros(len(n))
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(names[best], pa.string()), pa.array(score), pa.array(n)], names=["id", "lang_pred", "score", "words"])

    return docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text")).mapInArrow(run, "id bigint, lang_pred string, score double, words bigint")


def keep_identified(docs: DataFrame, model: Model, least_score: float = 0.5, text_col: str = "text") -> DataFrame:
    """``docs`` without rows of undetermined language or a score below ``least_score``; columns as before.

    Null texts and texts without a letter are undetermined and go, and so does every row if no language was
    learned; null ids and repeated rows stay with their text. An empty table gives no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        memory = WordMemory(len(model.languages))
        for whole in batches:
            for batch in slices(whole, at):
                total, n = batch_scores(model, *utf8(batch.column(at)), memory)
                keep = n > 0
                if len(model.languages):
                    keep &= 1 / np.exp(total - total.max(axis=1, keepdims=True)).sum(axis=1) >= least_score
                yield batch.filter(pa.array(keep & (len(model.languages) > 0)))

    return docs.mapInArrow(run, docs.schema)
