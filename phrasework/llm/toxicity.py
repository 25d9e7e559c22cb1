"""Toxic spans by a linear-chain conditional random field over words.

Two states, clean and toxic. A word's features are its letters as a whole, its beginnings and
its endings, hashed into one weight table. Word labels for training come from document labels:
a feature that marks toxic documents far beyond chance labels the words of toxic documents
that have it. Forward-backward marginals give offending words, and their largest and expected
number give the document's score.

The texts of a batch are one long chain in which each text's first word forgets what stood
before it, so forward and backward passes run over blocks side by side.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phrasework.llm.textbytes import LOW_BYTES, U64, Words, mix, slices, span_hashes, utf8

#: Labelled documents that the model is fitted on, by label; of more a hash picks about so many.
FIT_TOXIC, FIT_CLEAN = 1500, 2500
#: Bytes of text that the fit passes through at a time.
FIT_CHUNK = 1 << 20
LOG2_WEIGHTS = 18
BEGINNINGS, ENDINGS = (3, 4, 5, 6, 7, 8), (4, 5, 6)
#: A marking feature's odds against its odds in clean documents.
LEAST_ODDS = 6.0
EPOCHS, RATE, DECAY = 20, 1.0, 2e-6
#: Words that one row of a block scan has.
BLOCK = 128
THRESHOLD = 0.7
#: Words that the chain's matrices are held of at a time.
SEGMENT = 1 << 18
MASK = (1 << 64) - 1


def _letters() -> np.ndarray:
    keep = np.zeros(256, bool)
    keep[65:91] = keep[97:123] = keep[128:] = True
    return keep


IS_LETTER = _letters()


def word_features(words: Words) -> np.ndarray:
    """Hashed feature numbers, one row a word: whole, beginnings, endings, in letters only.

    A-Z and the capital letters of the Latin-1 block count as lower case; a feature longer than
    the word is number 0.
    """
    text = words.text
    keep = IS_LETTER[text]
    moved = np.zeros(len(text) + 1, np.int64)
    np.cumsum(keep, out=moved[1:])
    letters = text[keep].copy()
    letters[(letters >= 65) & (letters <= 90)] += 32
    after_c3 = np.flatnonzero((letters[:-1] == 0xC3) & (letters[1:] >= 0x80) & (letters[1:] <= 0x9E)) + 1
    letters[after_c3] += 32
    buffer = np.zeros(len(letters) + 8, np.uint8)
    buffer[: len(letters)] = letters
    groups = np.ndarray((len(letters) + 1,), dtype="<u8", buffer=buffer.data, strides=(1,))
    start, end = moved[words.starts], moved[words.ends]
    size = end - start
    shift = U64(64 - LOG2_WEIGHTS)
    out = np.zeros((1 + len(BEGINNINGS) + len(ENDINGS), len(words)), np.int32)
    out[0] = np.where(size > 0, span_hashes(groups, start, end, 11) >> shift, 0)
    head = groups[start]
    for k, n in enumerate(BEGINNINGS):
        out[1 + k] = np.where(size >= n, mix((head & LOW_BYTES[n]) + U64(n * 0x9E3779B97F4A7C15 & MASK)) >> shift, 0)
    for k, n in enumerate(ENDINGS):
        tail = groups[np.maximum(end - n, 0)] & LOW_BYTES[n]
        out[1 + len(BEGINNINGS) + k] = np.where(size >= n, mix(tail + U64((n + 64) * 0x9E3779B97F4A7C15 & MASK)) >> shift, 0)
    return out


def _times(a, b):
    """Products of 2x2 matrices held as (2, 2, n), scaled to entries that sum to one."""
    c = np.stack([np.stack([a[i, 0] * b[0, j] + a[i, 1] * b[1, j] for j in (0, 1)]) for i in (0, 1)])
    return c / c.sum(axis=(0, 1))


def chain_messages(steps: np.ndarray, block: int = BLOCK, start: tuple[float, float] = (1.0, 0.0)) -> np.ndarray:
    """Normalised row vectors after each step of a chain of 2x2 matrices (2, 2, n), from ``start``."""
    n = steps.shape[2]
    rows = max(1, -(-n // block))
    padded = np.zeros((2, 2, rows * block))
    padded[0, 0] = padded[1, 1] = 1.0
    padded[:, :, :n] = steps
    columns = padded.reshape(2, 2, rows, block).transpose(3, 0, 1, 2).copy()
    whole = columns[0]
    for c in range(1, block):
        whole = _times(whole, columns[c])
    starts = np.zeros((2, rows))
    v0, v1 = start
    w00, w01, w10, w11 = (whole[i, j].tolist() for i in (0, 1) for j in (0, 1))
    for r in range(rows):
        starts[0, r], starts[1, r] = v0, v1
        a, b = v0 * w00[r] + v1 * w10[r], v0 * w01[r] + v1 * w11[r]
        v0, v1 = a / (a + b), b / (a + b)
    out = np.zeros((2, block, rows))
    v = starts
    for c in range(block):
        m = columns[c]
        v = np.stack([v[0] * m[0, 0] + v[1] * m[1, 0], v[0] * m[0, 1] + v[1] * m[1, 1]])
        v = v / (v[0] + v[1])
        out[:, c] = v
    return out.transpose(0, 2, 1).reshape(2, -1)[:, :n]


@dataclass
class Field:
    """Weights of a fitted chain: features, moves between states, first states, document score."""

    weights: np.ndarray
    moves: np.ndarray
    first: np.ndarray
    scale: tuple[float, float, float]

    def steps(self, emission: np.ndarray, opens: np.ndarray) -> np.ndarray:
        """The chain's matrices; ``opens`` are positions of first words."""
        e = np.exp(np.clip(emission, -30, 30))
        m = np.empty((2, 2, len(e)))
        m[0, 0], m[1, 0] = np.exp(self.moves[0, 0]), np.exp(self.moves[1, 0])
        m[0, 1], m[1, 1] = np.exp(self.moves[0, 1]) * e, np.exp(self.moves[1, 1]) * e
        m[:, 0, opens] = np.exp(self.first[0])
        m[:, 1, opens] = np.exp(self.first[1]) * e[opens]
        return m

    def marginals(self, emission: np.ndarray, opens: np.ndarray):
        """P(toxic) of each word, and what the gradient needs: steps, forward and backward vectors."""
        m = self.steps(emission, opens)
        ahead = chain_messages(m)
        flipped = np.ascontiguousarray(m[:, :, ::-1].transpose(1, 0, 2))
        shifted = np.concatenate([np.ones((2, 2, 1)), flipped[:, :, :-1]], axis=2)
        back = chain_messages(shifted)[:, ::-1]
        both = ahead * back
        return both[1] / (both[0] + both[1]), m, ahead, back

    def toxic_chances(self, words: Words) -> np.ndarray:
        """P(toxic) of each word of a batch of rows.

        More words than a segment has, a very long text's for instance, go segment by segment: forward keeping
        the vector at each border, then backward once more through each, so memory is a segment's.
        """
        n = len(words)
        opens = words.rows[:-1][words.counts > 0]
        if n <= SEGMENT:
            return self.marginals(self.emission(word_features(words)), opens)[0] if n else np.zeros(0)
        cuts = [(k, min(k + SEGMENT, n)) for k in range(0, n, SEGMENT)]

        def steps(a: int, b: int) -> np.ndarray:
            return self.steps(self.emission(word_features(words.part(a, b))), opens[(opens >= a) & (opens < b)] - a)

        borders = [(1.0, 0.0)]
        for a, b in cuts[:-1]:
            borders.append(tuple(chain_messages(steps(a, b), start=borders[-1])[:, -1]))
        out, after = np.empty(n), (0.5, 0.5)
        for (a, b), before in zip(reversed(cuts), reversed(borders)):
            m = steps(a, b)
            flipped = np.ascontiguousarray(m[:, :, ::-1].transpose(1, 0, 2))
            back = np.concatenate([np.array(after)[:, None], chain_messages(flipped, start=after)], axis=1)
            both = chain_messages(m, start=before) * back[:, -2::-1]
            out[a:b] = both[1] / (both[0] + both[1])
            after = tuple(back[:, -1])
        return out

    def emission(self, features: np.ndarray) -> np.ndarray:
        out = self.weights[features[0]].copy()
        for f in features[1:]:
            out += self.weights[f]
        return out.astype(np.float64)

    def score(self, largest: np.ndarray, expected: np.ndarray) -> np.ndarray:
        """Document score from its largest marginal and the expected number of toxic words."""
        a, b, c = self.scale
        return 1 / (1 + np.exp(-np.clip(a + b * _logit(largest) + c * np.log1p(expected), -40, 40)))


def _logit(p: np.ndarray) -> np.ndarray:
    p = np.clip(p, 1e-7, 1 - 1e-7)
    return np.log(p / (1 - p))


def document_sums(p: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Largest and summed marginal of each row's words; zeros without words."""
    full = np.flatnonzero(np.diff(rows))
    largest, total = np.zeros(len(rows) - 1), np.zeros(len(rows) - 1)
    if len(full):
        largest[full] = np.maximum.reduceat(p, rows[full])
        total[full] = np.add.reduceat(p, rows[full])
    return largest, total


class MarkCounts:
    """In how many toxic and clean documents each feature stands."""

    def __init__(self):
        self.toxic, self.clean = np.zeros(1 << LOG2_WEIGHTS), np.zeros(1 << LOG2_WEIGHTS)

    def add(self, features: np.ndarray, row_of: np.ndarray, toxic_rows: np.ndarray) -> None:
        size = 1 << LOG2_WEIGHTS
        for f in features:
            pair = np.unique(row_of * np.int64(size) + f)
            of_toxic = toxic_rows[pair >> LOG2_WEIGHTS]
            self.toxic += np.bincount(pair[of_toxic] & (size - 1), minlength=size)
            self.clean += np.bincount(pair[~of_toxic] & (size - 1), minlength=size)

    def marks(self, toxic_rows: int, clean_rows: int) -> np.ndarray:
        """Features that mark toxic documents beyond chance, by an exact-tail bound over all features."""
        a, b = max(1, toxic_rows), max(1, clean_rows)
        base, n = a / (a + b), self.toxic + self.clean
        share = np.clip(self.toxic / np.maximum(n, 1), 1e-9, 1 - 1e-9)
        gain = n * (share * np.log(share / base) + (1 - share) * np.log((1 - share) / (1 - base)))
        marks = (gain > np.log(2 * max(1, int((n > 0).sum())))) & (self.toxic / a > LEAST_ODDS * (self.clean + 0.5) / b)
        marks[0] = False
        return marks


@dataclass
class Chunk:
    """Some texts of the fit: features of their words, row boundaries, word labels."""

    features: np.ndarray
    rows: np.ndarray
    label: np.ndarray

    @property
    def opens(self) -> np.ndarray:
        return self.rows[:-1][np.diff(self.rows) > 0]

    @property
    def inner(self) -> np.ndarray:
        inner = np.ones(self.features.shape[1], bool)
        inner[self.opens] = False
        return np.flatnonzero(inner)


def _chunks(texts: list[str], y: np.ndarray) -> list[Chunk]:
    """Cut the texts into chunks and label their words by marking features."""
    sizes = np.cumsum([len(t.encode()) for t in texts])
    chunks, counts = [], MarkCounts()
    for part in np.split(np.arange(len(texts)), np.flatnonzero(np.diff(sizes // FIT_CHUNK)) + 1):
        words = Words(*utf8(pa.array([texts[i] for i in part], pa.large_string())))
        features = word_features(words)
        counts.add(features, np.repeat(np.arange(len(part)), words.counts), y[part])
        chunks.append(Chunk(features, words.rows, np.repeat(y[part], words.counts)))
    marks = counts.marks(int(y.sum()), int((~y).sum()))
    for chunk in chunks:
        chunk.label &= marks[chunk.features].any(axis=0)
    return chunks


def fit(texts: list[str], labels: list[int]) -> Field:
    """Fit the chain on labelled texts; without both labels every score is the same low one."""
    field = Field(np.zeros(1 << LOG2_WEIGHTS, np.float32), np.array([[0.0, -5.0], [0.0, -2.0]]), np.array([0.0, -5.0]), (-3.0, 0.0, 0.0))
    y = np.array(labels, np.int64) == 1
    if not len(y) or y.all() or not y.any():
        return field
    chunks = _chunks(texts, y)
    n_words = sum(c.features.shape[1] for c in chunks)
    weights, seen = np.zeros(1 << LOG2_WEIGHTS), np.full(1 << LOG2_WEIGHTS, 1e-6)
    other, other_seen = np.concatenate([field.moves.ravel(), field.first]), np.full(6, 1e-6)
    for _ in range(EPOCHS):
        field.weights = weights.astype(np.float32)
        field.moves, field.first = other[:4].reshape(2, 2), other[4:]
        slope, other_slope = -DECAY * n_words * weights, np.zeros(6)
        for c in chunks:
            opens, inner, label = c.opens, c.inner, c.label
            p, m, ahead, back = field.marginals(field.emission(c.features), opens)
            for f in c.features:
                slope += np.bincount(f, label - p, minlength=len(weights))
            pair = ahead[:, None, inner - 1] * m[:, :, inner] * back[None, :, inner]
            pair = (pair / pair.sum(axis=(0, 1))).sum(axis=2).ravel()
            before, after = label[inner - 1], label[inner]
            moves = np.array([np.count_nonzero((before == i) & (after == j)) for i in (0, 1) for j in (0, 1)])
            first = np.array([np.count_nonzero(label[opens] == i) for i in (0, 1)])
            other_slope += np.concatenate([moves - pair, first - [(1 - p[opens]).sum(), p[opens].sum()]])
        slope[0] = 0
        seen += slope * slope
        weights += RATE * slope / np.sqrt(seen)
        other_seen += other_slope * other_slope
        other = other + 0.3 * other_slope / np.sqrt(other_seen)
    sums = [document_sums(field.marginals(field.emission(c.features), c.opens)[0], c.rows) for c in chunks]
    largest, total = (np.concatenate(x) for x in zip(*sums))
    x = np.stack([np.ones(len(y)), _logit(largest), np.log1p(total)])
    beta = prior = np.array([0.0, 1.0, 0.0])
    for _ in range(40):  # Newton steps of a logistic fit with a unit prior, none longer than one
        q = 1 / (1 + np.exp(-np.clip(beta @ x, -30, 30)))
        hessian = (x * (q * (1 - q))) @ x.T + np.eye(3)
        step = np.linalg.solve(hessian, x @ (y - q) - (beta - prior))
        beta = beta + step / max(1.0, float(np.linalg.norm(step)))
        beta[1:] = np.maximum(beta[1:], 0)
    field.scale = tuple(float(v) for v in beta)
    return field


def held_out(id_col, folds: int, fold: int):
    """Whether the CRC-32 of an id as text falls into the fold kept for testing; null: false."""
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % folds == fold, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, toxic: int = FIT_TOXIC, clean: int = FIT_CLEAN, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> DataFrame:
    """Labelled rows outside the test fold, about ``toxic`` and ``clean`` of them: (text, label)."""
    known = labels.select(F.col(id_col).alias("id"), F.col(label_col).alias("label")).where(F.col("label").isin(0, 1) & F.col("id").isNotNull())
    known = known.where(~held_out(F.col("id"), 3, 1))
    sizes = {r[0]: r[1] for r in known.groupBy("label").count().collect()}
    share = F.lit(0.0)
    for value, want in ((1, toxic), (0, clean)):
        share = F.when(F.col("label") == value, F.lit(want / max(1, sizes.get(value, 0)))).otherwise(share)
    picked = known.where(F.pmod(F.xxhash64("id", F.lit("fit")), F.lit(1 << 20)) < share * (1 << 20)).limit(2 * (toxic + clean))
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(picked), "id").select("text", "label")


def fit_on(docs: DataFrame, labels: DataFrame, **names: str) -> Field:
    rows = labelled_sample(docs, labels, **names).toArrow()
    order = np.argsort(np.array([hash_of(t) for t in rows.column("text").to_pylist()], np.uint64), kind="stable") if rows.num_rows else []
    texts, values = rows.column("text").to_pylist(), rows.column("label").to_pylist()
    return fit([texts[i] or "" for i in order], [values[i] for i in order])


def hash_of(text: str | None) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(text or "")


SCORES = "id bigint, score double, toxic_words double, spans array<struct<start:int,end:int,p:double>>"


def score_texts(docs: DataFrame, field: Field, id_col: str = "doc_id", text_col: str = "text", span_at: float = 0.5) -> DataFrame:
    """(id, score, toxic_words, spans) of each whole text.

    ``spans`` are the words with a marginal of ``span_at`` or more, as byte offsets into the
    text itself, in UTF-8. Null and empty texts have no words and the lowest score
    there is; null ids and repeated rows stay; an empty table gives no rows.
    """
    model = docs.sparkSession.sparkContext.broadcast(field)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        field = model.value
        for whole in batches:
            for batch in slices(whole):
                raw, at = utf8(batch.column("text"))
                words = Words(raw, at)
                p = field.toxic_chances(words)
                largest, total = document_sums(p, words.rows)
                hit = np.flatnonzero(p >= span_at)
                owner = np.searchsorted(words.rows, hit, "right") - 1
                begin = words.given[hit] - at[owner]
                struct = pa.StructArray.from_arrays([pa.array(begin.astype(np.int32)), pa.array((begin + words.ends[hit] - words.starts[hit]).astype(np.int32)), pa.array(p[hit])], names=["start", "end", "p"])
                spans = pa.ListArray.from_arrays(pa.array(np.searchsorted(hit, words.rows).astype(np.int32)), struct)
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(field.score(largest, total)), pa.array(total), spans], names=["id", "score", "toxic_words", "spans"])

    return docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text")).mapInArrow(run, SCORES)


def keep_clean(docs: DataFrame, field: Field, threshold: float = THRESHOLD, text_col: str = "text") -> DataFrame:
    """``docs`` without rows whose text scores ``threshold`` or more; columns as before.

    Null and empty texts have the lowest score there is and stay, as do null ids and repeated rows that
    score below the threshold; equal texts score alike. An empty table gives no rows.
    """
    model = docs.sparkSession.sparkContext.broadcast(field)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        field = model.value
        for whole in batches:
            for batch in slices(whole, at):
                words = Words(*utf8(batch.column(at)))
                p = field.toxic_chances(words)
                yield batch.filter(pa.array(field.score(*document_sums(p, words.rows)) < threshold))

    return docs.mapInArrow(run, docs.schema)
