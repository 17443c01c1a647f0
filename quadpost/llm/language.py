"""Language identification: averaged hashed subword embeddings with a linear softmax.

A text's features are the 2- to 4-byte pieces of its lower-cased words, with the
words' borders, hashed to buckets. A document is the average of its pieces'
embeddings; a linear layer and softmax give the languages. Embeddings and layer
are trained by stochastic gradient descent in numpy on a bounded sample of
labelled rows. A temperature fitted on a held-back part calibrates the score,
and two limits of rejection are low quantiles of the right answers there: of the
score, and of the share of a text's pieces whose buckets training saw. A text is
accepted if its language scores enough. A text split between two known languages is
accepted if no more is left for all others than the second of the two has, and enough
of its pieces were seen. With one
or two known languages scores tell nothing, and the share of seen pieces decides.
Buckets that training never saw have zero embeddings, so strange texts score low.

Defined cases: a null text, or one without a letter, is ``und`` with score 0 and
is rejected; rows with a null lang are predicted but never learned from; without
any labelled row every text is ``und``; ties between languages go to the first
by name; repeated rows get equal answers; an empty table gives no rows; extra
columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BUCKET_BITS, DIMENSIONS = 16, 12
#: The bound on what is learned from: about so many rows of each language, chosen by a hash of doc_id.
ROWS_PER_LANGUAGE = 300
EPOCHS, RATE, HELD_BACK = 6, 2.0, 5
UNKNOWN = "und"
#: Each limit of rejection rejects about this share of right answers (of under 1000 of them, the least gives the limit);
#: the defaults hold if no held-back answer is right.
LOST_SHARE, DEFAULT_THRESHOLD, DEFAULT_SEEN = 0.001, 0.5, 0.5
_NOT_LETTERS = re.compile(r"[\W\d_]+")
_SPACE = 32


def pieces(text: str | None) -> np.ndarray | None:
    """The buckets of a text's subword pieces; None if it has no letter."""
    plain = _NOT_LETTERS.sub(" ", (text or "").lower()).strip()
    if not plain or not any(map(str.isalpha, plain)):
        return None
    b = np.frombuffer(f" {plain} ".encode("utf-8", "surrogatepass"), np.uint8)
    space, wide = b == _SPACE, b.astype(np.uint32)
    out, code = [], wide
    inner = np.ones(len(b), bool)
    for n in (2, 3, 4):
        if len(b) < n:
            break
        code = code[: len(b) - n + 1] * np.uint32(0x01000193) ^ wide[n - 1 :]
        if n > 2:
            inner = inner[: len(b) - n + 1] & ~space[n - 2 : len(b) - 1]
        mixed = (code + np.uint32(n)) * np.uint32(0x9E3779B1)
        out.append((mixed >> np.uint32(32 - BUCKET_BITS))[inner[: len(mixed)]])
    return np.concatenate(out)


class Model:
    """``table`` has the embeddings times the linear layer: one row of logits per bucket."""

    def __init__(self, languages: list[str], table: np.ndarray, bias: np.ndarray, temperature: float, threshold: float, seen: np.ndarray, least_seen: float):
        self.languages, self.table, self.bias, self.temperature, self.threshold = languages, table, bias, temperature, threshold
        self.seen, self.least_seen = seen, least_seen

    def logits(self, found: np.ndarray) -> np.ndarray:
        return self.table[found].sum(axis=0, dtype=np.float64) / max(1, len(found)) + self.bias

    def judge(self, text: str | None) -> tuple[str, float, bool]:
        """The language, its score, and whether the text is accepted."""
        found = pieces(text)
        if found is None or not self.languages:
            return UNKNOWN, 0.0, False
        p = _softmax(self.logits(found) / self.temperature)
        best = int(p.argmax())
        accepted = len(p) > 2 and p[best] >= self.threshold
        if not accepted:
            second, rest = (np.partition(p, -2)[-2], 1 - np.sort(p)[-2:].sum()) if len(p) > 2 else (0.0, 0.0)
            accepted = rest <= second and self.seen_share(found) >= self.least_seen
        return self.languages[best], float(min(1.0, p[best])), bool(accepted)

    def seen_share(self, found: np.ndarray) -> float:
        return np.count_nonzero(self.seen[found]) / max(1, len(found))

    def predict(self, text: str | None) -> tuple[str, float]:
        return self.judge(text)[:2]


def _softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max())
    return e / e.sum()


def train(rows: list[tuple[str, str]], seed: int = 7) -> Model:
    """rows: (text, language)."""
    data = [(f, lang) for text, lang in rows if (f := pieces(text)) is not None]
    languages = sorted({lang for _, lang in data})
    k, size = len(languages), 1 << BUCKET_BITS
    if not k:
        return Model([], np.zeros((size, 0), np.float32), np.zeros(0), 1.0, DEFAULT_THRESHOLD, np.zeros(size, bool), DEFAULT_SEEN)
    draw = np.random.default_rng(seed)
    number = {lang: i for i, lang in enumerate(languages)}
    held, learned = data[::HELD_BACK], [x for i, x in enumerate(data) if i % HELD_BACK] or data
    packed = [(*np.unique(f, return_counts=True), number[lang]) for f, lang in learned]
    embed = draw.normal(0, 0.1, (size, DIMENSIONS))
    layer, bias = np.zeros((DIMENSIONS, k)), np.zeros(k)
    seen = np.zeros(size, bool)
    steps, done = EPOCHS * len(packed), 0
    for _ in range(EPOCHS):
        for i in draw.permutation(len(packed)):
            buckets, counts, y = packed[i]
            seen[buckets] = True
            share = counts / counts.sum()
            mean = share @ embed[buckets]
            off = _softmax(mean @ layer + bias)
            off[y] -= 1
            rate = RATE * (1 - done / steps)
            back = layer @ off
            layer -= rate * np.outer(mean, off)
            bias -= 0.01 * rate * off
            embed[buckets] -= rate * 20 * np.outer(share, back)
            done += 1
    embed[~seen] = 0
    model = Model(languages, (embed @ layer).astype(np.float32), bias, 1.0, DEFAULT_THRESHOLD, seen, DEFAULT_SEEN)
    raw = [(model.logits(f), number[lang]) for f, lang in held]
    loss = lambda t: -sum(np.log(max(1e-12, _softmax(x / t)[y])) for x, y in raw)
    model.temperature = float(min(np.geomspace(0.5, 8, 25), key=loss))
    right = [(_softmax(x / model.temperature)[y], model.seen_share(f)) for (x, y), (f, _) in zip(raw, held, strict=True) if int(x.argmax()) == y]
    if right:
        model.threshold, model.least_seen = np.quantile(np.array(right), LOST_SHARE, axis=0).tolist()
    return model


def held_out(doc_id: Column) -> Column:
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(4)) == 2


def fit(docs: DataFrame, rows_per_language: int = ROWS_PER_LANGUAGE) -> Model:
    """Learns from text and lang of rows that are not held out."""
    labelled = docs.where(F.col("lang").isNotNull() & ~held_out(F.col("doc_id")))
    counts = {r[0]: r[1] for r in labelled.groupBy("lang").count().collect()}
    if not counts:
        return train([])
    share = F.lit(0)
    for lang, n in counts.items():
        share = F.when(F.col("lang") == lang, F.lit(int(min(1.0, rows_per_language / n) * (1 << 20)) + 1)).otherwise(share)
    chosen = labelled.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < share).select("doc_id", "lang", F.col("text").cast("string").alias("text"))
    rows = chosen.limit(2 * rows_per_language * len(counts)).collect()
    rows.sort(key=lambda r: (r["doc_id"] is None, r["doc_id"] or 0, r["lang"], r["text"] or ""))
    return train([(r["text"], r["lang"]) for r in rows])


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, lang_pred, score, accepted) for every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # buckets times languages

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            found = [m.judge(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([x for x, _, _ in found], pa.string()), pa.array([s for _, s, _ in found], pa.float64()), pa.array([a for _, _, a in found], pa.bool_())],
                ["doc_id", "lang_pred", "score", "accepted"],
            )

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, lang_pred string, score double, accepted boolean")


def keep_accepted(docs: DataFrame, model: Model) -> DataFrame:
    """The rows of ``docs`` whose text the model accepts, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            yield batch.filter(pa.array([m.judge(t.as_py())[2] for t in batch.column(at)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
