"""Toxicity by a linear-chain conditional random field over words.

Words are labelled from document labels: a word counts as toxic in a toxic document if it is found in many different toxic documents and hardly in others. A two-state chain is
fitted to the sentences of the labelled documents, all of them; its features are a word, its first bytes, and the words before and after it. Forward-backward marginals of the toxic state give spans with offsets; a
document's score is the chance that at least one of its marked words is toxic.

Words without features share one potential, so runs of them are powers of one matrix: a text costs one look-up a word and one step for each word with features, whatever its length, and no text is cut.
For the same reason the fit needs no texts: sentences are reduced to their length and the places, features and labels of their marked words, and equal ones are counted. Word counts, feature counts and these records are
made by the executors; the driver gets candidates for toxic words and features, and the different records.

The fit reads at most TRAIN_ROWS labelled rows of the two classes (least hash of the id), whole; never held-out rows. Labels, language, source and id are no inputs of a score.

Defined results: a null text counts as empty; an empty text, or one without marked words, has the score 0 and no spans; with no labelled rows of both classes all scores are 0; labels that name an id several times count
each time; repeated rows score alike; an empty table gives an empty table; other columns are not read. Sentences of more than LONGEST words are fitted in pieces of so many.
"""

from __future__ import annotations

import json
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.llm.common import id_and_text, per_batch, read, written
from chronolode.llm.quality import held_out

#: Labelled rows of each class (clean, toxic).
TRAIN_ROWS = (4_000, 2_000)
FOLDS, HELD_OUT, CUT = 3, 1, 0.7
#: A toxic word: found in so many different toxic documents, so purely, so seldom in copies only, and so unlikely by chance.
SUPPORT, PURITY, SPREAD, CHANCE = 3, 0.9, 0.4, 0.01
LONGEST, EPOCHS, RATE, DECAY = 40, 100, 0.2, 0.1
PREFIXES = (4, 5, 6)
#: Bytes of ASCII that are no part of a word become blanks.
_BREAKS = bytes(i if i >= 128 or chr(i).isalnum() else 32 for i in range(256))


def words(text: str) -> list[bytes]:
    return text.lower().encode().translate(_BREAKS).split()


def features_of(word: bytes) -> list[bytes]:
    return [b"=" + word, *(b"%d" % n + word[:n] for n in PREFIXES if len(word) >= n)]


def context_of(found: list[bytes], i: int) -> list[bytes]:
    """The words before and after a place, as features of it."""
    return [*([b"<" + found[i - 1]] if i else []), *([b">" + found[i + 1]] if i + 1 < len(found) else [])]


@dataclass
class Tagger:
    """Weights of the toxic state against the other: by feature, for any word, and of the state changes (from, to)."""

    weights: dict[bytes, float] = field(default_factory=dict)
    bias: float = 0.0
    moves: np.ndarray = field(default_factory=lambda: np.zeros((2, 2)))

    def __post_init__(self) -> None:
        least = min(PREFIXES)
        self.starts = {f[1 : least + 1] for f in self.weights if f[:1] not in b"<>"}
        self.before, self.after = ({f[1:] for f in self.weights if f[:1] == side} for side in (b"<", b">"))
        self.least = least
        # Powers of the step over one word without features, scaled by its larger eigenvalue.
        step = np.exp(self.moves) * np.exp([0.0, self.bias])[None, :]
        values, vectors = np.linalg.eig(step)
        values, vectors = values.real, vectors.real
        order = np.argsort(-values)
        self.ratio, self.base = float(values[order[1]] / values[order[0]]), vectors[:, order]
        self.back = np.linalg.inv(self.base)

    def potential(self, found: list[bytes], i: int) -> float:
        return self.bias + sum(self.weights.get(f, 0.0) for f in (*features_of(found[i]), *context_of(found, i)))

    def _run(self, k: int) -> np.ndarray:
        """The step matrix over k words without features, up to a factor."""
        return self.base * np.array([1.0, self.ratio**k])[None, :] @ self.back

    def marked(self, found: list[bytes]) -> list[int]:
        """Positions of words with features."""
        different = set(found)
        at = []
        if not self.starts.isdisjoint({w[: self.least] for w in different}):
            at = [i for i, w in enumerate(found) if w[: self.least] in self.starts and any(f in self.weights for f in features_of(w))]
        beside = []
        if not self.before.isdisjoint(different):
            beside += [i + 1 for i, w in enumerate(found[:-1]) if w in self.before]
        if not self.after.isdisjoint(different):
            beside += [i - 1 for i, w in enumerate(found) if i and w in self.after]
        return sorted({*at, *beside}) if beside else at

    def marginals(self, found: list[bytes]) -> tuple[list[int], list[float]]:
        """Positions of marked words, and the chance of the toxic state at each."""
        at = self.marked(found)
        if not at:
            return [], []
        step, forward, state, last = np.exp(self.moves), [], None, -1
        emit = [np.exp(np.array([0.0, np.clip(self.potential(found, i), -50, 50)])) for i in at]
        for i, e in zip(at, emit, strict=True):
            if state is None:
                state = (np.array([1.0, np.exp(self.bias)]) @ self._run(i - 1) @ step if i else np.ones(2)) * e
            else:
                state = state @ self._run(i - last - 1) @ step * e if i - last > 1 else state @ step * e
            state = state / state.sum()
            forward.append(state)
            last = i
        beta, out, nxt = self._run(len(found) - 1 - at[-1]) @ np.ones(2), [], None
        for j in range(len(at) - 1, -1, -1):
            if nxt is not None:
                gap = at[nxt] - at[j] - 1
                beta = (self._run(gap) if gap else np.eye(2)) @ step @ (emit[nxt] * beta)
            beta = beta / beta.sum()
            p = forward[j] * beta
            out.append(float(p[1] / p.sum()))
            nxt = j
        return at, out[::-1]

    def read(self, text: str, cut: float = 0.5) -> tuple[float, list[tuple[int, int, float]]]:
        """The document's score, and (start, end, chance) in characters of the text for words more likely toxic than not."""
        at, p = self.marginals(words(text))
        hot = {i: x for i, x in zip(at, p, strict=True) if x >= cut}
        # The same words, by their characters: lower-casing may change lengths, so places are counted in the text itself.
        pieces = [m.span() for m in re.finditer(r"[^\x00-/:-@\[-`{-\x7f]+", text)] if hot else []
        return (float(1 - np.prod(1 - np.array(p))) if p else 0.0), [(*pieces[i], x) for i, x in hot.items() if i < len(pieces)]

    def score(self, text: str) -> float:
        return self.read(text)[0]

    def spans(self, text: str, cut: float = 0.5) -> list[tuple[int, int, float]]:
        return self.read(text, cut)[1]


def lexicon(seen: list[tuple[bytes, int, int, int]], as_frequent: dict[int, int], share: float) -> set[bytes]:
    """Toxic words from (word, toxic, clean, copies): in how many different documents of each class a word is, and in how many toxic rows. Documents with the same signature (copies) count once in the first two.

    as_frequent: how many words are found in so many different documents; share: of toxic ones among these.
    A word is toxic if SUPPORT different toxic documents at least hold it, hardly any other does, and chance would hardly give one such word among those as frequent."""
    return {w for w, n, other, copies in seen if n >= max(SUPPORT, PURITY * (n + other), SPREAD * copies) and as_frequent[n + other] * share**n < CHANCE}


def pure(hot: dict[bytes, int], cold: dict[bytes, int]) -> list[bytes]:
    """Features that SUPPORT toxic cases at least have, and hardly any other."""
    return [f for f, n in hot.items() if n >= max(SUPPORT, PURITY * (n + cold.get(f, 0)))]


#: A sentence for the fit: its number of words, (place, features, label) of its marked ones, and how many sentences are equal to it.
Record = tuple[int, list[tuple[int, list[int], int]], int]


@dataclass
class Sequences:
    """Records as arrays: labels and places by (record, place), cells and ids of features, weights."""

    y: np.ndarray
    on: np.ndarray
    cells: np.ndarray
    ids: np.ndarray
    weight: np.ndarray

    @classmethod
    def of(cls, records: list[Record]) -> Sequences:
        n, t = len(records), max(size for size, _, _ in records)
        y, on, cells, ids = np.zeros((n, t)), np.zeros((n, t), bool), [], []
        for r, (size, marked, _) in enumerate(records):
            on[r, :size] = True
            for place, features, label in marked:
                y[r, place] = label
                cells += [r * t + place] * len(features)
                ids += features
        return cls(y, on, np.array(cells, np.int64), np.array(ids, np.int64), np.array([c for _, _, c in records], float))


def objective(theta: np.ndarray, s: Sequences, decay: float = DECAY) -> tuple[float, np.ndarray]:
    """Negative conditional log-likelihood with a quadratic penalty, and its gradient. theta: features, bias, moves."""
    (n, t), features = s.y.shape, len(theta) - 5
    bias, moves = theta[-5], theta[-4:].reshape(2, 2)
    hot = np.clip(np.bincount(s.cells, theta[s.ids], n * t).reshape(n, t) + bias, -50, 50)
    e = np.ones((n, t, 2))
    e[:, :, 1] = np.exp(hot)
    e[~s.on] = 1
    step, pair = np.exp(moves), s.on[:, 1:] & s.on[:, :-1]
    alpha, beta, log_z = np.empty((n, t, 2)), np.ones((n, t, 2)), np.zeros(n)
    for c in range(t):  # each step is scaled to sum 1
        a = (alpha[:, c - 1] @ step if c else 1.0) * e[:, c]
        size = a.sum(1, keepdims=True)
        alpha[:, c] = np.where(s.on[:, c, None], a / size, alpha[:, c - 1])
        log_z += np.where(s.on[:, c], np.log(size[:, 0]), 0)
    for c in range(t - 2, -1, -1):
        b = (e[:, c + 1] * beta[:, c + 1]) @ step.T
        beta[:, c] = np.where(s.on[:, c + 1, None], b / b.sum(1, keepdims=True), 1)
    both = alpha * beta
    p = both[:, :, 1] / both.sum(2) * s.on
    two = alpha[:, :-1, :, None] * step * (e[:, 1:] * beta[:, 1:])[:, :, None, :]
    two = two / two.sum((2, 3), keepdims=True) * pair[:, :, None, None]
    gold = np.stack([(pair & (s.y[:, :-1] == a) & (s.y[:, 1:] == b)).sum(1) for a in (0, 1) for b in (0, 1)], 1)
    loss = s.weight @ (log_z - (hot * s.y * s.on).sum(1) - gold @ moves.ravel()) + decay / 2 * theta @ theta
    error = (p - s.y) * s.on * s.weight[:, None]
    turns = np.tensordot(s.weight, two.sum(1), 1).ravel() - s.weight @ gold
    return float(loss), np.concatenate([np.bincount(s.ids, error.ravel()[s.cells], features), [error.sum()], turns]) + decay * theta


def fit(names: list[bytes], records: list[Record]) -> Tagger:
    """A tagger with the named features, by Adam."""
    if not names or not records:
        return Tagger()
    s, theta = Sequences.of(records), np.zeros(len(names) + 5)
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for epoch in range(1, EPOCHS + 1):
        _, grad = objective(theta, s)
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        theta = theta - RATE * (m / (1 - 0.9**epoch)) / (np.sqrt(v / (1 - 0.99**epoch)) + 1e-9)
    return Tagger({f: float(x) for f, x in zip(names, theta, strict=False)}, float(theta[-5]), theta[-4:].reshape(2, 2))


def sentences(text: str) -> Iterator[list[bytes]]:
    """The words of every sentence, in pieces of LONGEST at most."""
    for part in re.split(r"[.!?\n]", text):
        ws = words(part)
        yield from (ws[i : i + LONGEST] for i in range(0, len(ws), LONGEST))


def _sample(docs: DataFrame, labels: DataFrame, rows: tuple[int, int]) -> DataFrame:
    """(doc_id, text, label): at most so many labelled texts of each class outside the held-out fold."""
    open_rows = labels.filter(~held_out(FOLDS, HELD_OUT)).select(F.col("doc_id").alias("key"), F.col("toxic").cast("int").alias("label"))
    some = [open_rows.filter(F.col("label") == c).orderBy(F.xxhash64("key")).limit(rows[c]) for c in (0, 1)]
    keys = F.broadcast(some[0].union(some[1]))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).join(keys, F.col("doc_id") == F.col("key")).select("doc_id", "text", "label")


def _word_counts(some: DataFrame) -> DataFrame:
    """(word, toxic, clean, copies) over sampled texts, as for `lexicon`."""

    def distinct(batch: pa.RecordBatch) -> pa.RecordBatch:
        label, sign, out = [], [], []
        for text, y in zip(batch["text"].to_pylist(), batch["label"].to_pylist(), strict=True):
            ws = words(text)
            least = min(zlib.crc32(b" ".join(ws[i : i + 5])) for i in range(max(1, len(ws) - 4)))  # near copies mostly share it
            found = sorted({*ws, b""})  # the empty word stands for the document itself
            label += [y] * len(found)
            sign += [least] * len(found)
            out += found
        return pa.RecordBatch.from_arrays([pa.array(label, pa.int32()), pa.array(sign, pa.int64()), pa.array(out, pa.binary())], ["label", "sign", "word"])

    each = per_batch(some, distinct, "label int, sign long, word binary").groupBy("word", "label", "sign").agg(F.count("*").alias("rows"))
    one = lambda c: F.count(F.when(F.col("label") == c, 1))
    return each.groupBy("word").agg(one(1).alias("toxic"), one(0).alias("clean"), F.sum(F.when(F.col("label") == 1, F.col("rows")).otherwise(0)).alias("copies"))


def _prefix_features(counts: DataFrame, toxic: set[bytes]) -> list[bytes]:
    """Beginnings that several toxic words and hardly any other word share."""
    hot = Counter(f for w in toxic for f in features_of(w)[1:])
    spark = counts.sparkSession
    own = spark.createDataFrame([(bytearray(f),) for f, n in hot.items() if n >= SUPPORT], "name binary")
    mine = spark.createDataFrame([(bytearray(w),) for w in toxic], "word binary")
    named = F.explode(F.array_compact(F.array(*(F.when(F.length("word") >= n, F.concat(F.lit(b"%d" % n), F.substring("word", 1, n))) for n in PREFIXES))))
    other = counts.join(mine, "word", "left_anti").select(named.alias("name")).join(own, "name", "left_semi").groupBy("name").count().collect()  # as many as the toxic words' beginnings
    return pure({f: n for f, n in hot.items() if n >= SUPPORT}, {bytes(r.name): r["count"] for r in other})


def _context_features(some: DataFrame, toxic: set[bytes]) -> list[bytes]:
    """Neighbours that toxic words and hardly any other word have."""

    def beside(batch: pa.RecordBatch) -> pa.RecordBatch:
        hot, cold = Counter(), Counter()
        for text, y in zip(batch["text"].to_pylist(), batch["label"].to_pylist(), strict=True):
            for ws in sentences(text):
                for i, w in enumerate(ws):
                    (hot if y and w in toxic else cold).update(context_of(ws, i))
        names = sorted({*hot, *cold})
        return pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), *(pa.array([c[f] for f in names], pa.int64()) for c in (hot, cold))], ["name", "hot", "cold"])

    sums = per_batch(some, beside, "name binary, hot long, cold long").groupBy("name").agg(F.sum("hot").alias("hot"), F.sum("cold").alias("cold")).filter(F.col("hot") >= F.greatest(F.lit(SUPPORT), PURITY * (F.col("hot") + F.col("cold"))))
    return [bytes(r.name) for r in sums.collect()]


def _records(some: DataFrame, toxic: set[bytes], names: list[bytes]) -> list[Record]:
    """The different reduced sentences of the sampled texts."""
    index, plain = {f: i for i, f in enumerate(names)}, Tagger({f: 0.0 for f in names})

    def reduced(batch: pa.RecordBatch) -> pa.RecordBatch:
        found: Counter[str] = Counter()
        for text, y in zip(batch["text"].to_pylist(), batch["label"].to_pylist(), strict=True):
            for ws in sentences(text):
                marked = [(i, sorted(index[f] for f in (*features_of(ws[i]), *context_of(ws, i)) if f in index), int(y and ws[i] in toxic)) for i in plain.marked(ws)]
                found[json.dumps([len(ws), marked])] += 1
        return pa.RecordBatch.from_arrays([pa.array(found.keys(), pa.string()), pa.array(found.values(), pa.int64())], ["sentence", "n"])

    rows = per_batch(some, reduced, "sentence string, n long").groupBy("sentence").agg(F.sum("n").alias("n")).collect()
    return [(*json.loads(r.sentence), r.n) for r in sorted(rows)]  # sorted: the same sums each time


def train(docs: DataFrame, labels: DataFrame, rows: tuple[int, int] = TRAIN_ROWS) -> Tagger:
    """Counts words of the sampled texts for the lexicon, chooses features, and fits to all their sentences."""
    some = written(_sample(docs, labels, rows))
    counts = written(_word_counts(some))
    both, whole = (F.col("toxic") + F.col("clean")).alias("both"), counts.filter(F.length("word") == 0).first()
    if whole is None or not whole.toxic or not whole.clean:
        return Tagger()
    counts = counts.filter(F.length("word") > 0)
    as_frequent = {r.both: r["count"] for r in counts.groupBy(both).count().collect()}  # a row for each number of sampled documents at most
    able = counts.filter(F.col("toxic") >= F.greatest(F.lit(SUPPORT), PURITY * (F.col("toxic") + F.col("clean")), SPREAD * F.col("copies"))).collect()
    toxic = lexicon([(bytes(r.word), r.toxic, r.clean, r.copies) for r in able], as_frequent, whole.toxic / (whole.toxic + whole.clean))
    if not toxic:
        return Tagger()
    names = sorted([b"=" + w for w in toxic] + _prefix_features(counts, toxic) + _context_features(some, toxic))
    return fit(names, _records(some, toxic, names))


SPANS = "array<struct<start:long,end:long,chance:double>>"


def scores(docs: DataFrame, tagger: Tagger, cut: float = CUT) -> DataFrame:
    """(doc_id, score, predicted, spans) of every whole text; spans are the offending words, in characters of the text."""
    kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("chance", pa.float64())]))

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = [tagger.read(t) for t in batch["text"].to_pylist()]
        s = np.array([x for x, _ in found])
        spans = pa.array([[{"start": a, "end": b, "chance": p} for a, b, p in x] for _, x in found], kind)
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(s, pa.float64()), pa.array((s >= cut).astype(np.int32)), spans], ["doc_id", "score", "predicted", "spans"])

    return per_batch(id_and_text(docs), make, f"doc_id long, score double, predicted int, spans {SPANS}")


def span_rows(docs: DataFrame, tagger: Tagger) -> DataFrame:
    """(doc_id, start, end, chance): the offending spans, in characters of the text."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = [(d, *s) for d, t in zip(batch["doc_id"].to_pylist(), batch["text"].to_pylist(), strict=True) for s in tagger.spans(t)]
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.float64()]
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], ["doc_id", "start", "end", "chance"])

    return per_batch(id_and_text(docs), make, "doc_id long, start long, end long, chance double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    out = scores(docs, train(docs, read(spark, sf_dir, "labels")))
    return out.select("doc_id", held_out(FOLDS, HELD_OUT).alias("held_out"), "score", "predicted", "spans")
