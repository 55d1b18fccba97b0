"""Toxicity: a counterfactual-regularised classifier.

A logistic model over the presence of words and of word beginnings, fitted with an L1 penalty that leaves only words that matter and
with a penalty on (score before - score after)^2 of counterfactual pairs: sentences of the labelled texts in which one identity term
is swapped for each other of its kind, in four languages. A neutral mention of a group then moves the score little, however the
labels lean.

The vocabulary and weights come from a bounded sample of labelled rows: the ``max_rows`` smallest by hash of
the id. Words enter the vocabulary that at least ``min_docs`` rows of the sample hold and whose share of label 1 stands out by
``MIN_STRENGTH`` deviations, the ``max_features`` strongest of them; these are parameters of the fit. Everything else covers all data.

Defined cases: a null or empty text has no words and gets the intercept's score; ids without label, or with a
null one, don't train; an id labelled more than once trains with each label; with labels of one kind or none
the score is that share (0 without labels); other columns are never inputs of a score.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.llm.common import table
from winnow.plans.settle import settle

FOLDS = 5
MAX_ROWS = 20_000
MAX_FEATURES = 20_000
MIN_DOCS = 4
#: The fit: weight of the L1 penalty, weight of the counterfactual penalty, rounds at most.
L1, SWAP_PENALTY, ROUNDS = 1e-3, 1.0, 300
#: A feature enters the fit if its share of label 1 lies so many standard deviations from the sample's.
MIN_STRENGTH = 3.0
#: Beginnings of these lengths of longer words are features too.
STEMS = range(4, 10)

#: Terms that name groups of people, by kind and language. A swap stays within a line.
IDENTITY = (
    ("women", "men", "girls", "boys"),
    ("woman", "man", "girl", "boy"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("gay", "straight", "lesbian", "bisexual", "transgender", "queer"),
    ("black", "white", "asian", "latino", "african", "european"),
    ("immigrants", "refugees", "foreigners", "locals", "natives"),
    ("old", "young", "elderly"),
    ("deaf", "blind", "disabled"),
    ("femmes", "hommes", "filles", "garçons"),
    ("femme", "homme", "fille", "garçon"),
    ("musulmans", "chrétiens", "juifs", "hindous", "bouddhistes", "athées"),
    ("homosexuels", "hétérosexuels", "lesbiennes", "bisexuels"),
    ("noirs", "blancs", "arabes", "asiatiques", "africains", "européens"),
    ("immigrés", "réfugiés", "étrangers"),
    ("sourds", "aveugles", "handicapés"),
    ("frauen", "männer", "mädchen", "jungen"),
    ("frau", "mann"),
    ("muslime", "christen", "juden", "hindus", "buddhisten", "atheisten"),
    ("homosexuelle", "heterosexuelle", "lesben", "bisexuelle"),
    ("schwarze", "weiße", "araber", "asiaten", "afrikaner", "europäer"),
    ("einwanderer", "flüchtlinge", "ausländer", "einheimische"),
    ("gehörlose", "blinde", "behinderte"),
    ("mujeres", "hombres", "niñas", "niños"),
    ("mujer", "hombre", "niña", "niño"),
    ("musulmanes", "cristianos", "judíos", "hindúes", "budistas", "ateos"),
    ("homosexuales", "heterosexuales", "lesbianas", "bisexuales"),
    ("negros", "blancos", "árabes", "asiáticos", "africanos", "europeos"),
    ("inmigrantes", "refugiados", "extranjeros"),
    ("sordos", "ciegos", "discapacitados"),
)

_LETTERS = re.compile(r"[^\W\d_]+")
_ENDS = re.compile(r"[.!?\n]+")
_KIND: dict[str, tuple[str, ...]] = {}
for _line in IDENTITY:
    for _term in _line:
        _KIND[_term] = tuple(dict.fromkeys((*_KIND.get(_term, ()), *_line)))  # a term of two languages swaps within both lines


def words(text: str | None) -> set[str]:
    return set(_LETTERS.findall((text or "").lower()))


def features(word: str) -> list[str]:
    """The word, and its beginnings marked as such: a stem that goes on differs from the stem alone."""
    return [word, *(word[:k] + "+" for k in STEMS if k < len(word))]


def mentions(text: str | None) -> list[list[str]]:
    """The distinct sentences of a text that hold identity terms, as sorted words."""
    found = (words(x) for x in _ENDS.split(text or ""))
    return [list(x) for x in sorted({tuple(sorted(x)) for x in found if not x.isdisjoint(_KIND)})]


def swapped(found: set[str]) -> list[tuple[str, set[str]]]:
    """The counterfactuals of a sentence: for each identity term, every other term of its kind in its place."""
    return [(w, (found - {w}) | {t}) for w in sorted(found & _KIND.keys()) for t in _KIND[w] if t != w]


def differences(sentences: list[set[str]], at: dict[str, int]) -> Counter:
    """How often each difference of features occurs over all counterfactual pairs: ((feature, +1 or -1), ...) -> pairs.

    The score before less the score after depends on these features alone, so equal pairs are one row of the fit.
    """
    out: Counter = Counter()
    for s in sentences:
        times = Counter(f for w in s for f in features(w) if f in at)
        for w, after in swapped(s):
            new = {f for x in after - s for f in features(x) if f in at}
            gone = {f for f in features(w) if f in at and times[f] == 1}
            out[tuple(sorted([(at[f], 1) for f in gone - new] + [(at[f], -1) for f in new if not times[f]]))] += 1
    return out


@dataclass
class Model:
    bias: float
    weights: dict[str, float] = field(default_factory=dict)
    _known: dict[str, tuple] = field(default_factory=dict, repr=False)

    def score(self, found: set[str]) -> float:
        hits: set[str] = set()
        known = self._known
        for w in found:
            own = known.get(w)
            if own is None:
                if len(known) > 200_000:  # a memo of words seen lately, not of the corpus
                    known.clear()
                own = known[w] = tuple(f for f in features(w) if f in self.weights)
            if own:
                hits.update(own)
        z = self.bias + math.fsum(self.weights[f] for f in hits)
        return 1 / (1 + math.exp(-max(-35.0, min(35.0, z))))


def _soft(x: np.ndarray, by: float) -> np.ndarray:
    return np.sign(x) * np.maximum(np.abs(x) - by, 0)


def fit(
    examples: list[tuple[set[str], int]], vocabulary: list[str], sentences: list[set[str]] | None = None, l1: float = L1, swap_penalty: float = SWAP_PENALTY, rounds: int = ROUNDS
) -> Model:
    """Accelerated proximal gradient on mean log loss + swap_penalty * mean (score before - score after)^2 + l1 * |weights|.

    The mean is over all counterfactual pairs of ``sentences`` (by default the examples themselves), and scores are those
    before the logistic function. Classes count alike in the loss.
    """
    y = np.array([label for _, label in examples], float)
    if not len(y) or y.min() == y.max():
        share = float(y.mean()) if len(y) else 0.0
        return Model(math.log(share / (1 - share)) if 0 < share < 1 else 35.0 * (1 if share else -1))
    at = {w: i for i, w in enumerate(vocabulary)}

    def sparse(sets: list[set[str]]) -> tuple[np.ndarray, np.ndarray]:
        cols = [{at[f] for w in s for f in features(w) if f in at} for s in sets]
        return np.repeat(np.arange(len(cols)), [len(c) for c in cols]), np.array([i for c in cols for i in sorted(c)], int)

    row, col = sparse([s for s, _ in examples])
    swaps = differences([s for s, _ in examples] if sentences is None else sentences, at)
    swaps.pop((), None)  # pairs that no feature tells apart cost nothing
    d_row = np.repeat(np.arange(len(swaps)), [len(x) for x in swaps])
    d_col, d_sign = np.array([f for x in swaps for f in x], int).reshape(-1, 2).T
    share = np.array(list(swaps.values()), float) / max(1, sum(swaps.values()))
    n, k = len(y), len(vocabulary)
    weight = np.where(y == 1, 0.5 / y.sum(), 0.5 / (n - y.sum()))
    longest = max(1, np.bincount(row, minlength=n).max(initial=1))
    # words are scaled by how common they are, which keeps the step usable however long the texts
    scale = 1 / np.sqrt(np.maximum(1e-6, np.bincount(col, weight[row], k)) + 1e-3)
    # a term that no example holds keeps weight 0: swapped in, it draws the weight of the term it replaces towards 0
    seen = np.bincount(col, minlength=k) > 0
    w, b = np.zeros(k), 0.0
    look_w, look_b, momentum = w, b, 1.0
    step = 1.0

    def smooth(w: np.ndarray, b: float) -> tuple[float, np.ndarray, float]:
        v = w * scale
        z = b + np.bincount(row, v[col], n)
        loss = float(weight @ (np.logaddexp(0, z) - y * z))
        g = weight * (1 / (1 + np.exp(-z)) - y)
        grad = np.bincount(col, g[row], k)
        if len(d_col):
            d = np.bincount(d_row, v[d_col] * d_sign, len(share))
            loss += swap_penalty * float(share @ (d * d))
            grad = grad + np.bincount(d_col, 2 * swap_penalty * (share * d)[d_row] * d_sign, k)
        return loss, grad * scale, float(g.sum())

    for _ in range(rounds):
        loss, grad, grad_b = smooth(look_w, look_b)
        while True:
            new_w, new_b = _soft(look_w - step * grad, step * l1) * seen, look_b - step * grad_b
            dw, db = new_w - look_w, new_b - look_b
            if smooth(new_w, new_b)[0] <= loss + grad @ dw + grad_b * db + (dw @ dw + db * db) / (2 * step) + 1e-12 or step < 1e-9 / longest:
                break
            step /= 2
        nxt = (1 + math.sqrt(1 + 4 * momentum**2)) / 2
        look_w, look_b = new_w + (momentum - 1) / nxt * (new_w - w), new_b + (momentum - 1) / nxt * (new_b - b)
        moved = float(np.abs(new_w - w).max(initial=0)) + abs(new_b - b)
        w, b, momentum = new_w, new_b, nxt
        step *= 1.1
        if moved < 1e-5:
            break
    v = w * scale
    return Model(b, {vocabulary[i]: float(v[i]) for i in np.flatnonzero(v)})


_ROWS = "label int, words array<string>, mentions array<array<string>>"


def training_rows(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> DataFrame:
    """(label, words, mentions) of the bounded sample; rows of the held-out fold are never read."""
    fold = F.pmod(F.crc32(F.col("_tx_id").cast("string").cast("binary")), F.lit(FOLDS))
    chosen = (
        labels.select(F.col(id_col).cast("long").alias("_tx_id"), F.col(label_col).cast("int").alias("label"))
        .where(F.col("_tx_id").isNotNull() & F.col("label").isin(0, 1) & (fold != 0))
        .orderBy(F.xxhash64("_tx_id"), "_tx_id", "label")
        .limit(max_rows)  # the sample's documented bound, which also bounds the broadcast
    )
    joined = docs.select(F.col(id_col).cast("long").alias("_tx_id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(chosen), "_tx_id")

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(1).to_pylist()
            found = pa.array([sorted(words(x)) for x in texts], pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([b.column(0), found, pa.array([mentions(x) for x in texts], pa.list_(pa.list_(pa.string())))], names=["label", "words", "mentions"])

    return joined.select("label", "text").mapInArrow(of, _ROWS)


def train(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS, max_features: int = MAX_FEATURES, min_docs: int = MIN_DOCS, swap_penalty: float = SWAP_PENALTY, **cols) -> Model:
    """Fits on the sample. The driver gets at most ``max_rows`` rows of words that bear one of ``max_features`` features."""
    rows = settle(training_rows(docs, labels, max_rows, **cols).dropDuplicates(["label", "words", "mentions"]))
    total = rows.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("label"), F.lit(0)).alias("n1")).first()

    def counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n: Counter = Counter()
            n1: Counter = Counter()
            for label, found in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                have = {f for w in found for f in features(w)}
                n.update(have)
                if label:
                    n1.update(have)
            yield pa.RecordBatch.from_arrays(
                [pa.array(list(n), pa.string()), pa.array(list(n.values()), pa.int64()), pa.array([n1[f] for f in n], pa.int64())], names=["f", "n", "n1"]
            )

    counted = rows.select("label", "words").mapInArrow(counts, "f string, n long, n1 long").groupBy("f").agg(F.sum("n").alias("n"), F.sum("n1").alias("n1"))
    p = F.lit((total["n1"] + 0.5) / (total["n"] + 1.0))
    strength = F.abs(F.col("n1") - F.col("n") * p) / F.sqrt(F.col("n") * p * (1 - p))
    strong = counted.where((F.col("n") >= min_docs) & (strength >= MIN_STRENGTH)).orderBy(strength.desc(), "f").limit(max_features)
    vocabulary = sorted({r["f"] for r in strong.select("f").collect()} | set(_KIND))
    known = frozenset(vocabulary)

    def bearing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Leaves out words that bear no feature of the vocabulary."""
        bears: dict[str, bool] = {}

        def some(found: list[str]) -> list[str]:
            for w in found:
                if w not in bears:
                    bears[w] = any(f in known for f in features(w))
            return [w for w in found if bears[w]]

        for b in batches:
            few = pa.array([some(x) for x in b.column(1).to_pylist()], pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([b.column(0), few, pa.array([[some(x) for x in s] for s in b.column(2).to_pylist()], pa.list_(pa.list_(pa.string())))], names=["label", "words", "mentions"])

    sample = rows.mapInArrow(bearing, _ROWS).collect()
    examples = sorted(((set(r["words"]), r["label"]) for r in sample), key=lambda x: (x[1], sorted(x[0])))
    return fit(examples, vocabulary, [set(s) for r in sample for s in r["mentions"]], swap_penalty=swap_penalty)


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` plus score and predicted; a column of either name is replaced."""

    @F.pandas_udf("double")
    def scored(text):
        return text.map(lambda x: model.score(words(x))).astype(float)

    out = docs.withColumn("score", scored(F.coalesce(F.col(text_col).cast("string"), F.lit(""))))
    return out.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def clean(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with its columns, without the rows that the model rejects."""
    model = train(docs, labels, id_col=id_col, text_col=text_col)
    kept = score(docs.select(*[F.col(c).alias(f"_tx_{c}") for c in docs.columns]), model, f"_tx_{id_col}", f"_tx_{text_col}").where("predicted = 0")
    return kept.select(*[F.col(f"_tx_{c}").alias(c) for c in docs.columns])


def held_out(doc_id: int | None) -> bool:
    """Whether a row of this id is kept from training."""
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % FOLDS == 0


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, table(spark, sf_dir, "labels"))
    fold = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(FOLDS)) == 0
    return score(docs, model).select("doc_id", F.coalesce(fold, F.lit(False)).alias("held_out"), "score", "predicted")
