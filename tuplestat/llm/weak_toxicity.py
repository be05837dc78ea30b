"""Toxicity by weak supervision.

Voters: lexicons of insults by category; lexicons of words (by length) and pattern voters of word
beginnings (of three to six letters) that a development set, the labelled training rows, shows to
be toxic far more often than chance, also by tiers of that evidence; patterns of writing (capitals,
exclamation marks, digits, several hits); and voters for clean that vote when nothing listed
occurs. Languages whose insults no public list names have their lexicons from the development set
only. Each vote is toxic, clean or an abstention.

A generative label model then learns from the votes alone how often each voter is right (an EM
over the hidden class with three-way votes) and which voters repeat each other: the votes'
correlation given the class discounts a voter's evidence by the number of voters it agrees
with. It is given the class balance and no label. Its posterior probabilities are the targets of a
linear classifier on the listed words and beginnings, which generalises over them; a two-parameter
scaling on the training labels turns its margin into a probability at the training rows' share of
toxic texts. So labels choose patterns, balance and scale, and never a row's target.

The fit takes a bounded sample, `fit_rows` labelled rows at most per class by a keyed hash of the
id. Its texts stay on the executors: feature counts, at most `most` chosen features and each row's
list of them come to the driver. Scoring covers all rows in one scan without a shuffle.

Nulls are empty texts, which get the score of a text without evidence; rows with a null id are
scored and never train; repeated rows each give a row; labels with null or other values are
ignored; without any usable label of one class every score is the known share (0 if none).
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .linear import fit_logistic, fit_sparse_logistic, sigmoid
from .shared import batch_of, bounded_batches, discard, held, least_hashed, slices, staged, thrifty

WORD = re.compile(r"[^\W_]+")
BEGINNINGS = (3, 4, 5, 6)
CACHE_WORDS = 120_000

#: Common insults by category, a voter each.
INSULTS = {
    "mind": "idiot idiots moron morons stupid dumb fool imbecile clown",
    "worth": "loser losers pathetic worthless trash scum vermin filth",
    "disgust": "disgusting ugly jerk",
}
CATEGORY = {w: f"#{name}" for name, words in INSULTS.items() for w in words.split()}


def features_of(word: str) -> list[str]:
    """A word, its proper beginnings (marked by a star), and its category if it is a listed insult."""
    listed = CATEGORY.get(word)
    return [word] + [word[:k] + "*" for k in BEGINNINGS if len(word) > k] + ([listed] if listed else [])


def words_of(text: str) -> set[str]:
    return set(WORD.findall(text.lower()))


def count_features(texts: list[str], y: list[int]) -> list[tuple[str, int, int]]:
    """(feature, toxic rows, other rows) of a batch."""
    counts = Counter(), Counter()
    for t, label in zip(texts, y):
        counts[label].update({f for w in words_of(t) for f in features_of(w)})
    return [(f, counts[1][f], counts[0][f]) for f in counts[0].keys() | counts[1].keys()]


def select_features(counts: DataFrame, n1: int, n0: int, most: int) -> dict[str, int]:
    """Features far more frequent in toxic rows, best first: in three of them at least, with log-odds
    of two or more at four standard errors."""
    p, n = F.col("p"), F.col("n")
    odds = F.log((p + 0.5) / (F.lit(n1) - p + 0.5)) - F.log((n + 0.5) / (F.lit(n0) - n + 0.5))
    error = F.sqrt(1 / (p + 0.5) + 1 / (n + 0.5))
    ranked = counts.groupBy("f").agg(F.sum("p").alias("p"), F.sum("n").alias("n")).where("p >= 3")
    ranked = ranked.withColumn("z", odds / error).where((odds >= 2) & ((F.col("z") >= 4) | ((n == 0) & (p >= 5))))
    return {r.f: i for i, r in enumerate(ranked.orderBy(F.desc("z"), "f").limit(most).select("f").collect())}


@dataclass
class Model:
    features: dict[str, int] = field(default_factory=dict)
    weights: np.ndarray = field(default_factory=lambda: np.zeros(1))
    scale: tuple[float, float] = (1.0, 0.0)
    prior: float = 0.0
    voters: list[str] = field(default_factory=list)
    accuracy: np.ndarray = field(default_factory=lambda: np.zeros(0))
    discount: np.ndarray = field(default_factory=lambda: np.zeros(0))


class Table(dict):
    """Word -> its listed features' numbers; cleared when it is full."""

    def __init__(self, features: dict[str, int]):
        super().__init__()
        self.features = features

    def __missing__(self, word: str) -> tuple[int, ...]:
        if len(self) >= CACHE_WORDS:
            self.clear()
        get = self.features.get
        found = tuple(k for k in map(get, features_of(word)) if k is not None)
        self[word] = found
        return found


def rows_of(texts: list[str], table: Table) -> list[np.ndarray]:
    """Numbers of the listed features that occur in each text."""
    get = table.__getitem__
    out = []
    for text in texts:
        hit = set()
        for found in map(get, words_of(text)):
            if found:
                hit.update(found)
        out.append(np.fromiter(hit, dtype=np.int64, count=len(hit)))
    return out


def shape_votes(text: str) -> tuple[int, int, int]:
    """Votes of the patterns of writing: capitals, exclamation marks, digits."""
    n = max(len(text), 1)
    return (
        int(sum(map(str.isupper, text)) > 0.5 * n),
        int(text.count("!") > 0.02 * n),
        -int(sum(map(str.isdigit, text)) > 0.1 * n),
    )


#: Voters over all listed features, by name; each sees another side of a row's hits.
LENGTHS = ((1, 5), (6, 8), (9, 10_000))
TIERS = 4


def voters(features: dict[str, int]) -> tuple[list[str], np.ndarray]:
    """The names of the lexicon and beginning voters, and which of them each feature belongs to
    (features x voters): its category, the length of its beginning or word, its tier by rank. A
    voter spans languages, since voters of one language each would look like classes of their own."""
    names = [f"insult_{c}" for c in INSULTS] + [f"begins_{k}" for k in BEGINNINGS]
    names += [f"words_{lo}_{hi}" for lo, hi in LENGTHS] + [f"tier_{t}" for t in range(TIERS)]
    member = np.zeros((max(len(features), 1), len(names)), dtype=bool)
    for f, i in features.items():
        if f.startswith("#"):
            member[i, names.index(f"insult_{f[1:]}")] = True
            continue
        if f.endswith("*"):
            member[i, names.index(f"begins_{len(f) - 1}")] = True
        else:
            member[i, names.index(next(f"words_{lo}_{hi}" for lo, hi in LENGTHS if lo <= len(f) <= hi))] = True
        member[i, names.index(f"tier_{i * TIERS // len(features)}")] = True
    return names, member


def votes_of(rows: list[np.ndarray], shapes: list, features: dict[str, int]) -> tuple[np.ndarray, list[str]]:
    """Votes (1 toxic, -1 clean, 0 none), rows x voters, and the voters' names."""
    names, member = voters(features)
    begins = member[:, len(INSULTS) : len(INSULTS) + len(BEGINNINGS)].any(axis=1)
    votes = np.zeros((len(rows), len(names) + 8), dtype=np.int8)
    for i, (hit, shape) in enumerate(zip(rows, shapes)):
        stems = int(begins[hit].sum()) if len(hit) else 0
        if len(hit):
            votes[i, : len(names)] = member[hit].any(axis=0)
        votes[i, -8:] = (len(hit) >= 3, len(hit) >= 6, -(len(hit) == stems), -(stems == 0), -(len(hit) == 0), *shape)
    return votes, [*names, "three_hits", "six_hits", "no_word", "no_beginning", "no_hit", "capitals", "exclamations", "digits"]


def label_model(votes: np.ndarray, balance: float = 0.5, rounds: int = 50) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Posterior of toxic for each row, accuracy of each voter's non-abstentions, and the
    discount of each voter's evidence for what it repeats of others. Labels are not used.

    The class balance is given; voters start better than chance, and the first posterior has the
    balance too: the rows with the most votes for toxic are its toxic ones. Correlations are those
    of the votes around their class means under the current posterior.
    """
    n, k = votes.shape
    hot = np.stack([votes == v for v in (-1, 0, 1)], axis=2).astype(float)
    total = votes.sum(axis=1) / np.sqrt(k)
    p = sigmoid(4.0 * (total - np.quantile(total, 1 - balance)))
    discount = np.ones(k)
    for _ in range(rounds):
        both = np.stack([1 - p, p], axis=1)
        mass = both.sum(axis=0)
        table = (np.einsum("nc,nkv->ckv", both, hot) + 0.1) / (mass[:, None, None] + 0.3)
        mean = np.einsum("nc,nk->ck", both, votes.astype(float)) / np.maximum(mass[:, None], 1e-9)
        residual = votes - both @ mean
        spread = residual.std(axis=0)
        live = spread > 1e-9
        corr = np.zeros((k, k))
        if live.any():
            r = residual[:, live] / spread[live]
            corr[np.ix_(live, live)] = (r.T @ r) / n
        np.fill_diagonal(corr, 0.0)
        discount = 1.0 / (1.0 + np.clip(corr, 0, 1).sum(axis=1))
        evidence = np.log(table[1]) - np.log(table[0])
        share = np.clip(balance, 0.01, 0.99)
        margin = np.log(share / (1 - share)) + (np.einsum("nkv,kv->nk", hot, evidence) * discount).sum(axis=1)
        new = sigmoid(margin)
        if np.abs(new - p).max() < 1e-6:
            p = new
            break
        p = new
    right = np.where(votes == 1, p[:, None], np.where(votes == -1, 1 - p[:, None], 0.0)).sum(axis=0)
    cast = (votes != 0).sum(axis=0)
    return p, np.where(cast > 0, right / np.maximum(cast, 1), 0.5), discount


def margins(rows: list[np.ndarray], weights: np.ndarray) -> np.ndarray:
    return np.array([weights[r].sum() for r in rows]) + weights[-1]


def fit(rows: list[np.ndarray], shapes: list, labels: np.ndarray, features: dict[str, int], prior: float) -> Model:
    """Label model, classifier and scale from rows of feature numbers; `prior` is the share of
    toxic rows that scores should have."""
    y = labels.astype(np.int64)
    votes, names = votes_of(rows, shapes, features)
    posterior, accuracy, discount = label_model(votes, float(y.mean()))
    weights = fit_sparse_logistic(rows, posterior, len(features))
    weight = np.where(y == 1, prior / y.mean(), (1 - prior) / (1 - y.mean()))
    scale = fit_logistic(margins(rows, weights)[:, None], y.astype(float), weight, l2=1e-5)
    return Model(features, weights, (float(scale[0]), float(scale[1])), float(prior), names, accuracy, discount)


def scores(texts: list[str], model: Model, table: Table) -> np.ndarray:
    if not model.features:
        return np.full(len(texts), model.prior)
    a, b = model.scale
    return sigmoid(a * margins(rows_of(texts, table), model.weights) + b)


# ------------------------------------------------------------------ on Spark


def held_out_by_crc(id_column: Column, modulus: int = 4, fold: int = 2) -> Column:
    return F.coalesce(F.crc32(id_column.cast("string")) % modulus == fold, F.lit(False))


def fit_model(
    docs: DataFrame,
    labels: DataFrame,
    fit_rows: int = 3000,
    id_col: str = "doc_id",
    text_col: str = "text",
    label_col: str = "toxic",
    most: int = 20_000,
) -> Model:
    """Fit on at most `fit_rows` training rows of each class and `most` features."""
    usable = (
        labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("y"))
        .where(F.col("doc_id").isNotNull() & F.col("y").isin(0, 1) & ~held_out_by_crc(F.col("doc_id")))
    )
    share = usable.agg(F.avg("y").alias("p")).first().p
    picked = None
    for y in (0, 1):
        one = least_hashed(usable.where(F.col("y") == y), fit_rows, "doc_id")
        picked = one if picked is None else picked.union(one)
    ids = picked.dropDuplicates(["doc_id"])
    bounded_batches(docs.sparkSession)
    sample = staged(
        docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
        .join(F.broadcast(ids), "doc_id")  # 2 * fit_rows short rows at most
        .dropDuplicates(["doc_id"]),
        "fit",
    )
    n = {r.y: r.n for r in sample.groupBy("y").agg(F.count("*").alias("n")).collect()}
    if len(n) < 2:
        discard(sample)
        return Model(prior=float(share or 0.0))

    def counted(batches):
        schema = pa.schema([("f", pa.string()), ("p", pa.int64()), ("n", pa.int64())])
        for part in slices(batches, 1 << 20):
            found = count_features([t or "" for t in part.column(0).to_pylist()], part.column(1).to_pylist())
            if found:
                yield batch_of(schema, *zip(*found))

    features = select_features(sample.select("text", "y").mapInArrow(counted, "f string, p long, n long"), n[1], n[0], most)
    shipped = docs.sparkSession.sparkContext.broadcast(features)

    def listed(batches):
        schema = pa.schema([("doc_id", pa.int64()), ("y", pa.int32()), ("hit", pa.list_(pa.int32())), ("shape", pa.list_(pa.int32()))])
        table = Table(shipped.value)
        for part in slices(batches, 1 << 20):
            texts = [t or "" for t in part.column(1).to_pylist()]
            hits = [np.sort(r).tolist() for r in rows_of(texts, table)]
            yield batch_of(schema, part.column(0), part.column(2), hits, [list(shape_votes(t)) for t in texts])

    # 2 * fit_rows rows of at most a few hundred numbers.
    rows = sample.select("doc_id", "text", "y").mapInArrow(listed, "doc_id long, y int, hit array<int>, shape array<int>").collect()
    discard(sample)
    rows.sort(key=lambda r: r.doc_id)
    return fit(
        [np.array(r.hit, dtype=np.int64) for r in rows],
        [tuple(r["shape"]) for r in rows],
        np.array([r.y for r in rows], dtype=np.int64),
        features,
        float(share),
    )


def _table(model: Model) -> Table:
    key = hash((len(model.features), model.weights.tobytes()))
    return held(("toxicity", key), lambda: Table(model.features))


def toxicity(
    docs: DataFrame, model: Model, threshold: float = 0.3, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of `docs`."""
    bounded_batches(docs.sparkSession)
    shipped = docs.sparkSession.sparkContext.broadcast(model)
    schema = pa.schema(
        [("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())]
    )

    def run(batches):
        m = shipped.value
        table = _table(m)
        for part in slices(batches):
            s = scores([t or "" for t in part.column(2).to_pylist()], m, table)
            yield batch_of(schema, part.column(0), part.column(1), s, (s >= threshold).astype(np.int32))

    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        held_out_by_crc(F.col(id_col)).alias("held_out"),
        F.col(text_col).cast("string").alias("text"),
    )
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def score_column(text: Column, model: Model, spark) -> Column:
    """The score as a column, for filters that keep a table's other columns."""
    bounded_batches(spark)
    shipped = spark.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def score(column: pa.Array) -> pa.Array:
        m = shipped.value
        thrifty()
        return pa.array(scores([t or "" for t in column.to_pylist()], m, _table(m)), pa.float64())

    return score(text)
