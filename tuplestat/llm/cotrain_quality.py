"""Quality scores by co-training two separate views of a document.

The text view sees the text and nothing else: shares and shapes of its characters, words and lines.
The page view sees what is recorded about it and nothing of its text: source, language and declared
length. Each view has a logistic classifier. In every round, each classifier offers the unlabelled
rows it is most sure of (by its margin calibrated on labelled rows that it did not train on), per
class in the classes' proportion, for the other one to train on. Offers come from all unlabelled
rows: a scan of their staged features keeps the surest of each task, and a distributed top-k the
surest of all. A row has its pseudo-label from one view only and is never relabelled, and a view
takes an offer only where it does not raise its loss on the labelled rows that calibrate it. After
the last round a logistic combination of the two calibrated margins, fitted on labelled rows of its
own and holding a share of both views, scores all documents.

Labelled rows are a bounded sample by a keyed hash of the id (`fit_rows`), dealt in four: two parts
train, one calibrates and guards, one combines. Texts are scanned once and never shuffled: what is
kept, joined with labels and scanned in every round are a few numbers a row.

Null columns count as empty text, "" or zero; rows with a null id are scored and never train;
repeated rows each give a row; labels other than 0 and 1 are ignored; without labels of both
classes every score is the known share (1 if there is none). An empty table gives no rows.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .linear import fit_logistic, sigmoid
from .shared import batch_of, bounded_batches, discard, is_space, least_hashed, slices, staged, text_bytes, word_hashes, word_spans

HASHED = 24  # slots for source and for language
TEXT_VIEW, PAGE_VIEW = 12, 2 + 2 * HASHED
SALTS = 64  # tasks that share a top-k before its last step


def _per_row(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0.0], np.cumsum(values, dtype=np.float64)])
    return total[offsets[1:]] - total[offsets[:-1]]


def distinct_share(h: np.ndarray, row: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(items, distinct items) of each row."""
    items = np.bincount(row, minlength=n).astype(float)
    order = np.lexsort((h, row))
    h, row = h[order], row[order]
    new = np.ones(len(h), dtype=bool)
    new[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
    return items, np.bincount(row[new], minlength=n).astype(float)


def text_features(texts: pa.Array) -> np.ndarray:
    """The text view of a batch, a row each; all passes are over whole arrays."""
    raw, offsets = text_bytes(texts)
    n = len(offsets) - 1
    size = np.maximum(np.diff(offsets), 1).astype(float)
    starts, ends, row = word_spans(raw, offsets)
    words, distinct = distinct_share(word_hashes(raw, starts, ends), row, n)
    some = np.maximum(words, 1)
    width = (ends - starts).astype(float)
    longest = np.zeros(n)
    np.maximum.at(longest, row, width)
    is_digit = (raw >= 48) & (raw <= 57)
    is_upper = (raw >= 65) & (raw <= 90)
    is_lower = (raw >= 97) & (raw <= 122)
    is_mark = (raw < 128) & ~is_digit & ~is_upper & ~is_lower & ~is_space(raw) if len(raw) else np.zeros(0, bool)
    # Lines: cut at line feeds and at rows' ends; a line's hash is that of all its bytes.
    feed = raw == 10
    cuts = np.unique(np.concatenate([np.flatnonzero(feed), offsets[1:]]))
    begin = np.concatenate([[0], cuts[:-1] + (feed[np.minimum(cuts[:-1], max(len(raw) - 1, 0))] if len(raw) else 0)])
    keep = begin < cuts
    begin, cuts = begin[keep].astype(np.int64), cuts[keep].astype(np.int64)
    line_row = np.searchsorted(offsets, begin, side="right") - 1
    lines, distinct_lines = distinct_share(word_hashes(raw, begin, cuts), line_row, n)
    some_lines = np.maximum(lines, 1)
    mean_width = _per_row(width, np.concatenate([[0], np.cumsum(words)]).astype(int)) / some
    return np.stack(
        [
            np.log1p(words),
            distinct / some,
            _per_row(is_mark, offsets) / size,
            _per_row(is_digit, offsets) / size,
            _per_row(is_upper, offsets) / size,
            _per_row(raw >= 128, offsets) / size,
            mean_width,
            np.log1p(longest),
            1 - distinct_lines / some_lines,
            (distinct / some) ** 2,
            np.log1p(words) * distinct / some,
            (words == 0).astype(float),
        ],
        axis=1,
    )


@dataclass
class View:
    centre: np.ndarray
    spread: np.ndarray
    beta: np.ndarray
    scale: tuple[float, float] = (1.0, 0.0)

    @classmethod
    def fit(cls, x: np.ndarray, y: np.ndarray) -> "View":
        centre, spread = x.mean(axis=0), x.std(axis=0)
        spread = np.where(spread > 1e-9, spread, 1.0)
        return cls(centre, spread, fit_logistic((x - centre) / spread, y, l2=1e-3))

    def margin(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.centre) / self.spread, -8, 8)
        return z @ self.beta[:-1] + self.beta[-1]

    def calibrate(self, x: np.ndarray, y: np.ndarray) -> None:
        a, b = fit_logistic(self.margin(x)[:, None], y, l2=1e-4)
        self.scale = float(a), float(b)

    def calibrated(self, x: np.ndarray) -> np.ndarray:
        return self.scale[0] * self.margin(x) + self.scale[1]


@dataclass
class Model:
    text: View | None
    page: View | None
    mix: np.ndarray
    prior: float
    exchanged: list[tuple[int, int]]

    def score(self, text: np.ndarray, page: np.ndarray) -> np.ndarray:
        if self.text is None:
            return np.full(len(text), self.prior)
        both = np.stack([self.text.calibrated(text), self.page.calibrated(page)], axis=1)
        return sigmoid(both @ self.mix[:-1] + self.mix[-1])


def parts_of(y: np.ndarray) -> list[np.ndarray]:
    """Rows that train, calibrate and combine: half, a quarter and a quarter, or all of them for each
    where that would leave a part without one of the classes."""
    at = np.arange(len(y)) % 4
    parts = [at < 2, at == 2, at == 3]
    if any(len(np.unique(y[p])) < 2 for p in parts):
        return [np.ones(len(y), dtype=bool)] * 3
    return parts


def combination(both: np.ndarray, y: np.ndarray, least: float = 0.1) -> np.ndarray:
    """Logistic weights of the two margins, neither below `least` of the other, and an intercept."""
    mix = fit_logistic(both, y, l2=1e-3)
    weights = np.maximum(mix[:-1], max(least * mix[:-1].max(), 1e-3))
    scale = fit_logistic((both @ weights)[:, None], y, l2=1e-3)
    return np.concatenate([weights * max(scale[0], 1e-3), scale[1:]])


def cotrain(labelled: tuple[np.ndarray, np.ndarray, np.ndarray], offers, rounds: int = 5, tolerance: float = 1e-3) -> Model:
    """The exchange: labelled (text, page, y); `offers(views, share)` gives, for each view, the rows it
    is sure of as (text, page, labels), none of them twice."""
    xt, xp, y = labelled
    if len(y) < 8 or y.min() == y.max():
        return Model(None, None, np.zeros(3), float(y.mean()) if len(y) else 1.0, [])
    train, guard, last = parts_of(y)
    own = (xt, xp)
    given = [(np.zeros((0, x.shape[1])), np.zeros(0)) for x in own]

    def refit(k: int, rows: np.ndarray, labels: np.ndarray) -> tuple[View, float]:
        """View k on its labelled rows and what it was given; its loss on the rows that calibrate it."""
        view = View.fit(np.concatenate([own[k][train], rows]), np.concatenate([y[train], labels]).astype(float))
        view.calibrate(own[k][guard], y[guard].astype(float))
        m = view.calibrated(own[k][guard])
        return view, float((np.logaddexp(0, m) - y[guard] * m).mean())

    views, losses = map(list, zip(*(refit(k, *given[k]) for k in range(2))))
    exchanged = []
    for _ in range(rounds):
        offered = offers(views, float(y[train].mean()))
        moved = [0, 0]
        for k in range(2):
            rows, labels = offered[1 - k][k], offered[1 - k][2]
            if not len(labels):
                continue
            more = np.concatenate([given[k][0], rows]), np.concatenate([given[k][1], labels])
            view, loss = refit(k, *more)
            if loss <= losses[k] + tolerance:  # else this offer taught it noise
                given[k], views[k], losses[k], moved[1 - k] = more, view, loss, len(labels)
        exchanged.append(tuple(moved))
        if not any(len(o[2]) for o in offered):
            break
    both = np.stack([views[0].calibrated(xt[last]), views[1].calibrated(xp[last])], axis=1)
    return Model(views[0], views[1], combination(both, y[last].astype(float)), float(y.mean()), exchanged)


def class_rows(most: int, share: float) -> tuple[int, int]:
    """Rows of class 0 and 1 in an offer of `most`, in the classes' proportion, one at least."""
    return max(1, round(most * (1 - share))), max(1, round(most * share))


def pool_offers(text: np.ndarray, page: np.ndarray, most: int, least_sure: float):
    """Offers from arrays: the whole pool is looked at in every round."""
    free = np.ones(len(text), dtype=bool)

    def offers(views: list[View], share: float) -> list:
        out = []
        for view, x in zip(views, (text, page)):
            p = sigmoid(view.calibrated(x))
            rows, labels = [], []
            for value, k in enumerate(class_rows(most, share)):
                sure = np.where(free, p if value else 1 - p, -1.0)
                best = np.argsort(-sure, kind="stable")[:k]
                best = best[sure[best] >= least_sure]
                free[best] = False
                rows, labels = rows + best.tolist(), labels + [float(value)] * len(best)
            out.append((text[rows], page[rows], np.array(labels)))
        return out

    return offers


# ------------------------------------------------------------------ on Spark

FEATURES = "doc_id long, text array<float>, source int, lang int, declared float"
_SCHEMA = pa.schema(
    [("doc_id", pa.int64()), ("text", pa.list_(pa.float32())), ("source", pa.int32()), ("lang", pa.int32()), ("declared", pa.float32())]
)


def feature_rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """FEATURES of every row: the text view's numbers, and the page view's slots and declared length."""
    bounded_batches(docs.sparkSession)

    def col(name, kind):
        return F.col(name).cast(kind) if name in docs.columns else F.lit(None).cast(kind)

    def run(batches):
        for part in slices(batches, 1 << 20):
            slot = [[zlib.crc32((v or "").encode()) % HASHED for v in part.column(k).to_pylist()] for k in (2, 3)]
            declared = [max(float(v or 0), 0.0) for v in part.column(4).to_pylist()]
            yield batch_of(_SCHEMA, part.column(0), list(text_features(part.column(1)).astype(np.float32)), *slot, declared)

    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.col(text_col).cast("string").alias("text"),
        col("source", "string").alias("source"),
        col("lang", "string").alias("lang"),
        col("n_chars", "double").alias("n_chars"),
    )
    return rows.mapInArrow(run, FEATURES)


def views_of(text: pa.Array, source, lang, declared) -> tuple[np.ndarray, np.ndarray]:
    """Both views as matrices, from columns of FEATURES."""
    n = len(text)
    x = text.flatten().to_numpy(zero_copy_only=False).reshape(n, -1).astype(float) if n else np.zeros((0, TEXT_VIEW))
    page = np.zeros((n, PAGE_VIEW))
    length = np.log1p(np.asarray(declared, dtype=float))
    page[:, 0], page[:, 1] = length, length**2
    page[np.arange(n), 2 + np.asarray(source)] = 1
    page[np.arange(n), 2 + HASHED + np.asarray(lang)] = 1
    return x, page


def collected(rows: DataFrame) -> tuple:
    """(table, text view, page view) of a bounded number of feature rows, on the driver."""
    t = rows.toArrow()
    return t, *views_of(t.column("text").combine_chunks(), *(t.column(c).to_numpy() for c in ("source", "lang", "declared")))


def corpus_offers(unlabelled: DataFrame, most: int, least_sure: float):
    """Offers from all rows of `unlabelled` (FEATURES with an id): each task keeps its surest rows, then
    the surest of all are picked in two steps, so that no task gets more than SALTS times `most`."""
    taken: set[int] = set()
    schema = pa.schema([("view", pa.int32()), ("label", pa.int32()), ("sure", pa.float64()), *_SCHEMA])
    spark = unlabelled.sparkSession

    def offers(views: list[View], share: float) -> list:
        shipped = spark.sparkContext.broadcast((list(views), np.array(sorted(taken), dtype=np.int64)))
        wanted = class_rows(most, share)

        def run(batches):
            now, done = shipped.value
            kept: dict[tuple[int, int], pa.Table] = {}
            for part in slices(batches, 4 << 20):
                sides = views_of(part.column(1), *(part.column(k).to_numpy() for k in (2, 3, 4)))
                ids = part.column(0).to_numpy()
                free = ~np.isin(ids, done)
                for v, view in enumerate(now):
                    p = sigmoid(view.calibrated(sides[v]))
                    for label, k in enumerate(wanted):
                        sure = np.where(free, p if label else 1 - p, -1.0)
                        at = np.flatnonzero(sure >= least_sure)
                        at = at[np.lexsort((ids[at], -sure[at]))[:k]]
                        if not len(at):
                            continue
                        head = [pa.array(np.full(len(at), c), t) for c, t in ((v, pa.int32()), (label, pa.int32()))]
                        new = pa.Table.from_arrays([*head, pa.array(sure[at]), *(c.take(pa.array(at)) for c in part.columns)], schema=schema)
                        old = kept.get((v, label))
                        both = new if old is None else pa.concat_tables([old, new])
                        kept[v, label] = both.sort_by([("sure", "descending"), ("doc_id", "ascending")]).slice(0, k).combine_chunks()
            for table in kept.values():
                yield from table.to_batches()

        found = unlabelled.mapInArrow(run, "view int, label int, sure double, " + FEATURES)
        rank = lambda *by: F.row_number().over(Window.partitionBy("view", "label", *by).orderBy(F.desc("sure"), "doc_id"))
        fits = F.col("rank") <= F.element_at(F.array(*map(F.lit, wanted)), F.col("label") + 1)
        salted = found.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)))
        few = salted.withColumn("rank", rank("salt")).where(fits).drop("rank", "salt")
        table, text, page = collected(few.withColumn("rank", rank()).where(fits).orderBy("view", "label", F.desc("sure"), "doc_id"))
        view, label, ids = (table.column(c).to_numpy() for c in ("view", "label", "doc_id"))
        out = []
        for v in range(2):  # a row that both views offer goes with the first
            mine = np.array([w == v and i not in taken for w, i in zip(view, ids.tolist())], dtype=bool)
            taken.update(ids[mine].tolist())
            out.append((text[mine], page[mine], label[mine].astype(float)))
        return out

    return offers


def fit_features(rows: DataFrame, labels: DataFrame, fit_rows: int, per_round: int, rounds: int, least_sure: float, id_col: str, label_col: str) -> Model:
    """The model from feature rows of all documents."""
    known = labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("y")).where(
        F.col("doc_id").isNotNull() & F.col("y").isin(0, 1)
    )
    known = known.groupBy("doc_id").agg(F.min("y").alias("y"))
    train = least_hashed(known, fit_rows, "doc_id")
    # `train` has fit_rows short rows at most.
    table, text, page = collected(rows.join(F.broadcast(train), "doc_id").dropDuplicates(["doc_id"]).orderBy("doc_id"))
    y = table.column("y").to_numpy().astype(np.int64)
    named = rows.where("doc_id IS NOT NULL").join(known.select("doc_id"), "doc_id", "left_anti").dropDuplicates(["doc_id"])
    unlabelled = staged(named.select("doc_id", "text", "source", "lang", "declared"), "unlabelled")
    model = cotrain((text, page, y), corpus_offers(unlabelled, per_round, least_sure), rounds)
    discard(unlabelled)
    return model


def scored(rows: DataFrame, model: Model, threshold: float) -> DataFrame:
    """doc_id, text_score, page_score, score, keep from feature rows."""
    shipped = rows.sparkSession.sparkContext.broadcast(model)
    schema = pa.schema(
        [("doc_id", pa.int64())] + [(x, pa.float64()) for x in ("text_score", "page_score", "score")] + [("keep", pa.bool_())]
    )

    def run(batches):
        m = shipped.value
        for part in slices(batches, 4 << 20):
            text, page = views_of(part.column(1), *(part.column(k).to_numpy() for k in (2, 3, 4)))
            s = m.score(text, page)
            views = (sigmoid(m.text.calibrated(text)), sigmoid(m.page.calibrated(page))) if m.text else (s, s)
            yield batch_of(schema, part.column(0), *views, s, s >= threshold)

    return rows.mapInArrow(run, "doc_id long, text_score double, page_score double, score double, keep boolean")


def fit_model(
    docs: DataFrame,
    labels: DataFrame,
    fit_rows: int = 6000,
    per_round: int = 400,
    rounds: int = 5,
    least_sure: float = 0.9,
    id_col: str = "doc_id",
    text_col: str = "text",
    label_col: str = "quality",
) -> Model:
    """Co-train on the documents; offers of `per_round` rows a view and round come from all of them."""
    rows = staged(feature_rows(docs, id_col, text_col), "views")
    model = fit_features(rows, labels, fit_rows, per_round, rounds, least_sure, id_col, label_col)
    discard(rows)
    return model


def quality(docs: DataFrame, model: Model, threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_score, page_score, score (probability of good quality), keep of every row."""
    return scored(feature_rows(docs, id_col, text_col), model, threshold)


def cotrained(
    docs: DataFrame,
    labels: DataFrame,
    fit_rows: int = 6000,
    per_round: int = 400,
    rounds: int = 5,
    least_sure: float = 0.9,
    threshold: float = 0.5,
    id_col: str = "doc_id",
    text_col: str = "text",
    label_col: str = "quality",
) -> DataFrame:
    """`quality` under `fit_model` on the same documents, whose texts are scanned only once."""
    rows = staged(feature_rows(docs, id_col, text_col), "views")
    return scored(rows, fit_features(rows, labels, fit_rows, per_round, rounds, least_sure, id_col, label_col), threshold)
