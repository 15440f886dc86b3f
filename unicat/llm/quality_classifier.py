"""Quality by co-training: a classifier of the text's content and one of the document's metadata teach each other.

A document is good if its label says quality and not toxic. Both views start from the labelled documents. In each round
each view labels all unlabelled documents of the table that it is sure of (calibrated probability SURE), and the other view
learns from them in one distributed pass: every task goes on from the view's weights, batch after batch, and the tasks'
weights are averaged. A view's new weights are taken if they do better on held-out labels. Then both views are calibrated
on these, combined there by logistic regression over their log-odds, and applied to all documents.

Features of all documents are computed once and kept as 16-bit places; a round reads these alone. What comes to the
driver is bounded by the number of features (weights) and by MAX_LABELLED labelled documents, in the order of a hash of id and
features (rows that repeat both count once), of which one in HOLD_OUT is held out. The decision threshold is the one
that keeps KEEP_SHARE of the good held-out documents, at most 0.5. Scoring reads every document.

Text view: presence of hashed words, and shares of character classes, repeated words and lines. Metadata view: language,
source and length.

Defined cases: null texts and metadata have features of their own (no words, the value "null"). Without labels of both
kinds every score is 0.5 and every document is kept. Rows that repeat an id are scored by themselves; a label counts for
each of them. Repeated labels of an id count as good only if all are. Empty tables work. Extra columns pass through; one
named like a column that is added comes out as in__...
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import aside, back, materialise, named

MAX_LABELLED, HOLD_OUT = 8_000, 5
ROUNDS, SURE = 3, 0.97
#: Gradient steps on a task's first batch, which fall with each further one down to the second number.
FIRST_STEPS, LATER_STEPS = 60, 4
#: Labels that are broadcast (16 bytes each); more are joined.
BROADCAST_IDS = 1_000_000
KEEP_SHARE = 0.995
WORD_BITS, META_BITS = 15, 10
STEPS, LEAST_ROWS = 120, 6
_DENSE = 14
BINS = 8


class WordPlaces(dict):
    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) > 500_000:
            self.clear()
        h = self[word] = xxhash.xxh32_intdigest(word) & ((1 << WORD_BITS) - 1)
        return h


_STRIP = b".,;:!?\"'()[]{}<>|*#$%&-_=+~`/\\"


def text_features(text: str | None, memo: WordPlaces) -> np.ndarray:
    """Places of the features that hold: hashed words, then one place for each dense feature's bin."""
    raw = (text or "").encode()
    words = raw.lower().split()
    n, size = max(1, len(words)), max(1, len(raw))
    hashed = np.unique(np.fromiter((memo[w.strip(_STRIP)] for w in set(words)), np.int64))
    lines = raw.split(b"\n")
    marks = sum(raw.count(c) for c in (b"#", b"*", b"$", b"%", b"&", b"<", b">"))
    upper = len(raw) - len(raw.translate(None, b"ABCDEFGHIJKLMNOPQRSTUVWXYZ"))
    digits = len(raw) - len(raw.translate(None, b"0123456789"))
    shares = (
        len(set(words)) / n, marks / n, raw.count(b"|") / n, upper / size, digits / size, raw.count(b"!") / n, raw.count(b".") / n, raw.count(b",") / n,
        1 - len(set(lines)) / len(lines), len(lines) / n, min(1, np.log1p(len(words)) / 10), min(1, size / n / 20), raw.count(b"http") / n, raw.count(b"@") / n,
    )
    dense = (1 << WORD_BITS) + np.arange(_DENSE) * BINS + np.minimum(BINS - 1, np.floor(np.sqrt(np.minimum(1, shares)) * BINS)).astype(np.int64)
    return np.concatenate([hashed, dense])


def meta_features(lang, source, n_chars) -> np.ndarray:
    import xxhash

    mask = (1 << META_BITS) - 1
    length = "null" if n_chars is None else str(int(2 * np.log2(max(1, n_chars))))
    return np.array([xxhash.xxh32_intdigest(f"{k}={v}") & mask for k, v in (("lang", lang), ("source", source), ("length", length), ("both", f"{lang}/{source}"))], np.int64)


TEXT_SIZE, META_SIZE = (1 << WORD_BITS) + _DENSE * BINS, 1 << META_BITS


def _rows(places: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    return np.concatenate(places) if places else np.zeros(0, np.int64), np.repeat(np.arange(len(places)), [len(p) for p in places])


class Steps:
    """Weights (the last is the bias) that follow gradients by Adam's steps."""

    def __init__(self, w: np.ndarray):
        self.w, self.first, self.second, self.n = w.copy(), np.zeros_like(w), np.zeros_like(w), 0

    def go(self, g: np.ndarray) -> None:
        self.n += 1
        self.first, self.second = 0.9 * self.first + 0.1 * g, 0.999 * self.second + 0.001 * g * g
        self.w -= 0.1 * (self.first / (1 - 0.9**self.n)) / (np.sqrt(self.second / (1 - 0.999**self.n)) + 1e-8)


def gradient(w: np.ndarray, places: list[np.ndarray], y: np.ndarray, decay: float = 1e-4) -> np.ndarray:
    """Of the logistic loss of rows of places, both classes weighing the same. A feature of few rows stays as it is: it would
    only be learnt by heart."""
    flat, row = _rows(places)
    size = len(w) - 1
    share = np.where(y, 0.5 / max(1, y.sum()), 0.5 / max(1, (~y).sum()))
    d = (_sigmoid(np.bincount(row, weights=w[flat], minlength=len(y)) + w[-1]) - y) * share
    g = np.append(np.bincount(flat, weights=d[row], minlength=size), d.sum()) + decay * np.append(w[:-1], 0)
    return g * np.append(np.bincount(flat, minlength=size) >= LEAST_ROWS, True)


def fit_logistic(places: list[np.ndarray], y: np.ndarray, size: int, steps: int = STEPS) -> np.ndarray:
    """Weights (the last is the bias) by gradient steps on all rows."""
    own = Steps(np.zeros(size + 1))
    for _ in range(steps):
        own.go(gradient(own.w, places, y))
    return own.w


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def odds(places: list[np.ndarray], w: np.ndarray) -> np.ndarray:
    flat, row = _rows(places)
    return np.bincount(row, weights=w[flat], minlength=len(places)) + w[-1]


def _calibrate(columns: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Logistic regression over a few columns of log-odds, by Newton's steps with a small ridge."""
    x = np.column_stack([columns, np.ones(len(y))])
    w = np.zeros(x.shape[1])
    for _ in range(30):
        p = _sigmoid(x @ w)
        h = (x * (p * (1 - p))[:, None]).T @ x + 1e-2 * np.eye(len(w))
        w += np.linalg.solve(h, x.T @ (y - p) - 1e-2 * w)
    return w


_TABLE = "id {kind}, text binary, meta binary"


def feature_table(docs: DataFrame, id_col: str, columns: dict[str, str]) -> DataFrame:
    """id, text and meta: the places of both views of every row, 16 bits each."""

    def run(batches):
        memo = WordPlaces()
        for b in batches:
            text = [text_features(x.as_py(), memo).astype("<u2").tobytes() for x in b.column(1)]
            meta = [meta_features(*v).astype("<u2").tobytes() for v in zip(*(b.column(i).to_pylist() for i in (2, 3, 4)), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(text, pa.binary()), pa.array(meta, pa.binary())], ["id", "text", "meta"])

    rows = docs.select(F.col(id_col).alias("id"), *[F.col(columns[c]).alias(f"c{i}") for i, c in enumerate(("text", "lang", "source", "n_chars"))])
    return rows.mapInArrow(run, _TABLE.format(kind=docs.schema[id_col].dataType.simpleString()))


def _places(col) -> list[np.ndarray]:
    return [np.frombuffer(x.as_buffer(), "<u2").astype(np.int64) for x in col]


def teach(rows: DataFrame, models, guides, labelled, y: np.ndarray) -> tuple[list[np.ndarray], int]:
    """Both views' weights after one pass over the rows (text, meta), and how many labels the views gave each other.

    Each task starts from the views' weights and goes on with gradient steps over batch after batch: the rows that the other
    view (by its guide, the calibrated weights) is sure of, and as many labelled ones in turn. The tasks' weights are
    averaged by how many rows each has learnt from."""
    held = rows.sparkSession.sparkContext.broadcast((models, guides, labelled, y))
    sizes = (TEXT_SIZE, META_SIZE)

    def run(batches):
        models, guides, labelled, y = held.value
        own, used, at = [Steps(m) for m in models], [0, 0], 0
        for k, b in enumerate(batches):
            views = [_places(b.column(v)) for v in (0, 1)]
            p = [_sigmoid(odds(views[v], guides[v])) for v in (0, 1)]
            turn = np.arange(at, at + min(len(y), 1_000)) % len(y)
            at += len(turn)
            for v in (0, 1):
                good, bad = p[1 - v] >= SURE, p[1 - v] <= 1 - SURE
                sure = np.flatnonzero(good | bad)
                if len(sure):
                    used[v] += len(sure)
                    sets = [([views[v][i] for i in sure], good[sure]), ([labelled[v][i] for i in turn], y[turn])]
                    for _ in range(max(LATER_STEPS, FIRST_STEPS // (k + 1))):
                        own[v].go(sum(gradient(own[v].w, x, t) for x, t in sets))
        for v in (0, 1):
            if used[v]:
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(sizes[v] + 2) + v * 100_000), pa.array(np.append(own[v].w, 1.0) * used[v])], ["key", "value"])

    got = rows.select("text", "meta").mapInArrow(run, "key long, value double").groupBy("key").agg(F.sum("value")).collect()
    out = [np.zeros(n + 2) for n in sizes]
    for key, value in got:
        out[key // 100_000][key % 100_000] = value
    # Six places, so that the order of the sums does not matter.
    return [np.round(x[:-1] / x[-1], 6) if x[-1] else m for x, m in zip(out, models, strict=True)], int(sum(x[-1] for x in out))


def co_train(labelled, y: np.ndarray, held: np.ndarray, rest: DataFrame):
    """(text weights, meta weights, calibration of each, combination, threshold, rows labelled in each round).

    labelled: pair of lists of places, text view and metadata view; rest: the unlabelled rows (text, meta)."""
    train, check, sizes, added = np.flatnonzero(~held), np.flatnonzero(held), (TEXT_SIZE, META_SIZE), []
    own = [[labelled[v][i] for i in train] for v in (0, 1)]

    def judged(v: int, model: np.ndarray):
        """The held-out rows' log-odds under a model, their calibration, and the loss after it."""
        raw = odds([labelled[v][i] for i in check], model)
        scale = _calibrate(raw[:, None], y[check])
        p = np.clip(_sigmoid(raw * scale[0] + scale[1]), 1e-9, 1 - 1e-9)
        return raw, scale, -np.log(np.where(y[check], p, 1 - p)).mean()

    models = [fit_logistic(own[v], y[train], sizes[v]) for v in (0, 1)]
    state = [judged(v, models[v]) for v in (0, 1)]
    for _ in range(ROUNDS):
        guides = [m * c[0] + np.append(np.zeros(len(m) - 1), c[1]) for m, (_, c, _) in zip(models, state, strict=True)]
        taught, n = teach(rest, models, guides, own, y[train])
        added.append(n)
        better = False
        for v, model in enumerate(taught):
            now = judged(v, model)
            if now[2] < state[v][2]:  # what a view is taught must help on labels that it has not seen
                models[v], state[v], better = model, now, True
        if not better:
            break
    raw = np.column_stack([state[v][0] for v in (0, 1)])
    own = [state[v][1] for v in (0, 1)]
    calibrated = np.column_stack([raw[:, v] * own[v][0] + own[v][1] for v in (0, 1)])
    both = _calibrate(calibrated, y[check])
    final = _sigmoid(calibrated @ both[:2] + both[2])
    good = np.sort(final[y[check]])
    threshold = min(0.5, float(good[int((1 - KEEP_SHARE) * len(good))]) - 1e-9) if len(good) else 0.0
    return models[0], models[1], own, both, threshold, added


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", columns: dict[str, str] | None = None):
    """The model, or None without labels of both kinds in the training and the held-out part."""
    columns = columns or {c: c for c in ("text", "lang", "source", "n_chars")}
    known = labels.where(F.col(id_col).isNotNull() & F.col("quality").isNotNull()).groupBy(F.col(id_col).alias("of")).agg(F.min(((F.col("quality") == 1) & (F.coalesce("toxic", F.lit(0)) == 0)).cast("int")).alias("g"))
    known = materialise(known, "quality-labels")
    few = known.count() <= BROADCAST_IDS
    table = materialise(feature_table(docs, id_col, columns), "quality-features")
    marked = table.join(F.broadcast(known) if few else known, F.col("id") == F.col("of"), "left").select("id", "text", "meta", "g")
    key = F.xxhash64(F.lit(17), "id", "text", "meta")
    chosen = marked.where("g is not null").groupBy("id", key.alias("key")).agg(F.first("text").alias("text"), F.first("meta").alias("meta"), F.first("g").alias("g")).orderBy("key", "id").limit(MAX_LABELLED)
    got = chosen.select("text", "meta", "g", (F.pmod(F.xxhash64("id", F.lit(23)), F.lit(HOLD_OUT)) == 0).alias("held")).toArrow()
    y, held = np.array(got.column(2).to_pylist(), bool), np.array(got.column(3).to_pylist(), bool)
    if not all(len(set(y[part])) == 2 for part in (held, ~held)):
        return None
    return co_train((_places(got.column(0)), _places(got.column(1))), y, held, marked.where("g is null"))


ADDED = T.StructType([*(T.StructField(f"__{n}", T.DoubleType()) for n in ("text_score", "meta_score", "score")), T.StructField("__kept", T.BooleanType())])


def score(docs: DataFrame, model, columns: dict[str, str] | None = None, drop_text: bool = False) -> DataFrame:
    """docs with the calibrated score of each view, the combined one, and whether it reaches the threshold."""
    columns = columns or {c: c for c in ("text", "lang", "source", "n_chars")}
    docs, names_in = aside(docs)
    columns = {c: named(x, names_in) for c, x in columns.items()}
    names = [c for c in docs.columns if not (drop_text and c == columns["text"])]
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        memo, m = WordPlaces(), held.value
        for b in batches:
            n = b.num_rows
            if m is None or not n:
                text = meta = both = np.full(n, 0.5)
                kept = np.ones(n, bool)
            else:
                at = b.schema.get_field_index
                raw_text = np.array([m[0][text_features(x.as_py(), memo)].sum() + m[0][-1] for x in b.column(at(columns["text"]))])
                raw_meta = np.array([m[1][meta_features(*v)].sum() + m[1][-1] for v in zip(*(b.column(at(columns[c])).to_pylist() for c in ("lang", "source", "n_chars")), strict=True)])
                a, c = raw_text * m[2][0][0] + m[2][0][1], raw_meta * m[2][1][0] + m[2][1][1]
                text, meta, both = _sigmoid(a), _sigmoid(c), _sigmoid(a * m[3][0] + c * m[3][1] + m[3][2])
                kept = both >= m[4]
            yield pa.RecordBatch.from_arrays([*(b.column(b.schema.get_field_index(c)) for c in names), pa.array(text), pa.array(meta), pa.array(both), pa.array(kept)], [*names, *ADDED.names])

    return back(docs.mapInArrow(run, T.StructType([*(docs.schema[c] for c in names), *ADDED])), names_in)
