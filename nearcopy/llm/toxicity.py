"""Toxicity by a support vector machine over a gap-weighted subsequence kernel with Nystrom landmarks.

Units are the words of a text, lower-cased, runs of single characters with blanks between ("s p a c e d", read
without the blanks), and of longer ones windows of WINDOW characters. A unit is read as its letters (of any script)
between a mark for its start and one for its end; inserted signs and digits are passed over. The kernel of two units
sums, over triples of letters or marks that stand in both in this order, DECAY to the power of the lengths that they
span; inserted letters are gaps, which lower a match but don't break it. Spans over REACH count as 0. Kernels are
divided by each unit's root of the sum of squared weights over its triples.

The machine is linear in the kernels with some hundreds of landmarks, whitened (Nystrom). As the kernel's own
features, the triples, are few (CODES ** 3), the landmarks' weighted sum is folded into one table, so a unit's
margin costs the same for any number of landmarks, and no unit is left out by a prefilter.

A label belongs to a text, so training is by witnesses. The difference of the two classes' mean kernels ranks units
at first. A toxic text is then stood for by its highest units, a clean one by its highest ones too, and a sample of
all units is on the clean side. Landmarks are chosen by coverage: each toxic text none of whose witnesses is a
landmark yet adds its highest one; the rest are witnesses of clean texts. All three are chosen anew in each round.

A text's score is a logistic function of its highest margins and of the sums of its margins above several levels,
so that several weak hits can weigh as much as a strong one. It is fitted on margins of machines that have not seen
the text (two halves). Nulls and texts without units share one score.

The fit uses at most `per_class` labelled texts, of at most MAX_TRAIN_CHARS characters, of each class, chosen by a
hash of the id. Labels other than 0 and 1, and null ids, are left out; with no label or one class only, all scores
are one constant.
"""

from __future__ import annotations

import pickle
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.types import DoubleType, StructType

from nearcopy.llm.common import arrow_map, batch, check_columns, claim, documents
from nearcopy.llm.tokens import text_groups

DECAY, REACH, WINDOW = 0.7, 8, 24
PER_CLASS, MAX_TRAIN_CHARS = 1500, 32_000
LANDMARKS, ROUNDS = 400, 3
#: Highest units that stand for a toxic and for a clean text in training, and units of the sample on the clean side.
TOXIC_WITNESSES, CLEAN_WITNESSES, BACKGROUND = 3, 6, 4000
#: Weight of the sample within the clean side.
BACKGROUND_SHARE = 0.3
#: Share of toxic texts that the score is set to, where the labels hold fewer.
LEAST_PRIOR = 0.2
#: Units whose margin one Python worker keeps.
CACHE_UNITS = 300_000
#: Units that one kernel call looks at.
UNITS_AT_ONCE = 20_000
FLOOR, CEILING = -0.5, 1.5  # margins beyond these count as these
#: A text's features are its three highest margins and, for each of these levels, the sum of what margins have above
#: it, as it is and for its number of units.
LEVELS = (0.0, 0.3, 0.6)
FEATURES = 3 + 2 * len(LEVELS)
#: Codes: 0 gap, 1 to 26 a to z, START, then other letters (shared by code point), END.
CODES, START, END = 64, 27, 63
_spaced = re.compile(r"(?<!\S)\S(?: \S){2,}(?!\S)")


def units(text: str) -> set[str]:
    low = text.lower()
    out = set(low.split())
    if " " in low:
        out.update(m.group().replace(" ", "") for m in _spaced.finditer(low))
    for long in [w for w in out if len(w) > WINDOW]:
        out.remove(long)
        out.update(long[a : a + WINDOW] for a in range(0, len(long) - WINDOW // 2, WINDOW // 2))
    return out


def letter_codes(points: np.ndarray) -> np.ndarray:
    """Codes of lower-case code points."""
    out = np.where((points >= 97) & (points <= 122), points - 96, 0).astype(np.int32)
    other = np.flatnonzero(points >= 128)
    if len(other):
        kinds, which = np.unique(points[other], return_inverse=True)
        spread = END - START - 1
        shared = [START + 1 + c % spread if chr(c).isalpha() else 0 for c in kinds.tolist()]
        out[other] = np.array(shared, np.int32)[which]
    return out


def encode(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Codes of all words in a row, each from its start mark to its end mark, and the word of each code.
    Words without letters have none."""
    if not words:
        return np.zeros(0, np.int32), np.zeros(0, np.int64)
    joined = "\0".join(words)
    if joined.count("\0") >= len(words):
        joined = "\0".join([w.replace("\0", " ") for w in words])
    points = np.frombuffer(joined.encode("utf-32-le"), np.uint32).astype(np.int64)
    codes = letter_codes(points)
    owner = np.cumsum(points == 0)
    letters = np.flatnonzero(codes)
    if not len(letters):
        return np.zeros(0, np.int32), np.zeros(0, np.int64)
    codes, owner = codes[letters], owner[letters]
    turns = np.flatnonzero(np.diff(owner)) + 1
    bounds = np.concatenate([[0], turns, [len(codes)]])
    out = np.insert(codes, np.repeat(bounds, 2)[1:-1], np.tile([START, END], len(bounds) - 1))
    return out, np.insert(owner, np.repeat(bounds, 2)[1:-1], np.repeat(owner[bounds[:-1]], 2))


def triples(codes: np.ndarray, owner: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, float]]:
    """(word, triple, weight) of all triples with a span of REACH at most, grouped by their shape."""
    for wide in range(2, REACH):
        if len(codes) <= wide:
            return
        at = np.flatnonzero(owner[:-wide] == owner[wide:])
        for inside in range(1, wide):
            yield owner[at], (codes[at] * CODES + codes[at + inside]) * CODES + codes[at + wide], DECAY ** (wide + 1)


def norms(codes: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros(n)
    for own, _, weight in triples(codes, owner):
        out += np.bincount(own, minlength=n) * weight**2
    return np.sqrt(out)


def _ratio(a, b: np.ndarray) -> np.ndarray:
    return np.divide(a, b, out=np.zeros(len(b)), where=b > 0)


def table_margins(table: np.ndarray, words: list[str]) -> np.ndarray:
    """Of each word, the sum of the table over its triples, weighted and divided as the kernel is."""
    out = [np.zeros(0)]
    for a in range(0, len(words), UNITS_AT_ONCE):
        some = words[a : a + UNITS_AT_ONCE]
        codes, owner = encode(some)
        total, square = np.zeros(len(some)), np.zeros(len(some))
        for own, triple, weight in triples(codes, owner):
            total += np.bincount(own, table[triple], len(some)) * weight
            square += np.bincount(own, minlength=len(some)) * weight**2
        out.append(_ratio(total, np.sqrt(square)))
    return np.concatenate(out)


def mean_features(words: list[str], weight: np.ndarray) -> np.ndarray:
    """Over all triples: the words' features, summed with these weights."""
    out = np.zeros(CODES**3)
    for a in range(0, len(words), UNITS_AT_ONCE):
        codes, owner = encode(words[a : a + UNITS_AT_ONCE])
        share = _ratio(weight[a : a + UNITS_AT_ONCE], norms(codes, owner, len(words[a : a + UNITS_AT_ONCE])))
        for own, triple, w in triples(codes, owner):
            out += np.bincount(triple, share[own] * w, CODES**3)
    return out


def feature_rows(words: list[str], columns: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Features of each word over the given triples (None: all that occur), and these triples."""
    codes, owner = encode(words)
    share = _ratio(1.0, norms(codes, owner, len(words)))
    if columns is None:
        columns = np.unique(np.concatenate([np.zeros(0, np.int32), *(t for _, t, _ in triples(codes, owner))]))
    place = np.full(CODES**3, -1, np.int32)
    place[columns] = np.arange(len(columns))
    out = np.zeros((len(words), len(columns)), np.float32)
    for own, triple, w in triples(codes, owner):
        spot = place[triple]
        seen = spot >= 0
        np.add.at(out, (own[seen], spot[seen]), (share[own[seen]] * w).astype(np.float32))
    return out, columns


def subsequence_kernel(left: list[str], right: list[str]) -> np.ndarray:
    """Kernel of each left with each right unit."""
    marks, columns = feature_rows(right)
    rows = [feature_rows(left[a : a + 2000], columns)[0] @ marks.T for a in range(0, len(left), 2000)]
    return np.vstack(rows).astype(np.float64) if rows else np.zeros((0, len(right)))


def fit_svm(x: np.ndarray, y: np.ndarray, weight: np.ndarray, c: float = 1.0, rounds: int = 30) -> np.ndarray:
    """Weights and, last, the constant of a linear machine with squared hinge loss, by Newton steps."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w, ridge = np.zeros(x.shape[1]), np.eye(x.shape[1])
    ridge[-1, -1] = 1e-6
    for _ in range(rounds):
        active = y * (x @ w) < 1
        xa = x[active] * (weight[active] * c)[:, None]
        new = np.linalg.solve(ridge + xa.T @ x[active], xa.T @ y[active])
        if np.allclose(new, w, atol=1e-6):
            break
        w = new
    return w


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 5e-3) -> np.ndarray:
    """Weights, none of them negative, and, last, a constant: features that would get negative weights are left out,
    the lowest first."""
    used = np.arange(x.shape[1])
    while True:
        a = np.hstack([x[:, used], np.ones((len(x), 1))])
        w, penalty = np.zeros(a.shape[1]), ridge * len(x) * np.eye(a.shape[1])
        penalty[-1, -1] = 1e-6
        for _ in range(100):
            p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
            h = a.T @ (a * (weight * np.maximum(p * (1 - p), 1e-6))[:, None]) + penalty
            step = np.linalg.solve(h, a.T @ (weight * (y - p)) - penalty @ w)
            w += np.clip(step, -2, 2)
            if np.abs(step).max() < 1e-6:
                break
        if len(used) == 0 or w[:-1].min() >= 0:
            out = np.zeros(x.shape[1] + 1)
            out[used], out[-1] = w[:-1], w[-1]
            return out
        used = np.delete(used, np.argmin(w[:-1]))


def text_features(margins: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """One row a text; margins of all texts' distinct units, one text after another, `counts` units each."""
    n = len(counts)
    owner = np.repeat(np.arange(n), counts)
    high = np.flatnonzero(margins > FLOOR)
    value, own = np.minimum(margins[high], CEILING), owner[high]
    order = np.lexsort((-value, own))
    value, own = value[order], own[order]
    rank = np.arange(len(own)) - np.searchsorted(own, own)
    out = np.zeros((n, FEATURES))
    out[:, :3] = FLOOR
    for k in range(3):
        out[own[rank == k], k] = value[rank == k]
    for k, level in enumerate(LEVELS):
        total = np.bincount(own, np.maximum(value - level, 0), n)
        out[:, 3 + k] = np.log1p(total * 2)
        out[:, 3 + len(LEVELS) + k] = total / np.log(counts + 8)
    return out


@dataclass
class ToxicityModel:
    table: np.ndarray  # of a unit: weights of triples
    bias: float
    centre: np.ndarray  # of text features
    scale: np.ndarray
    weights: np.ndarray
    landmarks: list[str]

    @staticmethod
    def constant(share: float) -> ToxicityModel:
        """For too few labels: the same score for all texts."""
        p = min(max(share, 1e-3), 1 - 1e-3)
        weights = np.append(np.zeros(FEATURES), np.log(p / (1 - p)))
        return ToxicityModel(np.zeros(CODES**3, np.float32), FLOOR, np.zeros(FEATURES), np.ones(FEATURES), weights, [])

    def margins(self, words: list[str]) -> np.ndarray:
        return table_margins(self.table, words) + self.bias

    def score(self, features: np.ndarray) -> np.ndarray:
        x = (features - self.centre) / self.scale
        return 1 / (1 + np.exp(-np.clip(x @ self.weights[:-1] + self.weights[-1], -30, 30)))


def choose_landmarks(
    witnesses: list[np.ndarray], clean: np.ndarray, count: int, rng: np.random.Generator
) -> np.ndarray:
    """Units by coverage: the highest of each toxic text that has none yet, in an order that favours no text, and
    units of clean texts."""
    chosen: dict[int, None] = {}
    for k in rng.permutation(len(witnesses)):
        if len(chosen) < count * 3 // 4 and len(witnesses[k]) and not any(int(u) in chosen for u in witnesses[k]):
            chosen[int(witnesses[k][0])] = None
    for group in witnesses:  # room that is left goes to further witnesses
        for u in group[1:]:
            if len(chosen) < count // 2:
                chosen[int(u)] = None
    rest = clean[~np.isin(clean, list(chosen))]
    more = rng.choice(rest, min(len(rest), count - len(chosen)), replace=False) if len(rest) else rest
    return np.unique(np.append(np.array(list(chosen), np.int64), more).astype(np.int64))


def fit_units(words: list[str], inside: list[np.ndarray], y: np.ndarray) -> tuple[np.ndarray, float, list[str]]:
    """Table, constant and landmarks of the machine for units; inside: the units (numbers in `words`) of each text."""
    rng, n = np.random.default_rng(20240229), len(words)

    def times(groups, side):
        return np.bincount(np.concatenate([g for g, v in zip(groups, y, strict=True) if v == side]), minlength=n)

    used = [times(inside, side).astype(float) for side in (0, 1)]
    mean = [mean_features(words, u / max(1.0, u.sum())) for u in used]
    margin = table_margins((mean[1] - mean[0]) / np.sqrt(mean[0] + mean[1] + 1e-5), words)
    present = np.flatnonzero(used[0] + used[1])
    table, bias, marks = np.zeros(CODES**3), FLOOR, np.zeros(0, np.int64)
    for _ in range(ROUNDS):
        best = []
        for own, v in zip(inside, y, strict=True):
            best.append(own[np.argsort(-margin[own], kind="stable")[: TOXIC_WITNESSES if v else CLEAN_WITNESSES]])
        up, down = times(best, 1).astype(float), times(best, 0).astype(float)
        sample = rng.choice(present, min(len(present), BACKGROUND), replace=False)
        marks = choose_landmarks([b for b, v in zip(best, y, strict=True) if v], np.flatnonzero(down), LANDMARKS, rng)
        names = [words[k] for k in marks]
        gram = subsequence_kernel(names, names)
        values, vectors = np.linalg.eigh((gram + gram.T) / 2)
        keep = values > 1e-3
        whiten = vectors[:, keep] / np.sqrt(values[keep])
        chosen = np.unique(np.concatenate([np.flatnonzero(up), np.flatnonzero(down), sample]))
        x = subsequence_kernel([words[k] for k in chosen], names) @ whiten
        spread = np.zeros(n)
        spread[sample] = BACKGROUND_SHARE / max(1, len(sample))
        clean = (1 - BACKGROUND_SHARE) * down[chosen] / max(1.0, down.sum()) + spread[chosen]
        cost = np.append(up[chosen] / up.sum(), clean)
        sign, rows = np.repeat([1.0, -1.0], len(chosen)), np.tile(np.arange(len(chosen)), 2)
        some = cost > 0
        w = fit_svm(x[rows[some]], sign[some], cost[some] / cost[some].mean())
        features, columns = feature_rows(names)
        table, bias = np.zeros(CODES**3), float(w[-1])
        table[columns] = (whiten @ w[:-1]) @ features
        margin = table_margins(table, words) + bias
    return table, bias, [words[k] for k in marks]


def fit_model(texts: list[str | None], labels: list[int], prior: float | None = None) -> ToxicityModel:
    """prior: share of toxic texts to weight the classes to (None: as given)."""
    y = np.array([1 if v else 0 for v in labels])
    bags = [sorted(units(t or "")) for t in texts]
    share = (float(y.mean()) if len(y) else 0.0) if prior is None else prior
    if len({int(v) for b, v in zip(bags, y, strict=True) if b}) < 2:
        return ToxicityModel.constant(share)
    words = sorted(set().union(*bags))
    place = {w: k for k, w in enumerate(words)}
    inside = [np.array([place[w] for w in b], np.int64) for b in bags]
    counts = np.array([len(own) for own in inside])

    def seen(table, bias, some):
        margin = np.zeros(len(words))
        used = np.unique(np.concatenate([inside[k] for k in some]))
        margin[used] = table_margins(table, [words[k] for k in used]) + bias
        return text_features(np.concatenate([margin[inside[k]] for k in some]), counts[some])

    side, rng = np.zeros(len(y), np.int64), np.random.default_rng(20240301)
    for v in (0, 1):  # halves with equal shares of both classes
        mine = rng.permutation(np.flatnonzero((y == v) & (counts > 0)))
        side[mine] = np.arange(len(mine)) % 2
    x = np.zeros((len(y), FEATURES))
    for half in (0, 1):
        taught, asked = np.flatnonzero((side != half) & (counts > 0)), np.flatnonzero(side == half)
        if len(set(y[taught].tolist())) < 2:
            taught = np.flatnonzero(counts > 0)  # too few texts to part them
        if len(asked):
            machine = fit_units(words, [inside[k] for k in taught], y[taught])
            x[asked] = seen(machine[0], machine[1], asked)
    table, bias, marks = fit_units(words, [inside[k] for k in np.flatnonzero(counts)], y[counts > 0])
    centre, scale = x.mean(axis=0), x.std(axis=0) + 1e-3
    weight = np.where(y == 1, share / y.mean(), (1 - share) / (1 - y.mean()))
    w = fit_logistic((x - centre) / scale, y, weight)
    return ToxicityModel(table.astype(np.float32), bias, centre, scale, w, marks)


def training_rows(
    docs: DataFrame,
    labels: DataFrame,
    per_class: int = PER_CLASS,
    label: str = "toxic",
    text: str = "text",
    id_column: str = "doc_id",
    folds: int = 5,
) -> tuple[DataFrame | None, float]:
    """(_id, _text, _y) of the fit, in one partition, and the share of label 1: rows whose crc32 of the id's text is no
    multiple of `folds`; at most 2 * per_class of them, of MAX_TRAIN_CHARS characters. None where there are no
    labels."""
    learnt = F.crc32(F.col(id_column).cast("string")) % folds != 0
    known = labels.where(F.col(label).isin(0, 1) & F.col(id_column).isNotNull() & learnt)
    known = known.select(F.col(id_column).alias("_id"), F.col(label).alias("_y"))
    counts = {r[0]: r[1] for r in known.groupBy("_y").count().collect()}
    total = sum(counts.values())
    if not total:
        return None, 0.0
    spark, chosen = docs.sparkSession, []
    for y in (0, 1):
        some = known.where(F.col("_y") == y).orderBy(F.xxhash64("_id"), "_id").limit(per_class)
        chosen += [(r[0], y) for r in some.collect()]
    ids = F.broadcast(spark.createDataFrame(chosen, "_id long, _y int"))  # 2 * per_class rows
    plain = docs.select(docs[id_column].cast("long").alias("_doc"), docs[text].alias("_text"))
    plain = plain.where(F.length("_text") <= MAX_TRAIN_CHARS)
    rows = plain.join(ids, F.col("_doc") == F.col("_id")).select("_id", "_text", "_y")
    return rows.orderBy("_id", "_text", "_y").limit(2 * per_class), counts.get(1, 0) / total


def fit_toxicity(docs: DataFrame, labels: DataFrame, **options) -> ToxicityModel:
    """The fit is one task on an executor, which a lost executor only repeats; the driver sees the machine, not the
    texts."""
    rows, share = training_rows(docs, labels, **options)
    if rows is None:
        return ToxicityModel.constant(share)

    def fit(batches):
        claim("toxicity")
        texts, y = [], []
        for b in batches:
            texts += b.column(1).to_pylist()
            y += b.column(2).to_pylist()
        yield batch(pa.schema([("model", pa.binary())]), [pickle.dumps(fit_model(texts, y, max(share, LEAST_PRIOR)))])

    found = rows.transform(arrow_map, fit, "model binary").collect()  # a row of about 1 MB; none from empty tables
    return pickle.loads(found[0][0]) if found else ToxicityModel.constant(share)


def score_texts(model: ToxicityModel, texts: list[str | None], known: dict[str, float] | None = None) -> np.ndarray:
    known = {} if known is None else known
    bags = [units(t) if t else () for t in texts]
    new = list({w for b in bags for w in b if w not in known})
    known.update(zip(new, model.margins(new).tolist(), strict=True))
    counts = np.array([len(b) for b in bags], np.int64)
    margins = np.fromiter((known[w] for b in bags for w in b), np.float64, int(counts.sum()))
    if len(known) > CACHE_UNITS:
        for w in new:
            del known[w]
    return model.score(text_features(margins, counts))


def add_scores(docs: DataFrame, model: ToxicityModel, text: str = "text", column: str = "toxicity") -> DataFrame:
    """`docs` with a score from 0 to 1 for each row; empty and null texts get that of a text without units.
    A column of that name is replaced."""
    check_columns(docs, text)
    docs = docs.drop(column)
    shared = docs.sparkSession.sparkContext.broadcast(model)  # a table of CODES ** 3 numbers: 1 MB
    place = docs.columns.index(text)

    def run(batches):
        claim("toxicity")
        known: dict[str, float] = {}
        for b in batches:
            out = [score_texts(shared.value, texts, known) for _, texts in text_groups(b.column(place))]
            scores = pa.array(np.concatenate(out) if out else np.zeros(0))
            yield pa.RecordBatch.from_arrays([*b.columns, scores], names=[*b.schema.names, column])

    return docs.transform(arrow_map, run, StructType([*docs.schema.fields]).add(column, DoubleType()))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    model = fit_toxicity(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    held_out = (F.crc32(F.col("doc_id").cast("string")) % 5 == 0).alias("held_out")
    predicted = (F.col("score") >= 0.5).cast("int").alias("predicted")
    return add_scores(docs, model, column="score").select("doc_id", held_out, "score", predicted)
