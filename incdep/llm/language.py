"""Language identification by hierarchical discrimination.

Features are counts of hashed letter n-grams (one to three characters, runs of anything but letters as one space) of the
whole text: square roots, scaled to length one. A first set of linear support vector machines tells language families
apart, one against one; a second set, one against one too, separates the languages inside the chosen family. Families
aren't given: they come from clustering the languages' mean features.

Training takes at most ``per_language`` labelled rows of each language, those with the smallest hash of their id and text,
however often an id is repeated; this is the only sampling, and predictions read the text alone.

Defined cases: a null text and one without any letter are ``und`` with score 0; rows without a language are predicted but
never learned from; without any labelled row all predictions are ``und``; a null id counts as the empty string for the
held-out rule. An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import bpe

BINS = 4096
PER_LANGUAGE = 300
SLOPE = 3.0
_TABLE: list[np.ndarray] = []


def _letters() -> np.ndarray:
    """For each code point itself if it is a letter, else 0."""
    if not _TABLE:
        t = np.zeros(0x110000, np.uint32)
        t[[c for c in range(0x110000) if chr(c).isalpha()]] = 1
        _TABLE.append(t * np.arange(0x110000, dtype=np.uint32))
    return _TABLE[0]


def counts(text: str, piece: int = 1 << 19) -> np.ndarray | None:
    """Hashed n-gram counts of the whole text; None if it has no letter."""
    table, total, letters = _letters(), np.zeros(BINS), False
    tail = np.zeros(1, np.uint32)
    for at in range(0, len(text), piece):
        cp = table[np.frombuffer(text[at : at + piece].lower().encode("utf-32-le", "surrogatepass"), "<u4")]
        letters = letters or bool(cp.any())
        carried = len(tail)
        cp = np.concatenate([tail, cp])
        keep = np.ones(len(cp), bool)
        keep[1:] = (cp[1:] != 0) | (cp[:-1] != 0)
        keep[:carried] = True
        cp = cp[keep]
        k = cp[carried:].astype(np.uint32)
        one = k * np.uint32(2654435761)
        two = (cp[carried - 1 : -1] if carried else cp[:-1]) * np.uint32(2246822519) + one
        grams = [one[k != 0], two]
        if len(cp) > 2:
            third = cp[:-2] * np.uint32(3266489917) + cp[1:-1] * np.uint32(2246822519) + cp[2:] * np.uint32(2654435761)
            grams.append(third[max(0, carried - 2) :] if carried else third)
        total += np.bincount(np.concatenate(grams) >> np.uint32(20), minlength=BINS)
        tail = cp[-2:]
    return total if letters else None


def features(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Unit feature vectors, and whether the text has a letter."""
    out, known = np.zeros((len(texts), BINS), np.float32), np.zeros(len(texts), bool)
    for k, text in enumerate(texts):
        if text and (c := counts(text)) is not None:
            root = np.sqrt(c)
            out[k], known[k] = root / np.linalg.norm(root), True
    return out, known


def _svm(x: np.ndarray, y: np.ndarray, c: float = 10.0, epochs: int = 15, seed: int = 1) -> np.ndarray:
    """Weights (the last is the bias) of a linear SVM with hinge loss, by dual coordinate descent."""
    x = np.hstack([x, np.ones((len(x), 1), x.dtype)]).astype("f8")
    w, alpha, norm = np.zeros(x.shape[1]), np.zeros(len(x)), (x * x).sum(1)
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        for i in rng.permutation(len(x)):
            new = min(c, max(0.0, alpha[i] + (1 - y[i] * (x[i] @ w)) / norm[i]))
            if new != alpha[i]:
                w += (new - alpha[i]) * y[i] * x[i]
                alpha[i] = new
    return w


def _families(means: np.ndarray) -> list[list[int]]:
    """Average-linkage clusters of the languages' mean features, the square root of their number of them."""
    groups = [[k] for k in range(len(means))]
    near = means @ means.T
    while len(groups) > int(np.ceil(np.sqrt(len(means)))):
        a, b = max(combinations(range(len(groups)), 2), key=lambda p: near[np.ix_(groups[p[0]], groups[p[1]])].mean())
        groups[a] = sorted(groups[a] + groups.pop(b))
    return groups


@dataclass
class Model:
    languages: list[str]
    families: list[list[int]]
    pairs: list[tuple[int, int, int]]  # (family, or -1 for the family level; first; second), a column of weights each
    weights: np.ndarray

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Language numbers and scores of feature rows."""
        sure = 1 / (1 + np.exp(-SLOPE * (x @ self.weights[:-1].astype(x.dtype) + self.weights[-1].astype(x.dtype))))
        fam, p = self._vote(sure, -1, list(range(len(self.families))))
        lang, score = np.zeros(len(x), int), p.copy()
        for f, members in enumerate(self.families):
            at = np.flatnonzero(fam == f)
            if len(at):
                which, q = self._vote(sure[at], f, members)
                lang[at], score[at] = which, p[at] * q
        return lang, score

    def _vote(self, sure: np.ndarray, level: int, members: list[int]) -> tuple[np.ndarray, np.ndarray]:
        if len(members) == 1:
            return np.full(len(sure), members[0]), np.ones(len(sure))
        votes = np.zeros((len(sure), len(members)))
        for col, (f, a, b) in enumerate(self.pairs):
            if f == level:
                votes[:, members.index(a)] += sure[:, col]
                votes[:, members.index(b)] += 1 - sure[:, col]
        votes /= len(members) - 1
        best = votes.argmax(1)
        return np.asarray(members)[best], votes[np.arange(len(best)), best]


def fit(x: np.ndarray, labels: list[str]) -> Model:
    languages = sorted(set(labels))
    y = np.asarray([languages.index(n) for n in labels])
    means = np.stack([x[y == k].mean(0) for k in range(len(languages))])
    families = _families(means / np.linalg.norm(means, axis=1, keepdims=True))
    of = np.asarray([next(f for f, g in enumerate(families) if k in g) for k in range(len(languages))])
    pairs, columns = [], []
    for level, names, group in [(-1, range(len(families)), of[y]), *((f, g, y) for f, g in enumerate(families))]:
        for a, b in combinations(names, 2):
            at = np.flatnonzero((group == a) | (group == b))
            pairs.append((level, a, b))
            columns.append(_svm(x[at], np.where(group[at] == a, 1.0, -1.0)))
    return Model(languages, families, pairs, np.stack(columns, axis=1) if columns else np.zeros((BINS + 1, 0)))


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 4 == 2


def train(docs: DataFrame, per_language: int = PER_LANGUAGE) -> Model | None:
    """Learn from labelled rows of ``docs(doc_id, text, lang)`` that aren't held out; None if there are none."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "lang", "text").filter(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    # rows whose hash is below a bound that about four times as many rows have; then the smallest of them. Equal rows tie, so
    # a language may have more below the bound; whatever is left out then equals a row that stays
    hashed = rows.withColumn("_h", F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30)))
    share = hashed.groupBy("lang").agg(F.least(F.lit(1.0), 4.0 * per_language / F.count(F.lit(1))).alias("_share"))
    near = hashed.join(F.broadcast(share), "lang").filter(F.col("_h") < F.col("_share") * (1 << 30))
    first = Window.partitionBy("lang").orderBy("_h", "doc_id", "text")
    some = near.withColumn("_k", F.row_number().over(first)).filter(F.col("_k") <= per_language).select("lang", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                x, known = features(batch.column(1).slice(at, 64).to_pylist())
                keep = np.flatnonzero(known)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, 64).take(pa.array(keep)), pa.array([x[k].astype("<f2").tobytes() for k in keep], pa.binary())], names=["lang", "x"])

    # languages times per_language rows at most
    got = some.mapInArrow(run, "lang string, x binary").collect()
    if not got:
        return None
    got.sort(key=lambda r: (r["lang"], bytes(r["x"])))
    return fit(np.stack([np.frombuffer(r["x"], "<f2").astype("f4") for r in got]), [r["lang"] for r in got])


def identify(docs: DataFrame, model: Model | None) -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score``, from the whole ``text`` alone."""
    schema = ", ".join(f"`{n}` {t}" for n, t in docs.dtypes) + ", lang_pred string, score double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe.forget()
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch = whole.slice(at, 256)
                names, scores = ["und"] * batch.num_rows, np.zeros(batch.num_rows)
                texts = batch.column("text").to_pylist()
                for k in range(0, len(texts), 64):
                    x, known = features(texts[k : k + 64])
                    keep = np.flatnonzero(known)
                    if model and len(keep):
                        lang, p = model.predict(x[keep])
                        for j, n, s in zip(keep, lang, p, strict=True):
                            names[k + j], scores[k + j] = model.languages[n], s
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(names, pa.string()), pa.array(scores)], names=[*batch.schema.names, "lang_pred", "score"])

    return docs.mapInArrow(run, schema)


def predictions(docs: DataFrame, per_language: int = PER_LANGUAGE) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row."""
    got = identify(docs.select(F.col("doc_id").cast("long"), "text"), train(docs, per_language))
    return got.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", F.col("score"))


def keep_identified(docs: DataFrame, least: float = 0.0, per_language: int = PER_LANGUAGE) -> DataFrame:
    """``docs`` without documents of no language (``und``) or with a score below ``least``; all columns stay."""
    names = docs.columns
    plain = docs.withColumnsRenamed({n: f"{n}__own" for n in names if n in ("lang_pred", "score")})
    got = identify(plain, train(docs, per_language)).filter((F.col("lang_pred") != "und") & (F.col("score") >= least))
    return got.drop("lang_pred", "score").withColumnsRenamed({f"{n}__own": n for n in names if n in ("lang_pred", "score")})
