"""Operator 8: toxicity by a weighted lexicon on folded text."""

from __future__ import annotations

import math
import unicodedata
from collections import Counter
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize, tidy

#: Bound of the labelled rows that the lexicon is learned from, by label 1 and 0. All texts are used whole.
FIT_ROWS = {1: 3000, 0: 9000}
#: Terms of fewer toxic documents are not considered, as a share and at least; at most so many are.
LEAST_SHARE, LEAST_DOCS, MOST_TERMS = 0.004, 3, 20_000
#: Clean documents that a term may have for each toxic one: one chance hit weighs little, several weigh enough.
MOST_CLEAN = 0.5
#: Log-odds that a term must have.
LEAST_WEIGHT = 1.5
#: Chance that any term at all is taken which toxic documents have no more often than others.
CHANCE = 0.01
#: Lengths of word beginnings that can be terms, beside whole words.
PREFIXES = range(3, 9)
THRESHOLD = 0.7
#: Phrases in which a term means no harm.
EXCEPTIONS = ("trash can", "trash bin", "trash collection", "clown fish", "class clown", "loser bracket", "pathetic fallacy")

#: Look-alikes of Latin letters, and digits and signs that stand for letters.
#: l and 1 can stand for i, so i and l are one letter here.
HOMOGLYPHS = {
    "а": "a", "в": "b", "с": "c", "ԁ": "d", "е": "e", "ғ": "f", "ɡ": "g", "һ": "h", "і": "i", "ј": "j", "к": "k", "ӏ": "i", "м": "m", "н": "h", "о": "o", "р": "p", "ԛ": "q", "г": "r", "ѕ": "s", "т": "t", "у": "y", "ѵ": "v", "ԝ": "w", "х": "x",
    "α": "a", "β": "b", "ε": "e", "η": "n", "ι": "i", "κ": "k", "μ": "u", "ν": "v", "ο": "o", "ρ": "p", "τ": "t", "υ": "u", "χ": "x", "γ": "y", "ω": "w", "σ": "o", "ı": "i", "ł": "i", "ø": "o", "đ": "d", "ħ": "h", "ŧ": "t",
}
DIGITS = {"0": "o", "1": "i", "2": "z", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g"}
SIGNS = {"@": "a", "$": "s", "!": "i", "|": "i", "€": "e", "£": "i"}


class _Fold(dict):
    """Code point -> what it counts as; filled as code points occur."""

    def __missing__(self, code: int) -> str:
        c = chr(code)
        plain = unicodedata.normalize("NFKC", c.lower()).lower()  # accents stay: they tell words apart
        out = "".join(HOMOGLYPHS.get(x, DIGITS.get(x, x)) for x in plain).replace("l", "i")
        if unicodedata.category(c) in ("Cf", "Mn", "Me"):
            out = ""
        elif not out.isalnum():
            out = " "
        self[code] = out
        return out


_FOLD = _Fold()


def fold(text: str) -> str:
    """Folded words between single blanks. A sign counts as a letter where a letter follows and no sign goes before."""
    for sign, letter in SIGNS.items():
        if sign in text:
            parts = text.split(sign)
            text = parts[0]
            for p in parts[1:]:
                text += (letter if p[:1].isalpha() and not text.endswith(tuple(SIGNS)) else sign) + p
    return f" {' '.join(text.translate(_FOLD).split())} "


def terms(text: str) -> set[str]:
    """Whole words ' word ' and beginnings ' begi' of a folded text."""
    out = set()
    for w in set(fold(text).split()):
        out.add(f" {w} ")
        out.update(f" {w[:n]}" for n in PREFIXES if len(w) > n)
    return out


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % 3 == 1


class Lexicon:
    """Terms with weights, and the curve that turns a document's sum and length into a score."""

    def __init__(self, weights: dict[str, float], curve: tuple[float, float, float] = (-2.0, 0.0, 0.0), exceptions: tuple[str, ...] = EXCEPTIONS):
        self.weights, self.curve, self.exceptions = weights, curve, exceptions

    def automaton(self) -> ahocorasick.Automaton:
        a = ahocorasick.Automaton()
        for t, w in self.weights.items():
            a.add_word(t, (len(t), w))
        for p in self.exceptions:
            t = fold(p)
            a.add_word(t, (len(t), self.weights.get(t, 0.0) and 0.0))
        a.make_automaton()
        return a

    def features(self, a: ahocorasick.Automaton, text: str) -> tuple[float, float]:
        """Log of the matched weight, and log of the number of words."""
        x = fold(text)
        hits, spared = [], []
        if len(a):
            for end, (n, w) in a.iter(x):
                (hits if w else spared).append((end - n + 1, end, w))
        # a beginning's match has no closing blank, so spans compare by where a word starts
        total = sum(w for s, e, w in hits if not any(b <= s and e <= f for b, f, _ in spared))
        return math.log1p(total), math.log1p(x.count(" ") - 1)

    def score(self, f: tuple[float, float]) -> float:
        b0, b1, b2 = self.curve
        z = b0 + (b1 * f[0] + b2 * f[1] if f[0] > 0 else 0.0)
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, z))))


def tail(n: int, mean: float) -> float:
    """Bound of the probability that a count of this mean (Poisson) is at least n."""
    if n <= mean:
        return 1.0
    return min(1.0, math.exp(n * math.log(mean) - mean - math.lgamma(n + 1)) / (1 - mean / (n + 1)))


def select_terms(found: list[set[str]], n_toxic: Counter, n_clean: Counter, clean_docs: int, least: int, tried: int = 1) -> dict[str, float]:
    """Weights of the terms that together explain the toxic documents.

    Taken greedily by how many toxic documents a term explains that no former one does, less the
    clean ones it is in; so words that merely stand beside a term, as in families of near copies, stay out.
    So do those that so many toxic documents could have by chance, by the clean ones' share and the number of terms ``tried``.
    Ties go to the greater weight, then to whole words, then to the shorter term, then by code point.
    """
    toxic_docs = len(found)
    weight = {t: math.log((n + 0.5) / (toxic_docs + 1)) - math.log((n_clean[t] + 0.5) / (clean_docs + 1)) for t, n in n_toxic.items() if n >= least}
    chance = lambda t: tail(n_toxic[t], toxic_docs * (n_clean[t] + 0.5) / (clean_docs + 1)) * tried
    left = {t for t, w in weight.items() if w >= LEAST_WEIGHT and n_clean[t] <= MOST_CLEAN * n_toxic[t] and chance(t) <= CHANCE}
    docs = [d & left for d in found]
    gain = Counter(t for d in docs for t in d)
    by_term: dict[str, list[int]] = {}
    for i, d in enumerate(docs):
        for t in d:
            by_term.setdefault(t, []).append(i)
    open_, out = [True] * len(docs), {}
    while gain:
        t = max(gain, key=lambda t: (gain[t] - n_clean[t], weight[t], t.endswith(" "), -len(t), t))
        if gain[t] - n_clean[t] < least:
            break
        out[t] = weight[t]
        for i in by_term[t]:
            if open_[i]:
                open_[i] = False
                gain.subtract(docs[i])
        del gain[t]
    # terms that explain as well as the chosen ones, document by document, are as good as these
    strong = max((n_toxic[t] for t in out), default=0)
    out |= {t: weight[t] for t in left if t.endswith(" ") and n_toxic[t] >= max(least, strong / 4) and t not in out and not any(t.startswith(o) for o in out)}
    return out


def fit_curve(x: np.ndarray, y: np.ndarray) -> tuple[float, float, float]:
    """Logistic curve on (1, log weight, log words if any weight), by Newton steps with a small penalty."""
    z = np.column_stack([np.ones(len(x)), x[:, 0], np.where(x[:, 0] > 0, x[:, 1], 0)])
    b, penalty = np.zeros(3), np.array([1e-3, 1e-2, 0.5])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(z @ b, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty), z.T @ (y - p) - penalty * b)
        b += step
        if np.abs(step).max() < 1e-8:
            break
    return tuple(b.tolist())


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Lexicon:
    """Learn from labelled rows that are not held out, at most FIT_ROWS of each label, chosen by a hash of the id.

    Whole texts count, equal ones once (toxic if any of them is); an id that is labelled twice is toxic if once it is;
    null ids and labels teach nothing. Without toxic rows, as in empty tables, the lexicon is empty and every score is low.
    """
    known = labels.select(F.col("doc_id").alias("_id"), F.col("toxic").cast("int").alias("_toxic")).where(F.col("_id").isNotNull() & F.col("_toxic").isin(0, 1) & ~held_out(F.col("_id")))
    known = known.groupBy("_id").agg(F.max("_toxic").alias("_toxic")).withColumn("_h", F.xxhash64("_id"))
    chosen = [known.where(F.col("_toxic") == y).orderBy("_h", "_id").limit(n) for y, n in FIT_ROWS.items()]
    chosen = F.broadcast(materialize(chosen[0].unionByName(chosen[1]).select("_id", "_toxic")))  # bounded by FIT_ROWS
    rows = docs.select(docs[id_col].alias("_id"), docs[text_col].alias("text")).join(chosen, "_id")
    rows = materialize(rows.groupBy("text").agg(F.max("_toxic").alias("toxic")))
    toxic, clean = rows.where("toxic = 1"), rows.where("toxic = 0")
    n_toxic_docs, n_clean_docs = toxic.count(), clean.count()
    least = max(LEAST_DOCS, round(LEAST_SHARE * n_toxic_docs)) if n_toxic_docs >= 20 else 2
    if not n_toxic_docs:
        return Lexicon({})

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([sorted(terms(t.as_py() or "")) for t in b.column(0)], pa.list_(pa.string()))], ["terms"])

    every = materialize(toxic.select("text").mapInArrow(tidy(listed), "terms array<string>").select(F.explode("terms").alias("term")).groupBy("term").count())
    common = every.where(F.col("count") >= least)
    n_toxic = Counter({r["term"]: r["count"] for r in common.orderBy(F.desc("count"), "term").limit(MOST_TERMS).collect()})

    def known_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([sorted(n_toxic.keys() & terms(t.as_py() or "")) for t in b.column(0)], pa.list_(pa.string()))], ["terms"])

    n_clean = clean.select("text").mapInArrow(tidy(known_terms), "terms array<string>").select(F.explode("terms").alias("term")).groupBy("term").count()
    n_clean = Counter({r["term"]: r["count"] for r in n_clean.collect()})  # at most MOST_TERMS rows
    rare = {t for t, n in n_toxic.items() if n_clean[t] <= MOST_CLEAN * n}

    def rare_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([sorted(rare & terms(t.as_py() or "")) for t in b.column(0)], pa.list_(pa.string()))], ["terms"])

    found = [set(r["terms"]) for r in toxic.select("text").mapInArrow(tidy(rare_terms), "terms array<string>").collect()]  # bounded by FIT_ROWS
    lexicon = Lexicon(select_terms(found, n_toxic, n_clean, n_clean_docs, least, every.count()))

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = lexicon.automaton()
        for b in batches:
            f = np.array([lexicon.features(a, t.as_py() or "") for t in b.column(0)]).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([pa.array(f[:, 0]), pa.array(f[:, 1]), b.column(1)], ["w", "n", "toxic"])

    seen = rows.select("text", "toxic").mapInArrow(tidy(measured), "w double, n double, toxic int").collect()  # three numbers a row, bounded by FIT_ROWS
    lexicon.curve = fit_curve(np.array([(r["w"], r["n"]) for r in seen]), np.array([float(r["toxic"]) for r in seen]))
    return lexicon


def scored(docs: DataFrame, lexicon: Lexicon, text_col: str = "text") -> DataFrame:
    """The documents' columns in _row, and score.

    Null and empty texts have no match and the score of such texts; equal texts have equal scores, repeated rows too;
    whole texts are matched, however long; an empty table gives no rows; columns may have any name.
    """

    @F.arrow_udf("double")
    @tidy
    def score(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        a = lexicon.automaton()
        for part in texts:
            yield pa.array([lexicon.score(lexicon.features(a, t.as_py() or "")) for t in part], pa.float64())

    return docs.select(F.struct(*[docs[f"`{c}`"] for c in docs.columns]).alias("_row"), score(docs[text_col]).alias("score"))


def accepted(docs: DataFrame, lexicon: Lexicon, threshold: float = THRESHOLD) -> DataFrame:
    """The documents that score below the threshold."""
    return scored(docs, lexicon).where(F.col("score") < threshold).select("_row.*")


def op8(docs: DataFrame, labels: DataFrame) -> DataFrame:
    x = scored(docs.select("doc_id", "text"), fit(docs, labels))
    return x.select(F.col("_row.doc_id").alias("doc_id"), held_out(F.col("_row.doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
