"""Toxicity by a weighted lexicon that an Aho-Corasick automaton matches on folded text.

Folding lower-cases, maps homoglyphs and digit or sign substitutions to letters and turns every
run of other characters into one space, so entries are anchored at word starts (stems) or at both
ends (words). At each word the longest entry counts; entries inside an exception phrase do not.
The sums are normalised by the text's length and calibrated by a logistic fit.

Weights, exception phrases and the calibration are learnt from labelled rows, at most
``max_train_rows`` of them, taken by a hash of the id; one part of them yields the lexicon, the
other the calibration. Every row is scored on its whole text.

Defined cases: a null or empty text has no hits and gets the calibrated score of such a text; a
null doc_id is scored and is never held out; repeated rows are scored each; labels that repeat
count once (the larger); without labelled rows of both kinds every score is 0.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadlab.llm.common import RowBuffer, arrow_rows, table, tidy

# Look-alike letters and the letters they stand for; digits and signs used as letters.
HOMOGLYPHS = str.maketrans("аеорсухіјѕһԁӏԛԝɡɑοαεικνρτυхᴀткм", "aeopcyxijshdlqwgaoaeiknptuxatkm")
DIGITS = str.maketrans("0134578", "oieastb")
SIGNS = str.maketrans("@$!|", "asii")
INVISIBLE = dict.fromkeys([0xAD, 0x200B, 0x200C, 0x200D, 0x2060, 0xFEFF])

LETTERS_LIKE = {**HOMOGLYPHS, **INVISIBLE}
MIXED_DIGITS = re.compile(r"(?<=[^\W\d_])[0134578]+(?=[^\W\d_])|\b[0134578](?=[^\W\d_]{2})|(?<=[^\W\d_]{2})[0134578]\b")
INNER_SIGNS = re.compile(r"[@$!|](?<=[^\W\d_].)(?=[^\W\d_])")
FOREIGN_MARKS = re.compile(r"[^\x00-\x7f\w]+")
# ASCII: letters in lower case (l as i, for 1 stands for either), digits as they are, all else a space; other bytes stay
BYTES = bytes(ord("i") if chr(b) in "lL" else b + 32 if 65 <= b <= 90 else b if b > 127 or chr(b).isalnum() else 32 for b in range(256))
STEM_LENGTHS = range(3, 11)


def fold(text: str | None) -> str:
    """Folded text: words between single spaces, with one space at either end."""
    if not text:
        return " "
    if not text.isascii():
        text = FOREIGN_MARKS.sub(" ", text.lower().translate(LETTERS_LIKE))
    if "$" in text or "@" in text or "!" in text or "|" in text:
        text = INNER_SIGNS.sub(lambda m: m[0].translate(SIGNS), text)
    words = text.encode("utf-8", "surrogatepass").translate(BYTES).decode("utf-8", "surrogatepass").split()
    if any(d in text for d in "0134578"):
        words = [w if w.isalpha() else MIXED_DIGITS.sub(lambda m: m[0].translate(DIGITS), w) for w in words]
    return f" {' '.join(words)} " if words else " "


@dataclass
class Lexicon:
    """Entries (' stem' or ' word ') with weights, exception phrases (' a b '), and the calibration."""

    weights: dict[str, float] = field(default_factory=dict)
    exceptions: set[str] = field(default_factory=set)
    coefficients: tuple[float, ...] = ()
    _automaton: object = None

    def automaton(self):
        if self._automaton is None:
            import ahocorasick

            found = ahocorasick.Automaton()
            for entry, w in self.weights.items():
                found.add_word(entry, (len(entry), w, entry))
            for phrase in self.exceptions:
                found.add_word(phrase, (len(phrase), None, phrase))
            found.make_automaton()
            self._automaton = found
        return self._automaton

    def __getstate__(self):
        return {"weights": self.weights, "exceptions": self.exceptions, "coefficients": self.coefficients, "_automaton": None}

    def hits(self, folded: str) -> list[tuple[int, str, float]]:
        """(start, entry, weight): the longest entry at each word start outside exception phrases."""
        if not self.weights:
            return []
        best: dict[int, tuple[int, str, float]] = {}
        spared: list[tuple[int, int]] = []
        for end, (size, w, entry) in self.automaton().iter(folded):
            start = end - size + 1
            if w is None:
                spared.append((start, end))
            elif start not in best or best[start][0] < size:
                best[start] = (size, entry, w)
        if not spared:
            return [(at, entry, w) for at, (_, entry, w) in sorted(best.items())]
        return [(at, entry, w) for at, (size, entry, w) in sorted(best.items()) if not any(a <= at and at + size - 2 <= b for a, b in spared)]

    def features(self, text: str | None) -> list[float]:
        folded = fold(text)
        n_words = max(1, folded.count(" ") - 1)
        found = self.hits(folded)
        total = sum(w for _, _, w in found)
        names = {e for _, e, _ in found}
        return [math.log1p(total), math.log1p(1000 * total / n_words), math.log1p(100 * total / math.sqrt(n_words)), math.log1p(len(names)), max((w for _, _, w in found), default=0.0), math.log1p(n_words)]

    def score(self, text: str | None) -> float:
        if not self.coefficients:
            return 0.0
        z = self.coefficients[0] + float(np.dot(self.coefficients[1:], self.features(text)))
        return 1.0 / (1.0 + math.exp(-max(-35.0, min(35.0, z))))


def stems_of(folded: str) -> Counter:
    """How often each stem and whole word occurs in a text."""
    out: Counter = Counter()
    for word, n in Counter(folded.split()).items():
        for k in STEM_LENGTHS:
            if len(word) < k:
                break
            out[" " + word[:k]] += n
        if len(word) >= 3:
            out[f" {word} "] += n
    return out


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 60) -> tuple[float, ...]:
    """Ridge-penalised logistic regression by damped Newton steps."""
    scale = x.std(0)
    scale[scale == 0] = 1.0
    a = np.hstack([np.ones((len(x), 1)), x / scale])
    beta = np.zeros(a.shape[1])
    penalty = np.full(a.shape[1], ridge * max(1.0, len(x) / 1000))
    penalty[0] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ beta, -35, 35)))
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + np.diag(penalty + 1e-9), a.T @ (y - p) - penalty * beta)
        beta += step / max(1.0, np.abs(step).max() / 5)
        if np.abs(step).max() < 1e-7:
            break
    return (float(beta[0]), *(beta[1:] / scale).tolist())


def choose_entries(rows: Iterable[tuple[str, int, int, int, int]], words_toxic: int, words_clean: int, docs_toxic: int, docs_clean: int, most: int) -> dict[str, float]:
    """Entries and weights from counts (entry, occurrences and documents among toxic and clean rows).

    The weight is the log ratio of smoothed rates; an entry needs several toxic rows and a ratio that
    is well above chance. Of nested stems the shorter stays unless the longer one says clearly more.
    """
    kept: dict[str, tuple[float, float]] = {}
    for entry, t_n, t_docs, c_n, c_docs in rows:
        if t_docs < 3:
            continue
        w = math.log((t_n + 0.5) / (words_toxic + 1)) - math.log((c_n + 0.5) / (words_clean + 1))
        share = math.log((t_docs + 0.5) / (docs_toxic + 1)) - math.log((c_docs + 0.5) / (docs_clean + 1))
        error = math.sqrt(1 / (t_docs + 0.5) + 1 / (c_docs + 0.5))
        if min(w, share + 1.0) >= 1.2 and share / error >= 1.9:
            kept[entry] = (w, share / error * math.sqrt(t_docs))
    chosen: dict[str, float] = {}
    for entry in sorted(kept, key=lambda e: (len(e.strip()), e.endswith(" "), e)):
        stem = entry.rstrip()
        above = max((chosen[p] for k in range(4, len(stem) + (entry != stem)) if (p := stem[:k]) in chosen), default=None)
        if above is None or kept[entry][0] > above + 0.7:
            chosen[entry] = kept[entry][0]
    best = sorted(chosen, key=lambda e: (-kept[e][1], e))[:most]
    return {e: min(8.0, chosen[e]) for e in best}


def labelled_sample(docs: DataFrame, labels: DataFrame, usable: Column, label_col: str, max_rows: int, id_col: str, text_col: str) -> DataFrame:
    """(id, text, label, part) of at most about ``max_rows`` usable labelled rows, by a hash of the id.

    The chosen labels are that few, so they are sent to the documents and no text is shuffled.
    """
    y = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("label")).filter("id IS NOT NULL AND label IS NOT NULL").groupBy("id").agg(F.max("label").alias("label"))
    y = y.withColumn("usable", usable).filter("usable")
    n = y.count()
    draw = F.pmod(F.xxhash64("id", F.lit(29)), F.lit(1 << 30)) / float(1 << 30)
    if n > max_rows:
        y = y.filter(draw < max_rows / n)
    part = F.pmod(F.xxhash64("id", F.lit(31)), F.lit(10)).cast("int")
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(y.select("id", "label")), "id").withColumn("part", part)


def fit_lexicon(sample: DataFrame, most_entries: int = 4000, most_candidates: int = 60_000) -> Lexicon:
    """Learn entries on parts 0-6 of the sample, exception phrases there too, the calibration on 7-9."""
    sample = sample.persist()
    try:
        learn, calibrate = sample.filter("part < 7"), sample.filter("part >= 7")

        def count(wanted: frozenset | None):
            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                n: dict[int, Counter] = {0: Counter(), 1: Counter()}
                docs: dict[int, Counter] = {0: Counter(), 1: Counter()}
                words, rows = [0, 0], [0, 0]
                for text, label in arrow_rows(batches, "text", "label"):
                    folded, y = fold(text), int(label > 0)
                    words[y] += folded.count(" ") - 1
                    rows[y] += 1
                    if wanted is None and not y:
                        continue
                    found = stems_of(folded)
                    if wanted is not None:
                        found = Counter({k: found[k] for k in found.keys() & wanted})
                    n[y].update(found)
                    docs[y].update(found.keys())
                keys = sorted(n[0].keys() | n[1].keys())
                out = {"entry": keys, "t_n": [n[1][k] for k in keys], "t_docs": [docs[1][k] for k in keys], "c_n": [n[0][k] for k in keys], "c_docs": [docs[0][k] for k in keys]}
                out = {k: v + [("" if k == "entry" else {"t_n": words[1], "t_docs": rows[1], "c_n": words[0], "c_docs": rows[0]}[k])] for k, v in out.items()}
                yield pa.RecordBatch.from_pydict(out, pa.schema([("entry", pa.string()), *((k, pa.int64()) for k in ("t_n", "t_docs", "c_n", "c_docs"))]))

            found = learn.select("text", "label").mapInArrow(tidy(run), "entry string, t_n long, t_docs long, c_n long, c_docs long")
            return found.groupBy("entry").agg(*(F.sum(k).alias(k) for k in ("t_n", "t_docs", "c_n", "c_docs")))

        first = count(None).filter("t_docs >= 3").orderBy(F.desc("t_docs"), "entry").limit(most_candidates + 1)
        wanted = frozenset(r.entry for r in first.select("entry").collect() if r.entry)
        if not wanted:
            return Lexicon()
        rows = [tuple(r) for r in count(wanted).collect()]
        totals = next(r for r in rows if not r[0])
        if not totals[2] or not totals[4]:
            return Lexicon()
        lexicon = Lexicon(choose_entries((r for r in rows if r[0]), totals[1], totals[3], totals[2], totals[4], most_entries))
        lexicon.exceptions = learn_exceptions(learn, lexicon)

        def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                x = [[*lexicon.features(t), float(y > 0)] for (t, y) in arrow_rows([b], "text", "label")]
                yield pa.RecordBatch.from_pydict({"x": x}, pa.schema([("x", pa.list_(pa.float64()))]))

        got = np.array([r.x for r in calibrate.select("text", "label").mapInArrow(tidy(measure), "x array<double>").collect()])
        if len(got) and 0 < got[:, -1].sum() < len(got):
            lexicon.coefficients = fit_logistic(got[:, :-1], got[:, -1])
        else:
            lexicon.coefficients = (math.log(totals[2] / totals[4]) - 1.0, 0.0, 0.5, 0.0, 0.0, 0.0, 0.0)
        return lexicon
    finally:
        sample.unpersist()


def learn_exceptions(learn: DataFrame, lexicon: Lexicon, least: int = 3, most: int = 2000) -> set[str]:
    """Two-word phrases around a hit that several clean rows hold and no toxic row does."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: dict[int, Counter] = {0: Counter(), 1: Counter()}
        for text, label in arrow_rows(batches, "text", "label"):
            folded = fold(text)
            phrases = set()
            for at, _, _ in lexicon.hits(folded):
                end = folded.index(" ", at + 1)
                before, after = folded.rfind(" ", 0, at), folded.find(" ", end + 1)
                if after > 0:
                    phrases.add(folded[at : after + 1])
                if before >= 0:
                    phrases.add(folded[before : end + 1])
            out[int(label > 0)].update(phrases)
        keys = sorted(out[0].keys() | out[1].keys())
        yield pa.RecordBatch.from_pydict({"phrase": keys, "t": [out[1][k] for k in keys], "c": [out[0][k] for k in keys]}, pa.schema([("phrase", pa.string()), ("t", pa.int64()), ("c", pa.int64())]))

    found = learn.select("text", "label").mapInArrow(tidy(run), "phrase string, t long, c long").groupBy("phrase").agg(F.sum("t").alias("t"), F.sum("c").alias("c"))
    rows = found.filter((F.col("t") == 0) & (F.col("c") >= least)).orderBy(F.desc("c"), "phrase").limit(most).collect()
    return {r.phrase for r in rows}


def score_toxicity(docs: DataFrame, lexicon: Lexicon, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, toxicity) of every row."""
    id_type = docs.schema[id_col].dataType
    schema = pa.schema([("id", pa.int64()), ("toxicity", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = RowBuffer(schema)
        for doc_id, text in arrow_rows(batches, "id", "text"):
            if out.add(doc_id, lexicon.score(text)):
                yield out.take()
        if len(out):
            yield out.take()

    scored = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy(run), "id long, toxicity double")
    return scored.select(F.col("id").cast(id_type).alias("id"), "toxicity")


def drop_toxic(docs: DataFrame, lexicon: Lexicon, threshold: float = 0.3, text_col: str = "text") -> DataFrame:
    """Rows of ``docs`` (all columns) that score below the threshold; nothing is shuffled."""

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array([lexicon.score(t) < threshold for (t,) in arrow_rows([b], text_col)], pa.bool_()))

    return docs.mapInArrow(tidy(keep), docs.schema)


def held_out(c: Column, modulus: int, rest: int) -> Column:
    return F.coalesce(F.crc32(c.cast("string")) % modulus == rest, F.lit(False))


def fit_for(docs: DataFrame, labels: DataFrame, max_train_rows: int = 12_000) -> Lexicon:
    """The lexicon that the contract's training rows give."""
    return fit_lexicon(labelled_sample(docs, labels, ~held_out(F.col("id"), 4, 2), "toxic", max_train_rows, "doc_id", "text"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score_toxicity(docs, fit_for(docs, table(spark, sf_dir, "labels")))
    return scored.select(F.col("id").alias("doc_id"), held_out(F.col("id"), 4, 2).alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= 0.3).cast("int").alias("predicted"))


QUERIES = {"op4_toxicity": op4_toxicity}
