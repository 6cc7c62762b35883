"""Toxicity by noisy-channel deobfuscation.

A character trigram model over all documents tells likely letter sequences. Tokens that look disguised (digits
or signs among letters or alone, letters drawn out, letters or stand-ins spaced or dotted apart) become lattices of
what each character may stand for, and Viterbi picks the likeliest reading. The restored text is then scored by a
logistic model over words and word beginnings, learnt from labelled rows.

Fitting reads a sample of at most SAMPLE labelled rows (a documented parameter; the rows with the least hash of
their id) on which the given fold is left out; the character model and the scores cover every whole text.

Cases: null text = empty text, scored by the model's prior; no labels at all: every score is 0; labels that
repeat a document or are null: rows without a label are left out, repeats count each; an empty table gives no
rows; further columns are left alone; ties at the threshold count as toxic.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from congraph.llm.common import doc_text, slices, written

#: Most labelled rows that fitting reads.
SAMPLE = 40_000
#: Most features, and the least G-squared of one.
FEATURES, LEAST_G2 = 3000, 30.0
#: Lengths of word beginnings that are features beside the whole word.
HEADS = (4, 5, 6)

#: What a sign may stand for; fixed values.
LEET = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "(": "c", "<": "c", "€": "e", "£": "l", "¡": "i", "#": "h",
}
_FILL = frozenset(" .-_*~'`·/\\")
#: Log costs of the channel: a letter as itself, a stand-in, a filler dropped, a repeated letter dropped, a sign kept out, a space kept as a break.
SAME, STANDIN, DROP_FILL, DROP_REPEAT, DROP_SIGN, BREAK = -0.05, -1.2, -0.4, -0.5, -5.0, -0.7

_WORD = re.compile(r"[^\W\d_]+")
_DRAWN = re.compile(r"([^\W\d_])\1\1")
_ONE = rf"(?:[^\W\d_]|[{re.escape(''.join(LEET))}])"
_APART = re.compile(rf"(?<![^\s\"'\[(]){_ONE}(?:[\s.\-_*~]+{_ONE}){{2,}}(?=[\s.,;:!?\"')\]\-_*~]|$)")
_TAIL = re.compile(r"(?:([^\w\s])\1{2,}|[.,;:!?\"')\]]+)+$")
#: Letters of the model: a break, a to z, the Latin-1 small letters, any other.
LETTERS = 64


def letter_code(c: str) -> int:
    k = ord(c)
    if 0x61 <= k <= 0x7A:
        return k - 0x60
    if 0xDF <= k <= 0xFF:
        return 27 + k - 0xDF
    return 63 if c.isalpha() else 0


_CODES = np.array([letter_code(chr(k)) for k in range(0x250)], "u1")


def trigram_counts(text: str) -> np.ndarray:
    """Codes of the text's trigrams, with two breaks before it and one behind."""
    points = np.frombuffer(("  " + text.lower() + " ").encode("utf-32-le"), "<u4")
    codes = np.where(points < 0x250, _CODES[np.minimum(points, 0x24F)], 63).astype("i4")
    codes = codes[np.concatenate(([True], (codes[1:] != 0) | (codes[:-1] != 0)))]  # one break at a time
    codes = np.concatenate(([0], codes))
    return codes[:-2] * LETTERS * LETTERS + codes[1:-1] * LETTERS + codes[2:]


def _count_trigrams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.zeros(LETTERS**3, "i8")
    for batch in slices(batches):
        for text in batch.column("text").to_pylist():
            total += np.bincount(trigram_counts(text.decode()), minlength=LETTERS**3) if len(text) > 1 << 18 else 0
            if len(text) <= 1 << 18:
                np.add.at(total, trigram_counts(text.decode()), 1)
    at = np.flatnonzero(total)
    if len(at):
        yield pa.record_batch([pa.array(at.astype("i4")), pa.array(total[at])], names=["gram", "n"])


def character_model(rows: DataFrame) -> np.ndarray:
    """log P(letter | two before) of all texts, a table of LETTERS^3 numbers whatever the corpus."""
    counts = np.zeros(LETTERS**3)
    for r in rows.mapInArrow(_count_trigrams, "gram int, n long").groupBy("gram").agg(F.sum("n").alias("n")).toLocalIterator():
        counts[r.gram] = r.n
    counts = counts.reshape(LETTERS, LETTERS, LETTERS)
    one = counts.sum((0, 1)) + 1
    two = counts.sum(0) + 5 * one / one.sum()
    two /= two.sum(1, keepdims=True)
    three = counts + 5 * two[None]
    return np.log(three / three.sum(2, keepdims=True)).astype("f4")


def decode(token: str, model: np.ndarray) -> str:
    """The likeliest letters behind a token: Viterbi over (last two letters) and one lattice column a character."""
    # A reading is a chain (what came before, letter), so that long runs cost their length.
    paths: dict[tuple[int, int, str], tuple[float, tuple | None]] = {(0, 0, ""): (0.0, None)}
    for c in token:
        column: list[tuple[str, float]] = []
        if c.isalpha():
            column.append((c, SAME))
        column.extend((x, STANDIN) for x in LEET.get(c, ""))
        space = c.isspace()
        drop = DROP_FILL if space or c in _FILL else None if c.isalpha() and c not in LEET else DROP_SIGN
        new: dict[tuple[int, int, str], tuple[float, tuple | None]] = {}
        for (a, b, last), (score, out) in paths.items():
            for x, cost in column:
                k = letter_code(x)
                s = score + cost + model[a, b, k]
                if s > new.get((b, k, x), (-1e30,))[0]:
                    new[b, k, x] = (s, (out, x))
            if space and b:
                s = score + BREAK + model[a, b, 0]
                if s > new.get((b, 0, " "), (-1e30,))[0]:
                    new[b, 0, " "] = (s, (out, " "))
            repeat = last and (c == last or last in LEET.get(c, ""))
            if (cost := DROP_REPEAT if repeat else drop) is not None and score + cost > new.get((a, b, last), (-1e30,))[0]:
                new[a, b, last] = (score + cost, out)
        paths = new or paths
    out = max(((s + (model[a, b, 0] if b or not last else 0.0), out) for (a, b, last), (s, out) in paths.items()), key=lambda x: x[0])[1]
    letters = []
    while out is not None:
        out, x = out
        letters.append(x)
    return "".join(reversed(letters))


class Restorer:
    """Disguised tokens of a text and their readings; readings are kept for tokens that come again."""

    def __init__(self, model: np.ndarray):
        self.model, self.kept = model, {}

    def reading(self, token: str) -> str:
        got = self.kept.get(token)
        if got is None:
            if len(self.kept) > 200_000:
                self.kept.clear()
            got = self.kept[token] = decode(token, self.model)
        return got

    def cores(self, token: str) -> set[str]:
        """What a disguised token may hold: a sign at either end may be a mark or a stand-in, so both are read. None: plain."""
        if token.isalpha() or token[:-1].isalpha() and token[-1] not in LEET:
            return set()
        body = token.lstrip("\"'[")
        cores = {x.lstrip("\"'([") if cut else x for x in (_TAIL.sub("", body), body.rstrip(".,;:?\"')]")) for cut in (True, False)}
        return {c for c in cores if c and not c.isalpha() and any(x in LEET or x in _FILL for x in c) and any(x in LEET or x.isalpha() for x in c)}

    def words(self, text: str) -> set[str]:
        """Distinct words of the restored text: disguised tokens and runs of spaced letters stand as what they are read as."""
        text, words = text.lower(), set()
        apart = [m.group() for m in _APART.finditer(text)]
        for run in apart:
            words.update(_WORD.findall(self.reading(run)))
        for token in set((_APART.sub(" ", text) if apart else text).split()):
            if cores := self.cores(token):
                for core in cores:
                    words.update(_WORD.findall(self.reading(core)))
            elif _DRAWN.search(token):
                words.update(x for w in _WORD.findall(token) for x in _WORD.findall(self.reading(w) if _DRAWN.search(w) else w))
            else:
                words.update((token,) if token.isalpha() else _WORD.findall(token))
        return words

    def readings(self, text: str) -> list[str]:
        """text: in lower case. What its disguised parts are read as."""
        out = [self.reading(m.group()) for m in _APART.finditer(text)]
        for token in set(text.split()):
            out.extend(self.reading(c) for c in self.cores(token))
        out.extend(self.reading(w) for w in {m.group() for m in _WORD.finditer(text)} if _DRAWN.search(w))
        return out


def features_of(words: set[str]) -> set[str]:
    out = {"=" + w for w in words}
    for n in HEADS:
        out.update(w[:n] for w in words if len(w) >= n)
    return out


def _count_features(model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer, counts = Restorer(model.value), {}

        def flush():
            keys = list(counts)
            columns = [pa.array(keys, pa.string()), *(pa.array([counts[k][i] for k in keys], pa.int64()) for i in (0, 1))]
            counts.clear()
            return pa.record_batch(columns, names=["feature", "clean", "toxic"])

        for batch in slices(batches):
            for text, label in zip(batch.column("text").to_pylist(), batch.column("label").to_pylist()):
                for x in features_of(restorer.words(text.decode())):
                    counts.setdefault(x, [0, 0])[label] += 1
                if len(counts) > 300_000:
                    yield flush()
        if counts:
            yield flush()

    return run


def _presence(model, vocabulary):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer, index = Restorer(model.value), vocabulary.value
        for batch in slices(batches):
            rows = [sorted(index[x] for x in features_of(restorer.words(t.decode())) if x in index) for t in batch.column("text").to_pylist()]
            yield pa.record_batch([batch.column("label"), pa.array(rows, pa.list_(pa.int32()))], names=["label", "found"])

    return run


def fit(found: list[list[int]], labels: np.ndarray, width: int, l2: float = 1.0, steps: int = 300) -> np.ndarray:
    """Weights and, last, the intercept of a logistic model over presence; accelerated gradient steps."""
    row = np.repeat(np.arange(len(found)), [len(x) for x in found])
    column = np.concatenate([np.asarray(x, "i8") for x in found]) if len(row) else np.empty(0, "i8")
    weights, ahead = np.zeros(width + 1), np.zeros(width + 1)
    weights[-1] = ahead[-1] = math.log((labels.sum() + 0.5) / (len(labels) - labels.sum() + 0.5))
    most = max([1, *(len(x) for x in found)])
    step = 4.0 / ((most + 1) * max(1, np.bincount(column, minlength=1).max(initial=1)) ** 0.5 + l2) if len(row) else 0.0
    for t in range(steps if len(row) else 0):
        z = np.bincount(row, ahead[column], minlength=len(found)) + ahead[-1]
        error = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - labels
        slope = np.append(np.bincount(column, error[row], minlength=width) + l2 * ahead[:-1], 0.0)
        scale = np.append(1 / (0.25 * np.sqrt(np.bincount(column, minlength=width) + 1.0) * 4 + l2), 0.0)
        new = ahead - np.minimum(step, scale) * slope
        ahead = new + t / (t + 3) * (new - weights)
        weights = new
    return weights


def _score(model, vocabulary, weights):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer, index, w = Restorer(model.value), vocabulary.value, weights.value
        least = min(HEADS)
        heads = {x.lstrip("=")[:least] for x in index}
        for batch in slices(batches):
            scores = []
            for text in batch.column("text").to_pylist():
                words = {x for x in restorer.words(text.decode()) if x[:least] in heads}
                z = w[-1] + sum(w[index[x]] for x in features_of(words) if x in index)
                scores.append(1 / (1 + math.exp(-max(-30.0, min(30.0, z)))))
            yield pa.record_batch([batch.column("doc_id"), pa.array(scores, pa.float64())], names=["doc_id", "score"])

    return run


def _g2(clean: Column, toxic: Column, all_clean: int, all_toxic: int) -> Column:
    """Log-likelihood ratio of presence against the label."""
    total = all_clean + all_toxic
    terms = []
    for n, marginal in ((clean, all_clean), (toxic, all_toxic)):
        for own, seen in ((n, clean + toxic), (F.lit(marginal) - n, F.lit(total) - clean - toxic)):
            expected = seen * F.lit(marginal / total)
            terms.append(F.when(own > 0, own * F.log(own / expected)).otherwise(0.0))
    return 2 * sum(terms[1:], terms[0])


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def _fitted(rows: DataFrame, labels: DataFrame, sample: int) -> tuple | None:
    """Broadcast character model, features and weights; None without labels."""
    spark = rows.sparkSession
    model = spark.sparkContext.broadcast(character_model(rows))
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("label")).where("doc_id is not null and label in (0, 1)")
    known = known.where(~held_out(F.col("doc_id"))).orderBy(F.xxhash64("doc_id"), "doc_id", "label").limit(sample)
    # At most `sample` rows of 12 bytes.
    train = written(rows.join(F.broadcast(known), "doc_id").select("text", "label"), "labelled").repartition(max(1, spark.sparkContext.defaultParallelism))
    sizes = {r.label: r.n for r in train.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not sizes:
        return None
    counted = train.mapInArrow(_count_features(model), "feature string, clean long, toxic long").groupBy("feature").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    g2 = _g2(F.col("clean"), F.col("toxic"), sizes.get(0, 0), sizes.get(1, 0))
    best = counted.where("clean + toxic >= 5").withColumn("g2", g2).where(F.col("g2") >= LEAST_G2).orderBy(F.desc("g2"), "feature").limit(FEATURES)
    index = {r.feature: i for i, r in enumerate(best.select("feature").collect())}
    vocabulary = spark.sparkContext.broadcast(index)
    seen = train.mapInArrow(_presence(model, vocabulary), "label int, found array<int>").collect()
    weights = spark.sparkContext.broadcast(fit([r.found for r in seen], np.array([r.label for r in seen], "f8"), len(index)))
    return model, vocabulary, weights


def score_toxicity(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted, one row for each row of docs."""
    rows = doc_text(docs)
    fitted = _fitted(rows, labels, sample)
    if fitted is None:
        scored = rows.select("doc_id", F.lit(0.0).alias("score"))
    else:
        scored = rows.mapInArrow(_score(*fitted), "doc_id long, score double")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """docs without the rows that are predicted toxic. Each row goes by its own text, whatever id it has."""
    rows = doc_text(docs)
    fitted = _fitted(rows, labels, sample)
    if fitted is None:
        return docs
    score = _score(*fitted)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            text = batch.column("text")
            text = (text if pa.types.is_string(text.type) else text.cast(pa.string())).fill_null("").cast(pa.binary())
            own = pa.record_batch([pa.nulls(batch.num_rows, pa.int64()), text], names=["doc_id", "text"])
            for marks in score(iter([own])):
                yield batch.filter(pa.array(marks.column("score").to_numpy() < 0.5))

    # The rows pass whole; a slice of them at a time is looked at.
    return docs.mapInArrow(keep, docs.schema)
