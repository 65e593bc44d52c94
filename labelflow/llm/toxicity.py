"""Toxicity scoring by maximum-scoring segments over token log-odds.

Training counts, over all labelled training documents, in how many toxic and other documents a token occurs (a word, or the
first 4, 5 or 6 letters of a longer one), and turns the counts into log-odds under a Dirichlet prior of the joint
frequencies. Tokens are kept whose support is real: enough toxic documents and enough different following words, so that the
copies of one document do not vouch for its rare words. Tokens score their own log-odds where these differ significantly from
zero, for or (words only) against; every word without positive ones costs a drift besides, which keeps the background's mean
negative, as the theory needs. A linear scan finds all maximal segments of positive total; the best is normalised by
extreme-value theory (scale from the background's scores and their rates a word, minus the log of the length), and a logistic
model over that, the number and the sum of significant segments gives the score.

Every token with support is scored; only those whose log-odds pass the tests come to the driver. Bounds, all parameters:
`calibration_rows` labelled rows for the logistic model, and `most_terms` selected tokens, beyond which training refuses and cuts
nothing. Up to `shared_terms` candidates the counts of other documents are kept for these alone, beyond that for all tokens, with
equal results. Counts are over all rows. Defined results: a null or empty text has no segments and gets the score of such texts; a label is toxic if
any of a document's label rows is; null labels are ignored; without any labelled training row of both kinds every score is
the smoothed base rate. Other columns pass through untouched.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.llm.common import arrow_rows, binary_text, doc_bucket, materialise, release
from labelflow.plans.joins import lookup

PREFIXES = (4, 5, 6)
CACHE = 400_000
#: Texts that a task holds as Python objects at once, and that training sends it in one batch; scored rows go back in batches of as many.
ROWS_AT_ONCE = 1_000
#: Stands for the number of words; no token is empty.
WORDS = b""
_SEPARATORS = bytes(b for b in range(128) if not (48 <= b <= 57 or 97 <= b <= 122))
_TO_SPACE = bytes.maketrans(_SEPARATORS, b" " * len(_SEPARATORS))


def words_of(raw: bytes) -> list[bytes]:
    """Lower-case words: runs of letters and digits; any non-ASCII character counts as a letter."""
    return raw.decode("utf-8", "replace").lower().encode("utf-8", "replace").translate(_TO_SPACE).split()


def tokens_of(word: bytes) -> list[bytes]:
    """The word and its prefixes, marked so that a prefix never equals a word."""
    if len(word) <= PREFIXES[0]:
        return [word]
    letters = word.decode("utf-8", "replace")
    return [word, *(b"^" + letters[:k].encode() for k in PREFIXES if len(letters) > k)]


@dataclass
class ToxicityModel:
    odds: dict[bytes, float] = field(default_factory=dict)
    drift: float = 0.25
    scale: float = 1.0
    least: float = 2.0
    weights: tuple[float, ...] = (0.0, 0.0, 0.0, 0.0)

    def word_score(self, word: bytes) -> float:
        """The largest positive log-odds of a word and its prefixes, else the word's own negative ones less the drift; 0 if none are known."""
        found = [self.odds[t] for t in tokens_of(word) if t in self.odds]
        best = max(found, default=0.0)
        return best if best >= 0 else best - self.drift

    def segments(self, words: list[bytes], cache: dict[bytes, float]) -> list[tuple[int, int, float]]:
        """(first word, last word, total) of every maximal segment of positive total."""
        hits = []
        get = cache.get
        for i, w in enumerate(words):
            s = get(w)
            if s is None:
                if len(cache) >= CACHE:
                    cache.clear()
                s = cache[w] = self.word_score(w)
            if s:
                hits.append((i, s))
        return maximal_segments(hits, self.drift) if hits else []

    def features(self, segments: list[tuple[int, int, float]], n_words: int) -> tuple[float, float, float]:
        """Extreme-value height of the best segment, and how many and how much in total is significant."""
        if not segments:
            return 0.0, 0.0, 0.0
        room = math.log(n_words + 1.0)
        heights = [max(0.0, self.scale * s - room) for _, _, s in segments]
        strong = [h for h in heights if h >= self.least]
        return max(heights), math.log1p(len(strong)), math.log1p(sum(strong))

    def score(self, features: tuple[float, float, float]) -> float:
        z = self.weights[0] + sum(w * x for w, x in zip(self.weights[1:], features, strict=True))
        return 1.0 / (1.0 + math.exp(-min(50.0, max(-50.0, z))))


def maximal_segments(hits: list[tuple[int, float]], drift: float) -> list[tuple[int, int, float]]:
    """All maximal-scoring segments when words outside `hits` cost `drift`, in time linear in the hits.

    Each held segment knows the nearest earlier one whose total before it is smaller. A hit follows these links, and whatever
    it passes stands between two such segments from then on and is never looked at again."""
    held: list[tuple[int, int, float, float, int]] = []  # first, last, total before, total after, link
    total, last = 0.0, -1
    for at, s in hits:
        total -= drift * (at - last - 1)
        last = at
        if s <= 0:
            total += s
            continue
        first, before = at, total
        total += s
        j = len(held) - 1
        while True:
            while j >= 0 and held[j][2] >= before:
                j = held[j][4]
            if j < 0 or held[j][3] >= total:
                held.append((first, at, before, total, j))
                break
            first, _, before, _, link = held[j]
            del held[j:]
            j = link
    return [(a, b, after - before) for a, b, before, after, _ in held]


def _pieces(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    for at in range(0, batch.num_rows, ROWS_AT_ONCE):
        yield batch.slice(at, ROWS_AT_ONCE)


def _raw_texts(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of a column of texts or bytes; null counts as empty."""
    return [raw or b"" for raw in column.cast(pa.binary()).to_pylist()]


def _count_toxic(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Per task: documents of each token, and 64 marks of the words that follow it."""
    held: dict[bytes, list[int]] = {}

    def out() -> pa.RecordBatch:
        names = list(held)
        marks = np.array([held[t][1] for t in names], np.uint64).view(np.int64) if names else np.empty(0, np.int64)
        return pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), pa.array([held[t][0] for t in names], pa.int64()), pa.array(marks, pa.int64())], names=["token", "n", "marks"])

    for batch in batches:
        for raw in batch.column(0).to_pylist():
            words = words_of(raw)
            seen: dict[bytes, int] = {}
            for w, after in zip(words, [*words[1:], b""], strict=True):
                mark = 1 << (xxhash.xxh64_intdigest(after) & 63)
                seen[w] = seen.get(w, 0) | mark
            tokens: dict[bytes, int] = {}
            for w, m in seen.items():
                for t in tokens_of(w):
                    tokens[t] = tokens.get(t, 0) | m
            for t, m in tokens.items():
                x = held.get(t)
                if x is None:
                    held[t] = [1, m]
                else:
                    x[0] += 1
                    x[1] |= m
            if len(held) >= CACHE:
                yield out()
                held.clear()
    yield out()


def _count_other(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Per task: documents of each token; and, under the name WORDS, how many words there are. It knows no candidates: their number
    grows with the corpus, and so would the rows of equal tasks."""
    held: dict[bytes, int] = {WORDS: 0}
    cache: dict[bytes, list[bytes]] = {}

    def out() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array(list(held.values()), pa.int64())], names=["token", "n"])

    for batch in batches:
        for raw in batch.column(0).to_pylist():
            found: set[bytes] = set()
            words = words_of(raw)
            held[WORDS] = held.get(WORDS, 0) + len(words)
            for w in set(words):
                t = cache.get(w)
                if t is None:
                    if len(cache) >= CACHE:
                        cache.clear()
                    t = cache[w] = tokens_of(w)
                found.update(t)
            for t in found:
                held[t] = held.get(t, 0) + 1
            if len(held) >= CACHE:
                yield out()
                held.clear()
    yield out()


def _score_rows(model: ToxicityModel, text: str, with_features: bool):
    """Adds to rows the score of their column `text`, or puts its features in that column's place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache: dict[bytes, float] = {}
        for batch in batches:
            at = batch.schema.get_field_index(text)
            for piece in _pieces(batch):
                feats = []
                for raw in _raw_texts(piece.column(at)):
                    words = words_of(raw)
                    feats.append(model.features(model.segments(words, cache), len(words)))
                keep = [i for i in range(piece.num_columns) if i != at or not with_features]
                cols, names = [piece.column(i) for i in keep], [piece.schema.names[i] for i in keep]
                if with_features:
                    cols += [pa.array([f[k] for f in feats], pa.float64()) for k in range(3)]
                    names += ["_f0", "_f1", "_f2"]
                else:
                    cols.append(pa.array([model.score(f) for f in feats], pa.float64()))
                    names.append("_score")
                yield pa.RecordBatch.from_arrays(cols, names=names)

    return run


def passages(model: ToxicityModel, text: str | None) -> list[tuple[int, int, float]]:
    """The significant passages of a text as word ranges with their totals."""
    words = words_of((text or "").encode())
    room = math.log(len(words) + 1.0)
    return [s for s in model.segments(words, {}) if model.scale * s[2] - room >= model.least]


def _scale(odds: dict[bytes, float], rates: dict[bytes, float], drift: float) -> float:
    """The positive root of E[exp(root * score)] = 1 over background words: the extreme-value scale of segment totals."""
    hits = sum(rates.values())
    total = max(1.0, hits)
    value = lambda t: odds[t] if odds[t] >= 0 else odds[t] - drift
    moment = lambda x: (1.0 - hits / total) * math.exp(-x * drift) + sum(r / total * math.exp(min(700.0, x * value(t))) for t, r in rates.items())
    if not rates or moment(1e-6) >= 1.0:
        return 1.0
    low, high = 1e-6, 1.0
    while moment(high) < 1.0 and high < 64:
        high *= 2
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if moment(mid) < 1.0 else (low, mid)
    return low


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 40) -> tuple[float, ...]:
    x = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(x.shape[1])
    w[0] = math.log((y.sum() + 1.0) / (len(y) - y.sum() + 1.0))
    penalty = np.diag([1e-6] + [ridge] * (x.shape[1] - 1))
    for _ in range(rounds):
        p = 1.0 / (1.0 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + penalty, x.T @ (y - p) - penalty @ w)
        w += np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-6:
            break
    return tuple(float(v) for v in w)


def train(docs: DataFrame, labels: DataFrame, **bounds) -> ToxicityModel:
    """Fits on labelled rows outside the held-out quarter (crc32 of the decimal id, modulo 4, is 2); `bounds` are those of _train."""
    with arrow_rows(docs.sparkSession, ROWS_AT_ONCE):
        return _train(docs, labels, **bounds)


def _train(docs: DataFrame, labels: DataFrame, shared_terms: int = 50_000, most_terms: int = 1_000_000, calibration_rows: int = 20_000, prior: float = 20.0, support: int = 3, contexts: int = 4, least_odds: float = 2.0) -> ToxicityModel:
    ids = F.col("doc_id").cast("long").alias("doc_id")
    marks = labels.select(ids, F.col("toxic").alias("_toxic")).filter("doc_id is not null and _toxic is not null").filter(doc_bucket("doc_id", 4) != 2)
    marks = marks.groupBy("doc_id").agg(F.max("_toxic").alias("_toxic"))
    texts = docs.select(ids, binary_text().alias("_raw")).filter("doc_id is not null")
    labelled = materialise(lookup(texts, marks, ["doc_id"], "inner", "doc_id"), "labelled")
    sizes = {r._toxic: r.n for r in marks.join(docs.select(ids), "doc_id").groupBy("_toxic").agg(F.count("*").alias("n")).collect()}
    n_toxic = sum(n for t, n in sizes.items() if t > 0)
    n_other = sum(n for t, n in sizes.items() if t <= 0)
    base = math.log((n_toxic + 1.0) / (n_other + 1.0)) if sizes else -50.0
    model = ToxicityModel(weights=(base, 0.0, 0.0, 0.0))
    if not n_toxic or not n_other:
        return model
    toxic = labelled.filter("_toxic > 0").select("_raw").mapInArrow(_count_toxic, "token binary, n long, marks long")
    toxic = toxic.groupBy("token").agg(F.sum("n").alias("n"), F.bit_count(F.bit_or("marks")).alias("contexts"))
    found = materialise(toxic.filter((F.col("n") >= support) & (F.col("contexts") >= contexts)).select("token", F.col("n").alias("k")), "toxic-terms")
    other = labelled.filter("_toxic <= 0").select("_raw").mapInArrow(_count_other, "token binary, n long").groupBy("token").agg(F.sum("n").alias("n"))
    if found.count() <= shared_terms:
        wanted = found.select("token").union(docs.sparkSession.range(1).select(F.lit(WORDS).alias("token")))
        other = other.join(F.broadcast(wanted), "token", "left_semi")
    other = materialise(other, "other-terms")
    n_words = float(max(1, other.filter(F.col("token") == F.lit(WORDS)).agg(F.sum("n")).first()[0] or 0))
    both = found.join(other, "token", "left").select("token", "k", F.coalesce("n", F.lit(0)).alias("n"))
    k, n = F.col("k"), F.col("n")
    share = prior * (k + n) / (n_toxic + n_other)
    odds = F.log((k + share) / (n_toxic + prior - k - share + 1e-9)) - F.log((n + share) / (n_other + prior - n - share + 1e-9))
    spread = F.sqrt(1.0 / (k + 0.5) + 1.0 / (n + 0.5))
    against = ~F.col("token").startswith(F.lit(b"^")) & (odds < 0) & (odds / spread <= -3.0 + 1e-6)
    chosen = materialise(both.filter((odds >= least_odds - 1e-6) & (odds / spread >= 3.0 - 1e-6) | against), "chosen-terms")
    if chosen.count() > most_terms:
        raise ValueError(f"more than {most_terms} tokens are selected: raise least_odds or most_terms")
    rates = {}
    for t, k, n in sorted((bytes(r.token), r.k, r.n) for r in chosen.collect()):
        share = prior * (k + n) / (n_toxic + n_other)
        odds = math.log((k + share) / (n_toxic + prior - k - share + 1e-9)) - math.log((n + share) / (n_other + prior - n - share + 1e-9))
        spread = math.sqrt(1.0 / (k + 0.5) + 1.0 / (n + 0.5))
        if odds >= least_odds and odds / spread >= 3.0 or odds < 0 and odds / spread <= -3.0 and not t.startswith(b"^"):
            model.odds[t] = min(8.0, max(-2.0, odds))
            rates[t] = (n + 0.1) / n_words
    model.scale = _scale(model.odds, rates, model.drift)
    part = min(1.0, calibration_rows / max(1, n_toxic + n_other))
    sample = labelled.filter(F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(1_000_000)) < int(part * 1_000_000))
    rows = sample.select("_toxic", "_raw").mapInArrow(_score_rows(model, "_raw", True), "_toxic int, _f0 double, _f1 double, _f2 double").collect()
    if rows:
        x = np.array([[r._f0, r._f1, r._f2] for r in rows])
        y = np.array([1.0 if r._toxic > 0 else 0.0 for r in rows])
        model.weights = _logistic(x, y)
    release(labelled, found, other, chosen)
    return model


def score(docs: DataFrame, model: ToxicityModel, text: str = "text") -> DataFrame:
    """The documents with a column _score; every text is scored whole. A text is sent to Python once, as the column that comes back."""
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInArrow(_score_rows(model, text, False), f"{schema}, _score double")
