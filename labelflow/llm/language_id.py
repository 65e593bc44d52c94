"""Language identification by a linear-chain conditional random field over words.

A word's evidence is the sum of learned weights of its character n-grams (those that touch a word boundary are its affixes)
and of its lexicon entry, if training saw it often; learned transitions tie neighbouring words. Training fits both by
maximum likelihood on code-switched sequences, pieces of labelled documents put end to end, so that switching inside a text
is learned too. Prediction runs forward-backward over all words of a text and takes the language of the largest mean posterior
over its words with a letter; the mean is the score.

Bounds, all parameters: the model is fitted on at most about `per_language` documents of each language, a piece of `piece`
words of each, chosen by hash. Prediction covers whole texts. Defined results: a null text or one without a letter is
`und` with score 0; so is every text where nothing could be learned; null languages are never learned; other columns pass
through untouched.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.llm.common import doc_bucket

BITS = 17
GRAMS = (2, 3, 4)
GROUP_WORDS = 1_000_000
CACHE = 400_000
UNKNOWN = "und"
_ASCII_LETTER = re.compile("[A-Za-z]")
_PUNCTUATION = bytes(b for b in range(128) if not chr(b).isalnum())
_TO_SPACE = bytes.maketrans(_PUNCTUATION, b" " * len(_PUNCTUATION))


def has_letter(text: str) -> bool:
    return bool(_ASCII_LETTER.search(text)) or any(c.isalpha() for c in text)


def words_of(text: str) -> list[bytes]:
    """Lower-case words: maximal runs of anything but ASCII white space and punctuation."""
    return text.lower().encode("utf-8", "replace").translate(_TO_SPACE).split()


def gram_ids(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed n-gram features of marked words: (feature of each n-gram, its word)."""
    data = np.frombuffer(b"".join(b"\x01" + w + b"\x02" for w in words), np.uint8).astype(np.uint32)
    size = np.fromiter(map(len, words), np.int64, len(words)) + 2
    owner = np.repeat(np.arange(len(words)), size)
    ends = np.cumsum(size)[owner]
    at = np.arange(len(data))
    ids, of = [], []
    for n in GRAMS:
        if len(data) < n:
            continue
        ok = at[: len(data) - n + 1]
        code = np.full(len(ok), n * 0x9E3779B1 & 0xFFFFFFFF, np.uint32)
        for k in range(n):
            code = (code ^ data[k : k + len(ok)]) * np.uint32(0x01000193)
        code ^= code >> np.uint32(15)
        inside = ok + n <= ends[: len(ok)]
        ids.append((code[inside] & np.uint32((1 << BITS) - 1)).astype(np.int32))
        of.append(owner[: len(ok)][inside])
    return np.concatenate(ids), np.concatenate(of)


def sums_by(values: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """Row sums of a matrix by owner."""
    return np.stack([np.bincount(owner, values[:, j], n) for j in range(values.shape[1])], axis=1)


def posteriors(evidence: np.ndarray, sizes: np.ndarray, transitions: np.ndarray) -> np.ndarray:
    """Forward-backward over many sequences at once; rows of `evidence` are the sequences' words one after another, and
    sequences come by falling size, so that those still running are the first ones at every step."""
    start = np.concatenate(([0], np.cumsum(sizes)[:-1]))
    x = np.exp(evidence - evidence.max(axis=1, keepdims=True))
    step = np.exp(transitions - transitions.max())
    longest = int(sizes[0]) if len(sizes) else 0
    running = np.searchsorted(-sizes, -np.arange(longest), side="left")  # sequences longer than t
    forward = np.empty_like(x)
    held = None
    for t in range(longest):
        at = start[: running[t]] + t
        held = x[at] if held is None else (held[: running[t]] @ step) * x[at]
        held = held / held.sum(axis=1, keepdims=True)
        forward[at] = held
    back = np.ones((0, x.shape[1]), x.dtype)
    for t in range(longest - 1, -1, -1):
        if t + 1 < longest:
            at = start[: running[t + 1]] + t + 1
            back = (x[at] * back) @ step.T
            back /= back.sum(axis=1, keepdims=True)
        if running[t] > len(back):
            back = np.concatenate([back, np.ones((running[t] - len(back), x.shape[1]), x.dtype)])
        forward[start[: running[t]] + t] *= back
    return forward / forward.sum(axis=1, keepdims=True)


@dataclass
class LanguageModel:
    langs: list[str]
    weights: np.ndarray  # n-gram features x languages
    transitions: np.ndarray
    lexicon: dict[bytes, int]
    lexicon_weights: np.ndarray

    def evidence(self, words: list[bytes]) -> np.ndarray:
        out = np.zeros((len(words), len(self.langs)), np.float32)
        for a in range(0, len(words), 50_000):
            part = words[a : a + 50_000]
            ids, of = gram_ids(part)
            got = sums_by(self.weights[ids], of, len(part))
            known = [self.lexicon.get(w, -1) for w in part]
            out[a : a + len(part)] = got + np.where(np.array(known)[:, None] >= 0, self.lexicon_weights[known], 0.0)
        return out

    def predict(self, texts: list[str | None], cache: EvidenceCache) -> tuple[list[str], list[float]]:
        """Language and score of each text, in groups of texts of similar size."""
        langs, scores = [UNKNOWN] * len(texts), [0.0] * len(texts)
        if not self.langs:
            return langs, scores
        rows: list[tuple[int, np.ndarray]] = []
        for i, text in enumerate(texts):
            if text and has_letter(text):
                rows.append((i, cache.rows(words_of(text))))
        rows.sort(key=lambda r: -len(r[1]))
        group: list[tuple[int, np.ndarray]] = []
        held = 0
        for r in rows:
            group.append(r)
            held += len(r[1])
            if held >= GROUP_WORDS:
                self._settle(group, cache, langs, scores)
                group, held = [], 0
        if group:
            self._settle(group, cache, langs, scores)
        return langs, scores

    def _settle(self, group: list, cache: EvidenceCache, langs: list[str], scores: list[float]) -> None:
        table, lettered = cache.tables()
        sizes = np.array([len(r) for _, r in group])
        spots = np.concatenate([r for _, r in group])
        p = posteriors(table[spots], sizes, self.transitions)
        weight = lettered[spots].astype(np.float32)
        start = np.concatenate(([0], np.cumsum(sizes)[:-1]))
        total = np.add.reduceat(p * weight[:, None], start, axis=0, dtype=np.float64)
        count = np.add.reduceat(weight, start, dtype=np.float64)
        mean = total / np.maximum(count, 1.0)[:, None]
        for (i, _), m, n in zip(group, mean, count, strict=True):
            if n:
                k = int(m.argmax())
                langs[i], scores[i] = self.langs[k], float(min(1.0, m[k]))


class EvidenceCache:
    """Evidence of the words met by a task, each computed once; emptied between batches when it has grown large."""

    def __init__(self, model: LanguageModel):
        self.model = model
        self.clear()

    def clear(self) -> None:
        self.index: dict[bytes, int] = {}
        self.done = 0
        self.parts: list[np.ndarray] = []
        self.letters: list[np.ndarray] = []

    def rows(self, words: list[bytes]) -> np.ndarray:
        index = self.index
        return np.fromiter((index.setdefault(w, len(index)) for w in words), np.int64, len(words))

    def tables(self) -> tuple[np.ndarray, np.ndarray]:
        if self.done < len(self.index):
            fresh = list(self.index)[self.done :]
            self.parts.append(self.model.evidence(fresh))
            self.letters.append(np.array([has_letter(w.decode("utf-8", "replace")) for w in fresh]))
            self.done = len(self.index)
            self.parts, self.letters = [np.concatenate(self.parts)], [np.concatenate(self.letters)]
        return self.parts[0], self.letters[0]


def fit(samples: list[tuple[str, list[bytes]]], epochs: int = 30, rate: float = 0.4, seed: int = 11, least_count: int = 3, decay: float = 1e-4) -> LanguageModel:
    """Maximum likelihood of the sampled pieces, strung together in threes in random order; full-batch adaptive gradient."""
    langs = sorted({lang for lang, words in samples if words})
    samples = [s for s in samples if s[1]]
    k = len(langs)
    place = {lang: i for i, lang in enumerate(langs)}
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(samples))
    chains = sorted((order[i : i + 3] for i in range(0, len(order), 3)), key=lambda c: -sum(len(samples[j][1]) for j in c))
    index: dict[bytes, int] = {}
    spots, truth, sizes, counts = [], [], [], Counter()
    for chain in chains:
        before = len(spots)
        for j in chain:
            lang, words = samples[j]
            spots += [index.setdefault(w, len(index)) for w in words]
            truth += [place[lang]] * len(words)
            counts.update(words)
        sizes.append(len(spots) - before)
    words = list(index)
    lexicon = {w: i for i, w in enumerate(w for w in words if counts[w] >= least_count)}
    model = LanguageModel(langs, np.zeros((1 << BITS, k), np.float32), np.zeros((k, k), np.float32), lexicon, np.zeros((max(1, len(lexicon)), k), np.float32))
    if k < 2:
        return model
    spots, truth, sizes = np.array(spots), np.array(truth), np.array(sizes)
    gold = np.eye(k, dtype=np.float32)[truth]
    inner = np.ones(len(spots), bool)
    inner[np.concatenate(([0], np.cumsum(sizes)[:-1]))] = False
    after = np.flatnonzero(inner)
    ids, of = gram_ids(words)
    lex_of = np.array([lexicon.get(w, -1) for w in words])
    seen_lex = np.flatnonzero(lex_of >= 0)
    moves = np.zeros((k, k))
    np.add.at(moves, (truth[after - 1], truth[after]), 1.0)
    speed_w, speed_t, speed_l = (np.full(x.shape, 1e-6) for x in (model.weights, model.transitions, model.lexicon_weights))
    for _ in range(epochs):
        table = sums_by(model.weights[ids], of, len(words))
        table[seen_lex] += model.lexicon_weights[lex_of[seen_lex]]
        x = table[spots].astype(np.float32)
        p = posteriors(x, sizes, model.transitions)
        by_word = sums_by(gold - p, spots, len(words)) / len(spots)
        g = sums_by(by_word[of], ids, 1 << BITS) - decay / 100 * model.weights
        gl = np.zeros_like(model.lexicon_weights, dtype=np.float64)
        gl[lex_of[seen_lex]] = by_word[seen_lex]
        gl -= decay / 100 * model.lexicon_weights
        # expected moves between neighbours, from the two-sided posteriors of each pair
        e = np.exp(x - x.max(axis=1, keepdims=True))
        step = np.exp(model.transitions - model.transitions.max())
        pair = _pair_moves(x, e, sizes, step, after)
        gt = (moves - pair) / len(spots)
        for w, grad, speed in ((model.weights, g, speed_w), (model.transitions, gt, speed_t), (model.lexicon_weights, gl, speed_l)):
            speed += grad * grad
            w += (rate * grad / np.sqrt(speed)).astype(np.float32)
    return model


def _pair_moves(x: np.ndarray, e: np.ndarray, sizes: np.ndarray, step: np.ndarray, after: np.ndarray) -> np.ndarray:
    """Expected count of each move between neighbouring words under the model."""
    start = np.concatenate(([0], np.cumsum(sizes)[:-1]))
    running = np.searchsorted(-sizes, -np.arange(int(sizes[0])), side="left")
    f, b = np.empty_like(e), np.ones_like(e)
    held = None
    for t, n in enumerate(running):
        at = start[:n] + t
        held = e[at] if held is None else (held[:n] @ step) * e[at]
        held = held / held.sum(axis=1, keepdims=True)
        f[at] = held
    for t in range(len(running) - 2, -1, -1):
        at = start[: running[t + 1]] + t
        y = (e[at + 1] * b[at + 1]) @ step.T
        b[at] = y / y.sum(axis=1, keepdims=True)
    left, right = f[after - 1], e[after] * b[after]
    norm = np.einsum("ij,jk,ik->i", left, step, right)
    return (left / norm[:, None]).T @ right * step


def _pieces(piece: int, seed: int):
    """Map side of the sample: a run of words at a place given by the row's hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for text, h in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                words = words_of(text or "")
                at = (h ^ seed) % max(1, len(words) - piece + 1)
                out.append(b" ".join(words[at : at + piece]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=["lang", "piece"])

    return run


def train(docs: DataFrame, per_language: int = 400, piece: int = 60, epochs: int = 30) -> LanguageModel:
    """Fits on documents with a language, outside the held-out third (crc32 of the decimal id, modulo 3, is 1)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").alias("lang"), F.col("text").alias("text")).filter("lang is not null and doc_id is not null and text is not null")
    rows = rows.filter(doc_bucket("doc_id", 3) != 1)
    sizes = {r.lang: r.n for r in rows.select("doc_id", "lang").groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not sizes:
        return LanguageModel([], np.zeros((1, 0), np.float32), np.zeros((0, 0), np.float32), {}, np.zeros((1, 0), np.float32))
    share = F.create_map(*[x for lang, n in sizes.items() for x in (F.lit(lang), F.lit(int(min(1.0, per_language / n) * 1_000_000)))])
    hashed = F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(1_000_000))
    sample = rows.filter(hashed < share[F.col("lang")]).select("lang", "text", F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(1 << 40)).alias("h"))
    pieces = sample.mapInArrow(_pieces(piece, 17), "lang string, piece binary").collect()
    return fit(sorted((r.lang, bytes(r.piece).split()) for r in pieces), epochs)


def _predict_rows(model: LanguageModel):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = EvidenceCache(model)
        for batch in batches:
            at = batch.schema.get_field_index("_text")
            langs, scores = model.predict(batch.column(at).to_pylist(), cache)
            keep = [i for i in range(batch.num_columns) if i != at]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in keep), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=[*(batch.schema.names[i] for i in keep), "_lang", "_score"])
            if len(cache.index) >= CACHE:
                cache.clear()

    return run


def predict(docs: DataFrame, model: LanguageModel, text: str = "text") -> DataFrame:
    """The documents with columns _lang and _score."""
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.withColumn("_text", F.col(text)).mapInArrow(_predict_rows(model), f"{schema}, _lang string, _score double")
