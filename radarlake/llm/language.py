"""Language by unigram pieces with all segmentations summed.

A language is a distribution over the pieces of a fixed public vocabulary (byte
strings, every single byte among them). The probability of a word, with a space in
front, is the sum over all ways to cut it into pieces, by a forward pass over its
bytes; expectation-maximisation with the backward pass fits the distributions. A
text's score is the sum over its words, lower-cased (A-Z). All pieces take part, and
words of any length: those of over SHORT bytes are summed in logarithms, with memory for
as many positions as the longest piece has bytes when scored.

Fitting takes at most about `per_language` documents of each language, chosen by a hash
of their id; all else covers all rows. A null or empty text, or one without a letter,
is `und` with score 0, and so is every text if there is nothing to learn from. Null and
repeated ids are rows like any other (a null id isn't held out), and all columns of a table
stay as they are.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from radarlake.llm.common import HashIndex, chunks, named, prefix_hashes, span_hashes, string_hashes, unused, words

#: Documents of a language that fitting takes, about.
PER_LANGUAGE = 1500
#: Bytes of a word, with its space, up to which words of equal length are summed side by side.
SHORT = 32
ROUNDS, SMOOTHING = 3, 0.05
CACHE = 1 << 19


class Pieces:
    """The vocabulary's pieces by hash, and the bytes of the longest; each single byte is one of them."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        found = {bytes([b]) for b in range(256)}
        for i in range(model.get_piece_size()):
            if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i)):
                found.add(model.id_to_piece(i).replace("▁", " ").encode().lower())
        listed = sorted(found - {b""})
        at = np.concatenate([[0], np.cumsum([len(p) for p in listed])])
        self.longest = max(map(len, listed))
        self.size = len(listed)
        self.index = HashIndex(len(listed))
        self.index.add(span_hashes(prefix_hashes(np.frombuffer(b"".join(listed), np.uint8)), at[:-1], at[1:]))

    def edges(self, text: np.ndarray) -> list[tuple[int, int, np.ndarray, np.ndarray]]:
        """For words of one length (a row of bytes each): (end, piece's length, words, pieces) by rising end."""
        n, size = text.shape
        prefix = prefix_hashes(np.ascontiguousarray(text).reshape(-1))
        at = np.arange(n) * size
        out = []
        for e in range(1, size + 1):
            for m in range(1, min(e, self.longest) + 1):
                piece = self.index.find(span_hashes(prefix, at + e - m, at + e))
                which = np.flatnonzero(piece >= 0)
                if len(which):
                    out.append((e, m, which, piece[which]))
        return out

    def ends(self, text: np.ndarray, block: int = 1 << 16) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """For a word of any length: each end, with the lengths and the numbers of the pieces that end there."""
        for a in range(0, len(text), block):
            low = max(a - self.longest + 1, 0)
            part = text[low : a + block]
            prefix = prefix_hashes(part)
            end = np.arange(a - low + 1, len(part) + 1)
            found = np.full((len(end), self.longest), -1, np.int64)
            for m in range(1, self.longest + 1):
                can = np.flatnonzero(end >= m)
                found[can, m - 1] = self.index.find(span_hashes(prefix, end[can] - m, end[can]))
            for k in range(len(end)):
                m = np.flatnonzero(found[k] >= 0)
                yield a + k + 1, m + 1, found[k, m]


@lru_cache(maxsize=2)
def pieces(path: str) -> Pieces:
    return Pieces(path)


def forward(p: np.ndarray, n: int, size: int, edges: list) -> np.ndarray:
    """alpha[e]: probability of the first e bytes of each of n words; more axes of p (piece, ...) go last."""
    alpha = np.zeros((size + 1, n, *p.shape[1:]))
    alpha[0] = 1
    for e, m, which, piece in edges:
        alpha[e][which] += alpha[e - m][which] * p[piece]
    return alpha


def expected(p: np.ndarray, n: int, size: int, edges: list, weight: np.ndarray) -> np.ndarray:
    """Expected uses of each piece over weighted words."""
    alpha = forward(p, n, size, edges)
    beta = np.zeros((size + 1, n))
    beta[size] = weight / alpha[size]
    out = np.zeros(len(p))
    for e, m, which, piece in reversed(edges):
        use = p[piece] * beta[e][which]
        out += np.bincount(piece, use * alpha[e - m][which], len(p))
        beta[e - m][which] += use
    return out


def _log_sum(x: np.ndarray) -> np.ndarray:
    top = x.max(0)
    return top + np.log(np.exp(x - top).sum(0))


def forward_long(logs: np.ndarray, vocabulary: Pieces, text: np.ndarray) -> np.ndarray:
    """Log probability of one word of any length, for each language (last axis of `logs`); holds the last positions alone."""
    width = vocabulary.longest + 1
    ring = np.zeros((width, *logs.shape[1:]))
    for e, m, piece in vocabulary.ends(text):
        ring[e % width] = _log_sum(ring[(e - m) % width] + logs[piece])
    return ring[len(text) % width]


def expected_long(logs: np.ndarray, vocabulary: Pieces, text: np.ndarray, weight: float) -> np.ndarray:
    """Expected uses of each piece over one word of any length."""
    steps = list(vocabulary.ends(text))
    alpha, beta = np.zeros(len(text) + 1), np.full(len(text) + 1, -np.inf)
    for e, m, piece in steps:
        alpha[e] = _log_sum(alpha[e - m] + logs[piece])
    beta[-1] = 0.0
    out = np.zeros(len(logs))
    for e, m, piece in reversed(steps):
        use = logs[piece] + beta[e]
        np.add.at(out, piece, weight * np.exp(use + alpha[e - m] - alpha[-1]))
        beta[e - m] = np.logaddexp(beta[e - m], use)
    return out


def _spaced(low: np.ndarray, start: np.ndarray, size: int) -> np.ndarray:
    """Words of one length, a space before each."""
    out = np.full((len(start), size + 1), 0x20, np.uint8)
    out[:, 1:] = low[start[:, None] + np.arange(size)]
    return out


def _fit(path: str):
    def run(key: tuple, table: pa.Table) -> pa.Table:
        vocabulary = pieces(path)
        counts: dict[bytes, int] = {}
        for _, data, offsets in chunks(table.to_batches(), "text"):
            start, end, _, low = words(data, offsets)
            at, n = np.unique(string_hashes(low, start, end), return_index=True, return_counts=True)[1:]
            raw = low.tobytes()
            for i, c in zip(at.tolist(), n.tolist(), strict=True):
                word = b" " + raw[start[i] : end[i]]
                counts[word] = counts.get(word, 0) + c
        by: dict[int, list[bytes]] = {}
        for word in sorted(counts):
            by.setdefault(len(word), []).append(word)
        groups, long_ = [], []
        for size, listed in sorted(by.items()):
            if size > SHORT:
                long_ += [(np.frombuffer(w, np.uint8), float(counts[w])) for w in listed]
                continue
            for a in range(0, len(listed), 20_000):
                part = listed[a : a + 20_000]
                edges = vocabulary.edges(np.frombuffer(b"".join(part), np.uint8).reshape(len(part), size))
                groups.append((len(part), size, edges, np.array([counts[w] for w in part], float)))
        p = np.zeros(vocabulary.size)
        for _, _, edges, weight in groups:
            for _, _, which, piece in edges:
                p += np.bincount(piece, weight[which], len(p))
        for text, weight in long_:
            for _, _, piece in vocabulary.ends(text):
                np.add.at(p, piece, weight)
        for step in range(ROUNDS + 1):
            p = (p + SMOOTHING) / (p.sum() + SMOOTHING * len(p))
            if step == ROUNDS:
                break
            logs = np.log(p)
            p = sum((expected(p, *g) for g in groups), np.zeros(len(p))) + sum((expected_long(logs, vocabulary, *g) for g in long_), np.zeros(len(p)))
        return pa.table({"lang": [key[0].as_py()], "p": pa.array([p.tolist()], pa.list_(pa.float64()))})

    return run


def fit(train: DataFrame, path: str, per_language: int = PER_LANGUAGE) -> dict[str, np.ndarray]:
    """Piece probabilities by language from rows (doc_id, text, lang); at most a vocabulary times the languages."""
    rows = train.filter(F.col("lang").isNotNull() & F.col("text").isNotNull())
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return {}
    share = F.coalesce(*(F.when(F.col("lang") == k, F.lit(min(1.0, per_language / n))) for k, n in counts.items()))
    drawn = rows.filter(F.pmod(F.xxhash64(F.col("doc_id"), F.lit("fit")), F.lit(1 << 30)) < share * (1 << 30)).select("lang", "text")
    fitted = drawn.groupBy("lang").applyInArrow(_fit(path), "lang string, p array<double>").collect()
    return {r["lang"]: np.array(r["p"]) for r in sorted(fitted, key=lambda r: r["lang"])}


class Scorer:
    """Log probabilities of words by language, kept by hash while the worker lives."""

    def __init__(self, path: str, model: dict[str, np.ndarray]):
        self.langs = list(model)
        self.p = np.stack(list(model.values()), 1)
        self.logs = np.log(self.p)
        self.vocabulary = pieces(path)
        self._clear()

    def _clear(self) -> None:
        self.index = HashIndex(CACHE)
        self.table = np.zeros((CACHE, len(self.langs)), np.float32)

    def words(self, low: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        out = np.empty((len(start), len(self.langs)), np.float32)
        size = end - start
        for n in np.unique(size).tolist():
            same = np.flatnonzero(size == n)
            if n + 1 > SHORT:
                for i in same.tolist():
                    out[i] = forward_long(self.logs, self.vocabulary, np.concatenate([np.array([0x20], np.uint8), low[start[i] : end[i]]]))
                continue
            for a in range(0, len(same), 4096):
                part = same[a : a + 4096]
                out[part] = np.log(forward(self.p, len(part), n + 1, self.vocabulary.edges(_spaced(low, start[part], n)))[n + 1])
        return out

    def rows(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Summed log probabilities (row, language) and words of each row."""
        start, end, row, low = words(data, offsets)
        n = np.bincount(row, minlength=len(offsets) - 1)
        out = np.zeros((len(n), len(self.langs)))
        if not len(start):
            return out, n
        hashed = string_hashes(low, start, end)
        for a in range(0, len(hashed), CACHE // 2):
            h, r = hashed[a : a + CACHE // 2], row[a : a + CACHE // 2]
            found = self.index.find(h)
            if (found < 0).any():
                lost = np.flatnonzero(found < 0)
                new, where = np.unique(h[lost], return_index=True)
                if self.index.size + len(new) > CACHE:
                    self._clear()
                    new, where = np.unique(h, return_index=True)
                    lost = np.arange(len(h))
                at = lost[where] + a
                self.table[self.index.size : self.index.size + len(new)] = self.words(low, start[at], end[at])
                self.index.add(new)
                found = self.index.find(h)
            edge = np.flatnonzero(np.concatenate([[True], r[1:] != r[:-1]]))
            out[r[edge]] += np.add.reduceat(self.table[found].astype(np.float64), edge)
        return out, n


_scorers: dict = {}


def _predict(path: str, shared):
    kind = pa.struct([("lang_pred", pa.string()), ("score", pa.float64())])

    def run(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        key, model = shared.value
        if key not in _scorers:
            _scorers.clear()
            _scorers[key] = Scorer(path, model)
        scorer = _scorers[key]
        names = np.array([*scorer.langs, "und"], object)
        for text in texts:
            told = [pa.array([], kind)]
            for _, data, offsets in chunks(iter([pa.RecordBatch.from_arrays([text], names=["text"])]), "text"):
                total, n = scorer.rows(data, offsets)
                letter = np.concatenate([[0], np.cumsum(((data | 0x20) >= 0x61) & ((data | 0x20) <= 0x7A) & (data < 0x80))])[offsets]
                has = np.diff(letter) > 0
                for i in np.flatnonzero(~has & (np.diff(offsets) > 0)).tolist():
                    has[i] = any(c.isalpha() for c in bytes(data[offsets[i] : offsets[i + 1]]).decode())
                # the odds of a word of average length, sharpened by the square root of their number
                odds = total / np.sqrt(np.maximum(n, 1))[:, None]
                odds = np.exp(odds - odds.max(1, keepdims=True))
                best = np.where(has, total.argmax(1), len(scorer.langs))
                score = np.where(has, odds.max(1) / odds.sum(1), 0.0)
                told.append(pa.StructArray.from_arrays([pa.array(names[best], pa.string()), pa.array(score)], fields=list(kind)))
            yield pa.concat_arrays(told)

    return run


def language(docs: DataFrame, path: str, model: dict[str, np.ndarray], text: str = "text") -> Column:
    """A column (lang_pred, score) for `docs`: the best language of the text and its share among the languages' odds.

    Only the text goes to Python; the other columns of a row wait where they are.
    """
    if not model:
        return F.struct(F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"))
    import hashlib

    key = hashlib.sha256(b"".join(k.encode() + v.tobytes() for k, v in model.items())).hexdigest()
    shared = docs.sparkSession.sparkContext.broadcast((key, model))  # a vocabulary times the languages
    return F.arrow_udf(_predict(path, shared), "lang_pred string, score double")(F.col(text))


def predict(docs: DataFrame, path: str, model: dict[str, np.ndarray]) -> DataFrame:
    """(doc_id, lang_pred, score) of each row."""
    return docs.select("doc_id", language(docs, path, model).alias("told")).select("doc_id", "told.*")


def keep(docs: DataFrame, path: str, least: float = 0.5) -> DataFrame:
    """The rows with a language at `least` or more, fitted on the rows that aren't held out; their columns stay as they are."""
    model = fit(docs.filter(~F.coalesce(held_out(F.col("doc_id")), F.lit(False))).select("doc_id", "text", "lang"), path)
    (told,) = unused(docs, "told")
    found = docs.select("*", language(docs, path, model).alias(told))
    return found.filter((F.col(told)["lang_pred"] != "und") & (F.col(told)["score"] >= least)).select(*named(docs))


def held_out(doc_id: Column) -> Column:
    """The fourth of the documents that nothing is learned from."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2


def classify(docs: DataFrame, path: str) -> DataFrame:
    """Learns from the documents that aren't held out and predicts all."""
    given = docs.select("doc_id", "text", "lang")
    model = fit(given.filter(~F.coalesce(held_out(F.col("doc_id")), F.lit(False))), path)
    return given.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), language(given, path, model).alias("told")).select("doc_id", "held_out", "told.*")
