"""Language identification by segmentation-marginalised unigrams.

Each language has a probability for every piece of a fixed public vocabulary. A word's probability is the sum over all
its segmentations into pieces, by a forward algorithm; a text's is the product over its words. Pieces are trained by expectation
maximisation over the words of a bounded sample of labelled rows: forward and backward sums give expected piece counts,
summed over the corpus sample by one aggregation per step; the driver holds languages x pieces numbers, no more.

Words are runs between Unicode white space, scored whole whatever their length (forward sums are rescaled as they go, and a long
word is looked at SPAN characters at a time); the vocabulary marks a word's beginning, and all its pieces take part. A
character that no piece holds has one small probability in every language. In a batch each different word is scored once, by
vectorised sums over all words at a time.

The prediction is the language of the highest probability. Its score compares, per character and so alike for texts of
any length, the languages and a background of evenly likely characters: the share of the predicted one when each is weighted by
its mean probability of SCORED characters, over the words with letters and no digit (over all, if there is none). Texts of one
language score near 1, evenly mixed ones near 1 over the number of languages, and letters that are no words of any near 0.

A text that is null or has no letter is `und` with score 0. Ties go to the first label in order. No labelled rows:
everything is `und`. Label, source and id are never inputs of a prediction.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, pieces

#: Characters of a word that are looked at together, and characters of a batch of words.
SPAN, BATCH_CHARS = 50_000, 300_000
#: Words longer than this are not learned from.
LEARNED = 256
#: The background's probability of a character, and the characters that the score weighs by.
BACKGROUND, SCORED = 1 / 64, 3.0
#: Bound of the training sample: rows per label (a threshold on a hash of the id, so about this many at most).
SAMPLE_ROWS = 1_500
STEPS = 2
FLOOR = 1e-8
K = np.uint64(0x9E3779B97F4A7C15)
TABLE_BITS = 20


def vocabulary(name: str = "piece_bpe_32k") -> list[str]:
    """The pieces, without control and byte pieces."""
    import public_tokenizers
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(f"{name}.model"))
    return [p for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i)) and (p := model.id_to_piece(i))]


def codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)


class Lattice:
    """The pieces of the vocabulary by hash, and all their places in a batch of words."""

    def __init__(self, words: list[str]):
        size = np.array([len(w) for w in words], np.int64)
        h = np.zeros(len(words), np.uint64)
        for k in np.unique(size).tolist():
            at = np.flatnonzero(size == k)
            own = codes("".join(words[i] for i in at)).astype(np.uint64).reshape(-1, k)
            for j in range(k):
                h[at] = h[at] * K + (own[:, j] + np.uint64(1))
        h *= K
        self.longest = max(map(len, words), default=1)
        self.order = np.argsort(h)
        self.sorted = h[self.order]
        self.seen = np.zeros(1 << TABLE_BITS, bool)
        self.seen[(h >> np.uint64(64 - TABLE_BITS)).astype(np.int64)] = True

    def places(self, words: list[str]) -> tuple[np.ndarray, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Lengths of the words, and the arrays (word, end, length, piece) of all pieces at all their places, in the order of end and
        word. Pieces are -1 for a character without a piece."""
        n = np.array([len(w) for w in words], np.int64)
        flat = codes("".join(words)).astype(np.uint64)
        word = np.repeat(np.arange(len(n)), n)
        place = np.arange(len(flat)) - np.repeat(np.cumsum(n) - n, n)
        at, size, piece = [], [], []
        h, left, start = np.zeros(len(flat), np.uint64), n[word] - place, np.arange(len(flat))
        for k in range(1, self.longest + 1):
            some = left >= k  # beginnings with k characters of their word
            h, left, start = h[some], left[some], start[some]
            if not len(h):
                break
            h = h * K + (flat[start + (k - 1)] + np.uint64(1))
            g = h * K
            ok = np.flatnonzero(self.seen[(g >> np.uint64(64 - TABLE_BITS)).astype(np.int64)])
            where = np.minimum(np.searchsorted(self.sorted, g[ok]), len(self.sorted) - 1)
            hit = self.sorted[where] == g[ok]
            ids = self.order[where[hit]]
            ok = start[ok[hit]]
            if k == 1:
                none = np.ones(len(flat), bool)
                none[ok] = False
                rest = np.flatnonzero(none)
                ok, ids = np.concatenate([ok, rest]), np.concatenate([ids, np.full(len(rest), -1)])
            at.append(ok + k - 1)
            size.append(np.full(len(ok), k))
            piece.append(ids)
        at, size, piece = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (at, size, piece))
        end = place[at] + 1 if len(at) else at
        order = np.argsort(end * np.int64(len(flat) + 1) + at)
        return n, (word[at[order]] if len(at) else at, end[order], size[order], piece[order])


def runs(x: np.ndarray) -> np.ndarray:
    """Where runs of equal numbers begin."""
    return np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]])) if len(x) else np.zeros(0, np.int64)


class Forward:
    """Sums over all segmentations of the words' beginnings, place by place: the last sums of each word and language, rescaled every
    few places, and the logarithm of the scale. p: [piece + 1, language], the last row for characters without a piece."""

    def __init__(self, words: int, longest: int, p: np.ndarray):
        self.p, self.turns = p, longest + 1
        self.ring = np.zeros((self.turns, words, p.shape[1]))
        self.ring[0] = 1.0
        self.scale = np.zeros((words, p.shape[1]))
        self.at = 0

    def run(self, n: np.ndarray, entries: tuple, skip: int = 0) -> np.ndarray:
        """Goes on by the entries' places from `skip` on; the logarithm of every word's sum where its n characters end."""
        word, end, size, piece = entries
        out = np.zeros_like(self.scale)
        last = int(n.max()) if len(n) else 0
        cut = np.searchsorted(end, np.arange(skip + 1, last + 2))
        done = np.searchsorted(np.sort(n), np.arange(skip + 1, last + 2))  # words come in the order of their length
        for t, (a, b) in enumerate(zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True), skip + 1):
            self.at += 1
            w = word[a:b]
            gain = self.ring[(self.at - size[a:b]) % self.turns, w] * self.p[piece[a:b]]
            first = runs(w)
            own, now = w[first], self.at % self.turns
            self.ring[now, own] = np.add.reduceat(gain, first, axis=0)
            if t == last or done[t - skip] > done[t - skip - 1]:
                over = own[n[own] == t]
                out[over] = np.log(self.ring[now, over]) + self.scale[over]
            if self.at % 8 == 0:
                most = self.ring[:, own].max(axis=0)
                self.ring[:, own] /= most
                self.scale[own] += np.log(most)
        return out


def log_scores(lattice: Lattice, words: list[str], p: np.ndarray) -> np.ndarray:
    """Natural logarithm of each word's probability in each language."""
    out = np.zeros((len(words), p.shape[1]))
    size = np.array([len(w) for w in words], np.int64)
    order = np.argsort(size, kind="stable")
    short = order[: np.searchsorted(size[order], SPAN, side="right")]
    part = np.cumsum(size[short]) // BATCH_CHARS
    for own in np.split(short, np.flatnonzero(np.diff(part)) + 1) if len(short) else []:
        n, entries = lattice.places([words[i] for i in own])
        out[own] = Forward(len(own), lattice.longest, p).run(n, entries)
    for i in order[len(short) :].tolist():
        f = Forward(1, lattice.longest, p)
        for a in range(0, len(words[i]), SPAN):
            lead = min(a, lattice.longest - 1)
            n, entries = lattice.places([words[i][a - lead : a + SPAN]])
            out[i] = f.run(n, entries, skip=lead)[0]
    return out


def log_sums(x: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Logarithms of the sums of exp(x) over the runs that begin at `first`."""
    most = np.maximum.reduceat(x, first)
    return most + np.log(np.add.reduceat(np.exp(x - np.repeat(most, np.diff(np.append(first, len(x))))), first))


def expected(lattice: Lattice, words: list[str], counts: np.ndarray, p: np.ndarray) -> np.ndarray:
    """Expected number of each piece in counts[word] of each word, for one language (p: [piece + 1, 1]). In logarithms."""
    out, logs = np.zeros(len(p)), np.log(p[:, 0])
    size = np.array([len(w) for w in words], np.int64)
    order = np.argsort(size, kind="stable")
    part = np.cumsum(size) if not len(words) else np.cumsum(size[order]) // BATCH_CHARS
    for own in np.split(order, np.flatnonzero(np.diff(part)) + 1) if len(order) else []:
        n, (word, end, length, piece) = lattice.places([words[i] for i in own])
        last, each = int(n.max()), np.arange(len(n))
        ahead = np.full((last + 1, len(n)), -np.inf)
        ahead[0] = 0.0
        cut = np.searchsorted(end, np.arange(1, last + 2))
        for t, (a, b) in enumerate(zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True), 1):
            first = runs(word[a:b])
            ahead[t, word[a:b][first]] = log_sums(ahead[t - length[a:b], word[a:b]] + logs[piece[a:b]], first)
        back = np.full((last + 1, len(n)), -np.inf)
        back[n, each] = 0.0
        by = np.lexsort((word, end - length))
        start = (end - length)[by]
        cut = np.searchsorted(start, np.arange(last + 1))
        for t in range(last - 1, -1, -1):
            some = by[cut[t] : cut[t + 1]]
            if len(some):
                first = runs(word[some])
                back[t, word[some][first]] = log_sums(back[t + length[some], word[some]] + logs[piece[some]], first)
        share = np.log(counts[own]) - ahead[n, each]
        np.add.at(out, piece, np.exp(ahead[end - length, word] + logs[piece] + back[end, word] + share[word]))
    return out


def marked(words: Iterable[str]) -> list[str]:
    """Words with their mark; words in capitals in small letters."""
    return [f"▁{w.lower() if w.isupper() else w}" for w in words]


def plain(word: str) -> bool:
    """Whether a word counts in the score: letters, and no digit."""
    return has_letter(word) and not any(map(str.isdigit, word))


def has_letter(text: str | None) -> bool:
    return text is not None and any(map(str.isalpha, text))


def train(labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang", sample_rows: int = SAMPLE_ROWS, steps: int = STEPS, name: str = "piece_bpe_32k") -> tuple[list[str], np.ndarray]:
    """Labels and [piece + 1, language] probabilities, from about sample_rows rows of each label at most."""
    own = labelled.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(label_col).cast("string").alias("label")).filter("label is not null and text is not null")
    sizes = {r["label"]: r["count"] for r in own.groupBy("label").count().collect()}
    labels = sorted(sizes)
    words = vocabulary(name)
    if not labels:
        return [], np.zeros((len(words) + 1, 0))
    share = F.element_at(F.create_map(*[x for k in labels for x in (F.lit(k), F.lit(min(1.0, sample_rows / sizes[k])))]), F.col("label"))
    part = own.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_003)) < share * 1_000_003)

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in pieces(batch):
                held: dict[tuple[str, str], int] = {}
                for text, label in zip(x.column("text").to_pylist(), x.column("label").to_pylist(), strict=True):
                    for w in marked(text.split()):
                        if len(w) <= LEARNED:
                            held[label, w] = held.get((label, w), 0) + 1
                yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in held], pa.string()), pa.array([k[1] for k in held], pa.string()), pa.array(list(held.values()), pa.int64())], ["label", "word", "n"])

    counts = materialize(part.select("text", "label").mapInArrow(counted, "label string, word string, n bigint").groupBy("label", "word").agg(F.sum("n").alias("n")), "language-words")
    p = np.full((len(words) + 1, len(labels)), 1.0 / len(words))
    p[-1] = FLOOR
    number = {k: i for i, k in enumerate(labels)}
    for _ in range(steps):
        held = labelled.sparkSession.sparkContext.broadcast(p)

        def expect(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            lattice, total = Lattice(words), np.zeros(held.value.shape)
            for batch in batches:
                label = np.array([number[x] for x in batch.column("label").to_pylist()])
                word, n = np.array(batch.column("word").to_pylist(), object), batch.column("n").to_numpy(zero_copy_only=False)
                for i in range(total.shape[1]):
                    at = np.flatnonzero(label == i)
                    if len(at):
                        total[:, i] += expected(lattice, word[at].tolist(), n[at], held.value[:, i : i + 1])
            piece, lang = np.nonzero(total[:-1])
            for a in range(0, len(piece), 50_000):
                i, j = piece[a : a + 50_000], lang[a : a + 50_000]
                yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(total[i, j])], ["piece", "lang", "n"])

        found = counts.mapInArrow(expect, "piece int, lang int, n double").groupBy("piece", "lang").agg(F.sum("n").alias("n")).toPandas()
        p = np.full((len(words) + 1, len(labels)), 0.01)
        p[found["piece"], found["lang"]] += found["n"]
        p /= p[:-1].sum(axis=0)
        p[-1] = FLOOR
        p = np.maximum(p, FLOOR)
    return labels, p


def share(total: np.ndarray, best: int, characters: int) -> float:
    """The score of the language `best` for a text of so many characters with these log probabilities."""
    mean = np.append(total / max(1, characters), np.log(BACKGROUND)) * SCORED
    return float(1.0 / np.exp(np.minimum(mean - mean[best], 700.0)).sum())


def predict(docs: DataFrame, model: tuple[list[str], np.ndarray], id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = (), name: str = "piece_bpe_32k") -> DataFrame:
    """doc_id, `keep` columns as k0, k1, ..., lang_pred, score (0 to 1, see above)."""
    labels, _ = model
    held = docs.sparkSession.sparkContext.broadcast(model[1])
    words = vocabulary(name)
    # a kept text crosses to Python once
    source = f"k{keep.index(text_col)}" if text_col in keep else "text"
    own = docs.select(F.col(id_col).alias("doc_id"), *[F.col(text_col).alias("text")] * (source == "text"), *[F.col(c).alias(f"k{i}") for i, c in enumerate(keep)])
    from pyspark.sql import types as T

    schema = T.StructType([f for f in own.schema if f.name != "text"] + [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    names = [f.name for f in schema][:-2]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lattice, p = Lattice(words), held.value
        for batch in batches:
            for part in pieces(batch, source, limit=12 << 20):
                seen: dict[str, int] = {}
                which = []
                for text in part.column(source).to_pylist():
                    which.append(np.array([seen.setdefault(w, len(seen)) for w in text.split()], np.int64) if labels and has_letter(text) else None)
                every = marked(seen)
                scores = log_scores(lattice, every, p)
                length = np.array([len(w) for w in every], np.int64)
                size = length * np.array([plain(w) for w in every], bool)
                lang, score = [], []
                for at in which:
                    if at is None:
                        lang.append("und")
                        score.append(0.0)
                        continue
                    total = scores[at].sum(axis=0)
                    best = int(np.argmax(total))
                    lang.append(labels[best])
                    own = at[size[at] > 0] if size[at].any() else at
                    score.append(share(scores[own].sum(axis=0), best, int(length[own].sum())))
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in names), pa.array(lang, pa.string()), pa.array(score, pa.float64())], [*names, "lang_pred", "score"])

    return own.mapInArrow(kernel, schema)


def held_out(id_col: str = "doc_id", folds: int = 5):
    return F.pmod(F.coalesce(F.crc32(F.col(id_col).cast("string")), F.lit(0)), F.lit(folds)) == 0
