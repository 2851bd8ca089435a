"""Language identification by words first, backing off to shorter and shorter character n-grams.

A word that the model knows is scored by its log frequency in each language. An unseen word is scored
by the longest known character n-grams that cover it, shortest last, over its whole length: a run of letters
without blanks is one word, however long. The model holds every word of a bounded sample: about SAMPLE_ROWS training
rows of each language, picked by a hash of their identifier, so that a rare language is learned like any other.

Edge cases: null text or text without a letter gives `und` with score 0; rows without language or
identifier are not learned from; without any training row every result is `und`; a tie goes to the
language that sorts first.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from pacedfl.llm.common import WORD_CACHE, checkpointed, dealt, repeated, salted, slices, texts

WORD = re.compile(r"[^\W\d_]+")
MAX_GRAM = 4
SAMPLE_ROWS = 1000  # expected labelled rows of a language that the model is fitted on
MAX_BROADCAST_ROWS = 1_000_000
CHUNK = 1 << 14  # n-grams of a long word that are scored at a time
UNKNOWN = "und"


@dataclass
class LanguageModel:
    langs: list[str]
    words: dict[str, np.ndarray]
    grams: dict[str, np.ndarray]
    floor: np.ndarray

    def __post_init__(self):
        self.word_at = {w: i for i, w in enumerate(self.words)}
        self.gram_at = {g: i for i, g in enumerate(self.grams)}
        self.word_table = np.array([*self.words.values(), self.floor], np.float32)
        self.gram_table = np.array([*self.grams.values(), self.floor], np.float32)
        self.words, self.grams = {}, {}

    def pieces(self, word: str) -> list[int]:
        """The n-grams that cover an unseen word, the longest known one at each place."""
        framed, at, found, get = f"<{word}>", 0, [], self.gram_at.get
        while at < len(framed):
            for n in range(MAX_GRAM, 0, -1):
                if (g := get(framed[at : at + n])) is not None:
                    found.append(g)
                    break
            at += n
        return found or [len(self.gram_at)]

    def of_words(self, words: list[str]) -> np.ndarray:
        """Log score of each word in each language: its own, or the mean of its n-grams'."""
        out = np.zeros((len(words), len(self.langs)), np.float32)
        known = np.fromiter((self.word_at.get(w, -1) for w in words), np.int64, len(words))
        out[known >= 0] = self.word_table[known[known >= 0]]
        new = np.flatnonzero(known < 0)
        if len(new):
            covers = [self.pieces(words[i]) for i in new]
            for i, c in zip(new, covers, strict=True):
                if len(c) > CHUNK:
                    out[i] = sum(self.gram_table[c[a : a + CHUNK]].sum(axis=0, dtype=np.float64) for a in range(0, len(c), CHUNK)) / len(c)
            some = [k for k, c in enumerate(covers) if len(c) <= CHUNK]
            new, covers = new[some], [covers[k] for k in some]
        if len(new):
            size = np.fromiter(map(len, covers), np.int64, len(covers))
            flat = np.fromiter((g for c in covers for g in c), np.int64, int(size.sum()))
            out[new] = np.add.reduceat(self.gram_table[flat], np.cumsum(size) - size, axis=0) / size[:, None]
        return out


def count_words(docs: DataFrame, lang_col: str, text_col: str) -> DataFrame:
    """(lang, word, n) over all rows: counted in each task first, then summed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, Counter] = defaultdict(Counter)

        def flush() -> pa.RecordBatch:
            rows = [(lang, w, n) for lang, c in held.items() for w, n in c.items()]
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.string(), pa.int64()))], names=["lang", "word", "n"])

        for batch in batches:
            for part in slices(batch, text_col, 2 << 20):
                for lang, text in zip(part.column(lang_col).to_pylist(), texts(part, text_col), strict=True):
                    held[lang].update(WORD.findall(text.lower()))
                if sum(map(len, held.values())) > WORD_CACHE:
                    yield flush()
        yield flush()

    return docs.select(lang_col, text_col).mapInArrow(run, "lang string, word string, n bigint").groupBy("lang", "word").agg(F.sum("n").alias("n"))


def fit_language_model(docs: DataFrame, lang_col: str = "lang", text_col: str = "text") -> LanguageModel:
    """Fit on all the rows given that have a language; give a sample, as the words of the rows reach the driver."""
    rows = count_words(docs.where(F.col(lang_col).isNotNull()), lang_col, text_col).toArrow()
    return model_of(zip(*(rows.column(c).to_pylist() for c in ("lang", "word", "n")), strict=True))


def model_of(counts: Iterable[tuple[str, str, int]]) -> LanguageModel:
    """The model of (language, word, count) rows."""
    words: dict[str, dict[str, int]] = {}
    grams: dict[str, Counter] = {}
    for lang, word, n in counts:
        words.setdefault(lang, {})[word] = n
        framed, own = f"<{word}>", grams.setdefault(lang, Counter())
        for size in range(1, MAX_GRAM + 1):
            for k in range(len(framed) - size + 1):
                own[framed[k : k + size]] += n
    langs = sorted(words)

    def table(by_lang: dict[str, dict[str, int]]) -> tuple[list[str], np.ndarray]:
        names = sorted({x for lang in langs for x in by_lang[lang]})
        at, out = {x: i for i, x in enumerate(names)}, np.zeros((len(names), len(langs)))
        for i, lang in enumerate(langs):
            out[[at[x] for x in by_lang[lang]], i] = list(by_lang[lang].values())
        return names, out

    (known, n), (pieces, m) = table(words), table(grams)
    if not langs:
        return LanguageModel([], {}, {}, np.zeros(0))
    size = np.array([len(g) for g in pieces])
    total = np.stack([m[size == k].sum(axis=0) for k in range(MAX_GRAM + 1)])
    logs = np.log((n + 0.5) / (n.sum(axis=0) + 0.5 * len(known)))
    gram_logs = np.log((m + 0.5) / (total[size] + 0.5 * len(pieces)))
    return LanguageModel(langs, dict(zip(known, logs, strict=True)), dict(zip(pieces, gram_logs, strict=True)), np.zeros(len(langs)))


def predict_language(docs: DataFrame, model: LanguageModel, keep: list[str], text_col: str = "text") -> DataFrame:
    """Columns keep, then lang_pred and score; one row per input row, no shuffle."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = docs.select(*keep).columns
    schema = docs.select(*keep).schema.add("lang_pred", "string").add("score", "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        width = max(1, len(m.langs))
        rows: dict[str, int] = {}  # row 0: no letter in it
        table = np.zeros((WORD_CACHE + 1, width), np.float32)

        def learn(words: list[str]) -> None:
            nonlocal table
            new = list(set(words) - rows.keys())
            if len(rows) + len(new) > WORD_CACHE:
                rows.clear()
                new = list(set(words))
            lettered = [w for w in new if any(map(str.isalpha, w))]
            rows.update(dict.fromkeys(new, 0))
            at = len(rows) - len(new) + 1
            if at + len(lettered) > len(table):
                table = np.concatenate([table, np.zeros((at + len(lettered) - len(table), width), np.float32)])
            table[at : at + len(lettered)] = m.of_words(lettered)
            rows.update(zip(lettered, range(at, at + len(lettered)), strict=True))

        for batch in batches:
            for part in slices(batch, text_col, 1 << 20):
                split = [WORD.findall(text.lower()) if m.langs else [] for text in texts(part, text_col)]
                if m.langs:
                    learn([w for words in split for w in words])
                ids = np.fromiter((rows[w] for words in split for w in words), np.int64, sum(map(len, split)))
                found, score, end = [], [], 0
                for words in split:
                    own, end = ids[end : end + len(words)], end + len(words)
                    own = own[own > 0]
                    lang, p = UNKNOWN, 0.0
                    if n := len(own):
                        total = table[own].sum(axis=0, dtype=np.float64)
                        best = int(total.argmax())
                        lang, p = m.langs[best], float(1 / np.exp(np.maximum((total - total[best]) / n * min(n, 20), -700)).sum())
                    found.append(lang)
                    score.append(p)
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in names), pa.array(found, pa.string()), pa.array(score, pa.float64())], names=[*names, "lang_pred", "score"])

    columns = [*keep, text_col] if text_col not in keep else keep
    return docs.select(*columns).mapInArrow(run, schema)


def held_out(id_col: str = "doc_id") -> Column:
    """crc32 of the identifier as text, modulo 4, is 2; false for a null identifier."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 4 == 2, F.lit(False))


def training_sample(train: DataFrame, id_col: str, lang_col: str, rows: int = SAMPLE_ROWS) -> DataFrame:
    """About `rows` rows of each language, all of a language with fewer: those of small hash. Only identifiers and
    languages are read to choose them; nothing is ranked, and languages that hold many rows are dealt over tasks."""
    ids = train.select(F.col(id_col).alias("__id"), F.col(lang_col).alias("__lang"))
    draw = F.pmod(F.xxhash64("__id"), F.lit(1 << 40)) / float(1 << 40)
    each = checkpointed(ids.groupBy("__lang").agg(F.count("*").alias("n")))
    hot = checkpointed(dealt(each, "__lang", each.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]))
    drawn = salted(ids, hot, "__lang", F.col("__id")).join(repeated(each, hot, "__lang"), ["__lang", "__salt"])
    picked = checkpointed(drawn.where(draw * F.col("n") < rows).select("__id", "__lang").distinct())
    side = F.broadcast(picked) if picked.count() <= MAX_BROADCAST_ROWS else picked
    return train.join(side, (F.col(id_col) == F.col("__id")) & (F.col(lang_col) == F.col("__lang")), "left_semi")


def identify_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Learn from a sample of the rows that are not held out, predict all rows from their texts alone."""
    docs = docs.select(F.col(id_col).cast("bigint").alias(id_col), F.col(text_col).alias(text_col), F.col(lang_col).alias(lang_col))
    train = docs.where(~held_out(id_col) & F.col(id_col).isNotNull() & F.col(lang_col).isNotNull())
    model = fit_language_model(training_sample(train, id_col, lang_col), lang_col, text_col)
    rows = docs.select(id_col, held_out(id_col).alias("held_out"), text_col)
    return predict_language(rows, model, [id_col, "held_out"], text_col)
