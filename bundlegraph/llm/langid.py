"""Language identification, word first: known words by their log frequency in each language,
unseen words by the longest known character n-grams, down to single characters.

The model is fitted on at most about `train_docs` labelled documents of each language (chosen by a
hash of doc_id), which bounds it by the number of languages; it knows every language that has a
labelled row. Words are kept from `least` occurrences in the sample on, n-grams are counted over all
words. Every document is scored on its whole text.

Nulls: a null text, and one without a letter, gets `und` and score 0. Rows without language are
not learned from. Repeated rows are scored alike; ties go to the language that sorts first; with
no labelled row at all every prediction is `und`, unless `untaught` names another value for texts
that have letters. Other columns are ignored.
"""

from __future__ import annotations

import re
from array import array
from collections import Counter
from collections.abc import Iterable, Iterator, Mapping

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fitted, take_over, trim

_WORD = re.compile(r"[^\W\d_]+")
UNKNOWN = "und"


def fold(doc_id: Column, folds: int) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds))


def sample_each(rows: DataFrame, key: str, group: str, most: int) -> DataFrame:
    """About `most` rows at most of each group, small groups whole: bound of what a fit reads."""
    sizes = rows.groupBy(group).agg(F.count("*").alias("__size"))
    return rows.join(F.broadcast(sizes), group).where(F.pmod(F.xxhash64(F.col(key), F.lit("sample")), F.lit(1 << 30)) < most / F.col("__size") * (1 << 30)).drop("__size")


def grams(word: str, longest: int) -> Iterator[str]:
    w = f" {word} "
    for n in range(1, longest + 1):
        for i in range(len(w) - n + 1):
            yield w[i : i + n]


class Rows(Mapping):
    """Keys and their rows of one table: an array for each key would take several times the room."""

    def __init__(self, at: dict[str, int], table: np.ndarray):
        self.at, self.table = at, table

    def __getitem__(self, key: str) -> np.ndarray:
        return self.table[self.at[key]]

    def __iter__(self) -> Iterator[str]:
        return iter(self.at)

    def __len__(self) -> int:
        return len(self.at)


class WordFirst:
    """Scores of words and n-grams, one column a language."""

    def __init__(self, langs: list[str], words: Rows, parts: Rows, longest: int):
        self.langs, self.words, self.parts, self.longest = langs, words, parts, longest

    @classmethod
    def fit(cls, counted: pa.Table, longest: int, least: int, langs: list[str], mixed: float = 0.1) -> "WordFirst":
        """counted: lang, word, n. `mixed`: weight of the mean over the languages in each one's frequencies, so that the
        words that a language lacks cost it the same whether its sample is small or large."""
        col = {lang: i for i, lang in enumerate(langs)}
        sums = counted.group_by("word").aggregate([("n", "sum")])
        often = set(sums.filter(pc.greater_equal(sums["n_sum"], least))["word"].to_pylist())
        words: dict[str, int] = {}
        word_counts = array("q")
        n_words = np.zeros(len(langs))
        pieces: list[Counter] = [Counter() for _ in langs]
        for b in counted.select(["lang", "word", "n"]).to_batches(max_chunksize=20_000):
            for lang, w, n in zip(*(c.to_pylist() for c in b.columns)):
                n_words[col[lang]] += n
                if w in often or len(w) == 1:
                    i = words.get(w)
                    if i is None:
                        i = words[w] = len(words)
                        word_counts.extend([0] * len(langs))
                    word_counts[i * len(langs) + col[lang]] += n
                mine = pieces[col[lang]]
                for g in grams(w, longest):
                    mine[g] += n
        parts: dict[str, int] = {}
        for mine in pieces:
            for g in mine:
                parts.setdefault(g, len(parts))
        part_counts = np.zeros((len(parts), len(langs)))
        for i, mine in enumerate(pieces):
            for g, n in mine.items():
                part_counts[parts[g], i] = n
            mine.clear()

        def logs(at: dict[str, int], counts: np.ndarray, total: np.ndarray) -> Rows:
            if not at:
                return Rows(at, counts)
            freq = counts / np.maximum(total, 1.0)
            return Rows(at, np.log((1 - mixed) * freq + mixed * freq.mean(axis=1, keepdims=True)))

        word_table = np.array(word_counts, dtype=float).reshape(len(words), len(langs))
        return cls(langs, logs(words, word_table, n_words), logs(parts, part_counts, part_counts.sum(axis=0)), longest)

    def unseen(self, word: str) -> np.ndarray:
        """The word in pieces, each the longest known n-gram from its place."""
        w, i, out, k = f" {word} ", 0, np.zeros(len(self.langs)), 0
        while i < len(w):
            for n in range(min(self.longest, len(w) - i), 0, -1):
                got = self.parts.get(w[i : i + n])
                if got is not None:
                    out = out + got
                    k += 1
                    break
            else:
                n = 1
            i += n
        return out / max(1, k)


class Scorer:
    """A model with a bounded memory of the words that it has seen."""

    def __init__(self, model: WordFirst, room: int = 400_000, untaught: str = UNKNOWN):
        self.model, self.room, self.untaught = model, room, untaught
        self.reset()

    def reset(self) -> None:
        self.index = dict(self.model.words.at)
        known = self.model.words.table
        self.table = np.concatenate([known, np.zeros((self.room, len(self.model.langs)))]).astype(np.float32)

    def score(self, text: str | None) -> tuple[str, float]:
        found = _WORD.findall(text.lower()) if text else ()
        if not any(c.isalpha() for w in found for c in w):
            return UNKNOWN, 0.0
        if not self.model.langs:
            return self.untaught, 0.0
        counts = Counter(found)
        if len(self.index) + len(counts) > len(self.table):
            self.reset()
        if len(counts) > self.room:
            vec = sum((n * self._one(w) for w, n in counts.items()), np.zeros(len(self.model.langs)))
        else:
            index, ids = self.index, []
            for w in counts:
                i = index.get(w)
                if i is None:
                    i = index[w] = len(index)
                    self.table[i] = self.model.unseen(w)
                ids.append(i)
            vec = np.fromiter(counts.values(), dtype=np.float32, count=len(ids)) @ self.table[ids]
        n = len(found)
        z = vec.astype(float) / n * min(n, 40)
        p = np.exp(z - z.max())
        k = int(p.argmax())
        return self.model.langs[k], float(p[k] / p.sum())

    def _one(self, w: str) -> np.ndarray:
        got = self.model.words.get(w)
        return self.model.unseen(w) if got is None else got


def fit_languages(labelled: DataFrame, train_docs: int = 3000, longest: int = 4, least: int = 3) -> WordFirst:
    """labelled: doc_id, text, lang; at most about `train_docs` of each language are read.
    Words are counted on the executors."""
    rows = labelled.where("lang IS NOT NULL AND text IS NOT NULL").select("doc_id", "text", "lang")
    langs = sorted(r.lang for r in rows.select("lang").distinct().collect())  # one row a language
    rows = sample_each(rows, "doc_id", "lang", train_docs).select("doc_id", "text", "lang")

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()

        def out():
            ks = list(seen)
            return pa.RecordBatch.from_arrays([pa.array([k[0] for k in ks], pa.string()), pa.array([k[1] for k in ks], pa.string()), pa.array([seen[k] for k in ks], pa.int64())], ["lang", "word", "n"])

        for b in batches:
            for t, lang in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                for w, n in Counter(_WORD.findall(t.lower())).items():
                    seen[lang, w] += n
            if len(seen) > 200_000:
                yield out()
                seen.clear()
        yield out()

    counted = rows.mapInArrow(count, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    return fitted(counted, lambda t: WordFirst.fit(t, longest, least, langs))  # bounded by the sample


def predict_languages(docs: DataFrame, model: WordFirst, name: str = "lang_pred", score: str = "score", keep: list[str] | None = None, untaught: str = UNKNOWN) -> DataFrame:
    """The columns of `keep` (doc_id if not given) with prediction and score; `untaught` is the
    prediction for texts with letters where the model knows no language."""
    trim()
    kept = keep or ["doc_id"]
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the sample of the fit
    at = kept.index("text") if "text" in kept else len(kept)
    fields = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in kept)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("langid", lambda: None)
        scorer = Scorer(shared.value, untaught=untaught)
        for b in batches:
            got = [scorer.score(t) for t in b.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(kept))), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())], [*kept, name, score])

    return docs.select(*[F.col(f"`{c}`") for c in kept], *([] if "text" in kept else ["text"])).mapInArrow(run, f"{fields}, `{name}` string, `{score}` double")


def language_report(docs: DataFrame, folds: int = 3, held: int = 1, train_docs: int = 3000) -> DataFrame:
    """Learn from the rows outside the held-out fold, predict for every row."""
    mark = fold(F.col("doc_id"), folds)
    model = fit_languages(docs.where(mark != held), train_docs)
    return predict_languages(docs, model).select("doc_id", F.coalesce(fold(F.col("doc_id"), folds) == held, F.lit(False)).alias("held_out"), "lang_pred", "score")
