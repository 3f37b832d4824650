"""Language identification by words first, shorter and shorter character n-grams for the rest.

Training counts words and the character n-grams of words per language over a bounded sample of labelled rows (at most about
``PER_LANGUAGE`` rows of each language, chosen by a hash of the id; their whole texts).  A known word scores its smoothed log
frequency in each language; an unseen one the mean over its known n-grams of the longest length that has any.  The posterior
of a document is the softmax of the sums over its words.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import remainder, tidy

PER_LANGUAGE = 4_000
LONGEST_GRAM = 5
#: More values than this are no languages (an error); places of languages are held in 16 bits.
MAX_LANGUAGES = 30_000
#: Words remembered with their logs, new words scored at once, and texts taken at once.
MEMO_WORDS, FRESH_WORDS, BATCH_TEXTS = 100_000, 20_000, 500
SMOOTHING = 0.01
UNDETERMINED = "und"

_WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str | None) -> Counter:
    """Lower-case words (runs of letters) and how often they come."""
    counts = Counter(_WORD.findall(text.lower())) if text else Counter()
    odd = [w for w in counts if not w.isalpha()]
    for w in odd:  # numerals that are word characters but not letters
        n = counts.pop(w)
        if letters := "".join(filter(str.isalpha, w)):
            counts[letters] += n
    return counts


def grams_of(word: str, n: int) -> list[str]:
    marked = f"␂{word}␃"
    return [marked[i : i + n] for i in range(len(marked) - n + 1)] if n > 1 else list(word)


def key_of(word: str) -> int:
    """Hash of a word, unsigned."""
    return xxhash.xxh64_intdigest(word.encode(), 42)


def word_keys(words: list[str]) -> np.ndarray:
    return np.fromiter(map(key_of, words), dtype=np.uint64, count=len(words))


def gram_keys(words: list[str], n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all n-grams of some words (see ``grams_of``), and the word that each is from."""
    marked = "".join([f"␂{w}␃" for w in words]) if n > 1 else "".join(words)
    points = np.frombuffer(marked.encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.uint64)
    sizes = np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 2 * (n > 1)
    owner = np.repeat(np.arange(len(words)), sizes)
    m = max(0, len(points) - n + 1)
    keys = np.zeros(m, dtype=np.uint64)
    for i in range(n):
        keys = (keys + points[i : i + m] + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
        keys ^= keys >> np.uint64(29)
    whole = owner[:m] == owner[n - 1 :]
    return keys[whole], owner[:m][whole]


class LanguageModel:
    """Log frequencies per language of words (length 0) and of character n-grams: for each length the entries' keys in order,
    and for each key its languages and their logs, where the others have that of a count of nothing."""

    def __init__(self, languages: np.ndarray, names: list[str], lengths: np.ndarray, keys: np.ndarray, counts: np.ndarray) -> None:
        """One entry each: place of the language in ``names``, length, key (unsigned) of the word or n-gram, count."""
        self.languages = names
        self._tables: list[tuple[np.ndarray, ...]] = []
        for n in range(LONGEST_GRAM + 1):
            own = np.flatnonzero(lengths == n)
            own = own[np.lexsort((languages[own], keys[own]))]
            at, seen = languages[own], counts[own].astype(np.float64)
            distinct, starts = np.unique(keys[own], return_index=True)
            totals = np.log(np.bincount(at, weights=seen, minlength=len(names)) + SMOOTHING * max(1, len(distinct)))
            logs = (np.log(seen + SMOOTHING) - totals[at]).astype(np.float32)
            self._tables.append((distinct, np.append(starts, len(own)), at.astype(np.int16), logs, np.log(SMOOTHING) - totals))
        self.forget()

    def _found(self, n: int, keys: np.ndarray, owner: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
        """For each of some words the mean logs over its known words or n-grams of a length, and how many are known."""
        table, starts, at, logs, nothing = self._tables[n]
        k = len(self.languages)
        if not len(table) or not len(keys):
            return np.zeros((words, k)), np.zeros(words, dtype=np.int64)
        places = np.minimum(table.searchsorted(keys), len(table) - 1)
        known = np.flatnonzero(table[places] == keys)
        places, owner = places[known], owner[known]
        seen = np.bincount(owner, minlength=words)
        sizes = starts[places + 1] - starts[places]
        entry = np.repeat(starts[places] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())
        slot = np.repeat(owner, sizes) * k + at[entry]
        more = np.bincount(slot, weights=logs[entry] - nothing[at[entry]], minlength=words * k).reshape(words, k)
        return more / np.maximum(seen, 1)[:, None] + nothing, seen

    def _scores(self, words: list[str]) -> np.ndarray:
        """Rows of logs per language: of the word, or of its known n-grams of the longest length that has any."""
        out = np.zeros((len(words), len(self.languages)))
        left = np.arange(len(words))
        for n in (0, *range(LONGEST_GRAM, 0, -1)):
            if not len(left):
                break
            own = [words[i] for i in left.tolist()]
            keys, owner = gram_keys(own, n) if n else (word_keys(own), np.arange(len(own)))
            found, seen = self._found(n, keys, owner, len(own))
            out[left[seen > 0]] = found[seen > 0]
            left = left[seen == 0]
        return out

    def forget(self) -> None:
        """Drop the memo of words.  Row 0 is that of no letter at all."""
        self._rows: dict[str, int] = {}
        self._matrix = np.zeros((1, len(self.languages)))

    def predict_all(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        """Languages of some texts and their posteriors; undetermined if there is no letter, or nothing was learnt."""
        names, scores = [UNDETERMINED] * len(texts), [0.0] * len(texts)
        if not self.languages:
            return names, scores
        words = [_WORD.findall(t.lower()) if t else [] for t in texts]
        if len(self._rows) > MEMO_WORDS:
            self.forget()
        fresh = [w for w in dict.fromkeys(chain.from_iterable(words)) if w not in self._rows]
        # numerals that are word characters but not letters
        letters = [w if w.isalpha() else "".join(filter(str.isalpha, w)) for w in fresh]
        for i in range(0, len(fresh), FRESH_WORDS):
            own = [w for w in letters[i : i + FRESH_WORDS] if w]
            at = iter(range(len(self._matrix), len(self._matrix) + len(own)))
            self._rows.update((f, next(at) if w else 0) for f, w in zip(fresh[i : i + FRESH_WORDS], letters[i : i + FRESH_WORDS], strict=True))
            self._matrix = np.concatenate([self._matrix, self._scores(own)])
        row = self._rows.__getitem__
        for i, own in enumerate(words):
            rows = np.fromiter(map(row, own), dtype=np.int64, count=len(own))
            if rows.any():
                total = np.zeros(len(self.languages))
                for at in range(0, len(rows), 10_000):
                    total += self._matrix[rows[at : at + 10_000]].sum(axis=0)
                best = int(total.argmax())
                names[i], scores[i] = self.languages[best], float(1 / np.exp(total - total[best]).sum())
        return names, scores

    def predict(self, text: str | None) -> tuple[str, float]:
        (name,), (score,) = self.predict_all([text])
        return name, score


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["lang", "length", "key", "n"]

    def rows(counts: dict[str, Counter]) -> Iterator[pa.RecordBatch]:
        for language, table in counts.items():
            words, times = list(table), np.fromiter(table.values(), dtype=np.int64, count=len(table))
            for n in range(LONGEST_GRAM + 1):
                keys, owner = gram_keys(words, n) if n else (word_keys(words), np.arange(len(words)))
                distinct, which = np.unique(keys, return_inverse=True)
                seen = np.bincount(which, weights=times[owner], minlength=len(distinct)).astype(np.int64)
                yield pa.record_batch([pa.array([language] * len(distinct), pa.string()), pa.array(np.full(len(distinct), n, dtype=np.int32)), pa.array(distinct.view(np.int64)), pa.array(seen)], names=names)

    held: dict[str, Counter] = defaultdict(Counter)
    for batch in batches:
        for text, language in zip(batch["text"], batch["lang"].to_pylist(), strict=True):
            held[language].update(words_of(text.as_py()))
        if sum(map(len, held.values())) > 300_000:
            yield from rows(held)
            held = defaultdict(Counter)
    yield from rows(held)


def train(labelled: DataFrame, per_language: int = PER_LANGUAGE) -> LanguageModel:
    """Model of the rows (doc_id, text, lang) whose lang isn't null."""
    labelled = labelled.where("lang IS NOT NULL AND text IS NOT NULL").select("doc_id", "text", "lang")
    sizes = labelled.groupBy("lang").count()
    names = sorted(r["lang"] for r in sizes.select("lang").limit(MAX_LANGUAGES + 1).collect())
    if len(names) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} values of lang: no column of languages")
    shares = sizes.select("lang", F.ceil(F.lit(per_language * 1_000_000) / F.col("count")).alias("share"))
    # one row a language, of which there are at most MAX_LANGUAGES
    chosen = labelled.join(F.broadcast(shares), "lang").where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < F.col("share"))
    counts = chosen.select("text", "lang").mapInArrow(tidy(_counts), "lang string, length int, key long, n long")
    kept = counts.groupBy("lang", "length", "key").agg(F.sum("n").alias("n")).toArrow()
    place = {x: i for i, x in enumerate(names)}
    coded = kept["lang"].combine_chunks().dictionary_encode()
    of = np.array([place[x] for x in coded.dictionary.to_pylist()], dtype=np.int64)[coded.indices.to_numpy()] if len(kept) else np.zeros(0, dtype=np.int64)
    told, at = np.unique(of, return_inverse=True)  # a language without letters is none
    return LanguageModel(at, [names[i] for i in told], kept["length"].to_numpy(), kept["key"].to_numpy().astype(np.int64).view(np.uint64), kept["n"].to_numpy())


def identify(docs: DataFrame, model: LanguageModel, pred: str = "lang_pred", score: str = "score") -> DataFrame:
    """``docs`` with the language (column ``pred``) and its posterior (``score``); reads nothing but the column text for it.  Null
    texts are undetermined.  A column of either name that is already there is replaced; name others to keep it."""
    docs = docs.drop(pred, score)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    kinds = {f.name: f.dataType.simpleString() for f in docs.schema}
    schema = ", ".join([*(f"`{n}` {k}" for n, k in kinds.items()), f"`{pred}` string, `{score}` double"])

    def predicted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, BATCH_TEXTS):
                part = batch.slice(at, BATCH_TEXTS)
                names, scores = own.predict_all(part["text"].to_pylist())
                yield pa.record_batch([*part.columns, pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=[*batch.schema.names, pred, score])
        own.forget()

    return docs.mapInArrow(tidy(predicted), schema)


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of every document, learnt from those that aren't held out."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    held_out = remainder("doc_id", 4) == 2
    model = train(docs.where(~held_out))
    found = identify(docs.select("doc_id", "text"), model)
    return found.select("doc_id", held_out.alias("held_out"), "lang_pred", "score")
