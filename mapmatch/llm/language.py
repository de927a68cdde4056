"""Language identification that looks words up first and backs off to characters.

Training counts words by language over a bounded, hash-chosen sample of the labelled documents. A word of the text
that training knows is scored by its smoothed log frequency in each language. An unseen word is scored by its
character n-grams (with word boundaries): the longest length of which any n-gram is known, then shorter ones down to
single characters; a word none of whose characters is known says nothing. The prediction is the language with the
highest sum over all words of the text; the score is its share under a softmax of the mean scores a word, sharpened.

Words are split, counted and scored as Arrow columns and numpy tables, the distinct ones of a slice once. Scores of
words that training has not seen are remembered, up to ``KEEP`` words; when they are full, those of the latest slice stay.

Defined results: words are runs of letters of the lower-cased text; null text, or text without a letter, is ``und`` with
score 0, as is everything if nothing can be learned; a text none of whose words says anything has the first language
and an even share; ties go to the first language in code-point order; repeated rows get equal results; other columns
are ignored by ``predict`` and kept by ``keep_identified``.
"""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import drop_stored, release, stored, text_slices, tidied, worker_slot

#: The most documents of each language that training reads, and the most (language, word) counts that it keeps, the commonest
#: first; what smooths counts; the longest n-grams.
SAMPLE_DOCUMENTS, MOST_WORDS, SMOOTH, LONGEST = 2_000, 100_000, 0.5, 4
#: Unseen words whose scores a worker remembers; characters of a slice.
KEEP, SLICE_CHARS = 200_000, 4_000_000
_NOT_LETTERS = r"[^\p{L}]+"


def words_of(texts: pa.Array) -> pa.ListArray:
    """The words of every text, lower-cased; the empty strings around them stand for nothing."""
    return pc.split_pattern_regex(pc.utf8_lower(pc.fill_null(texts.cast(pa.string()), "")), _NOT_LETTERS)


def _grams(words: pa.StringArray, n: int, alphabet: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of all n-grams of all words, with boundaries if n > 1: the word's place, and a number (-1 with unknown characters)."""
    codes = np.frombuffer("".join(words.to_pylist()).encode("utf-32-le", "surrogatepass"), np.uint32)
    size = pc.utf8_length(words).to_numpy().astype(np.int64)
    ids = np.searchsorted(alphabet, codes)
    known = (ids < len(alphabet)) & (alphabet[np.minimum(ids, len(alphabet) - 1)] == codes) if len(alphabet) else np.zeros(len(codes), bool)
    pad = int(n > 1)
    whole = np.zeros(len(codes) + 2 * pad * len(size), np.int64)  # 0: a boundary
    ends = np.cumsum(size + 2 * pad)
    inner = np.ones(len(whole), bool)
    if pad:
        inner[ends - 1] = inner[ends - size - 2] = False
    whole[inner] = np.where(known, ids + 1, -1)
    count = np.maximum(size + 2 * pad - n + 1, 0)
    word = np.repeat(np.arange(len(size)), count)
    at = np.arange(len(word)) - np.repeat(np.cumsum(count) - count, count) + (ends - size - 2 * pad)[word]
    key, bad, bits = np.zeros(len(word), np.int64), np.zeros(len(word), bool), max(1, int(len(alphabet) + 1).bit_length())
    for i in range(n):
        letter = whole[at + i]
        bad |= letter < 0
        key = key << bits | np.maximum(letter, 0)
    return word, np.where(bad, -1, key)


def _logs(counts: np.ndarray) -> np.ndarray:
    """Smoothed log frequencies, less the mean over the languages so that scores of different lengths compare."""
    logs = np.log(counts + SMOOTH) - np.log(counts.sum(axis=0) + SMOOTH * max(1, len(counts)))
    return logs - logs.mean(axis=1, keepdims=True)


class Model:
    """Log frequencies by language of words and of n-grams, as tables sorted by word or by number."""

    def __init__(self, counts: pa.Table):
        """counts: lang, word, n, one row for each pair."""
        self.languages: list[str] = sorted(set(counts["lang"].to_pylist()))
        distinct = pc.unique(counts["word"].combine_chunks()).sort()
        table = np.zeros((len(distinct), max(1, len(self.languages))))
        at = pc.index_in(counts["word"], value_set=distinct).to_numpy()
        table[at, [self.languages.index(x) for x in counts["lang"].to_pylist()]] = counts["n"].to_numpy()
        self.words, self.word_logs = distinct, _logs(table)
        self.alphabet = np.unique(np.frombuffer("".join(distinct.to_pylist()).encode("utf-32-le", "surrogatepass"), np.uint32))
        self.keys, self.gram_logs = [], []
        for n in range(1, LONGEST + 1):
            word, key = _grams(distinct, n, self.alphabet)
            keys, place = np.unique(key, return_inverse=True)
            sums = np.stack([np.bincount(place.ravel(), table[word, j], minlength=len(keys)) for j in range(table.shape[1])], axis=1) if len(keys) else np.zeros((0, table.shape[1]))
            self.keys.append(keys)
            self.gram_logs.append(_logs(sums))

    def backed_off(self, words: pa.StringArray) -> tuple[np.ndarray, np.ndarray]:
        """Scores of words that training has not seen, and whether they say anything."""
        out, said = np.zeros((len(words), self.word_logs.shape[1])), np.zeros(len(words), bool)
        left = np.arange(len(words))
        for n in range(LONGEST, 0, -1):
            if not len(left) or not len(self.keys[n - 1]):
                continue
            word, key = _grams(words.take(pa.array(left)), n, self.alphabet)
            at = np.minimum(np.searchsorted(self.keys[n - 1], key), len(self.keys[n - 1]) - 1)
            hit = self.keys[n - 1][at] == key
            word, at = word[hit], at[hit]
            times = np.bincount(word, minlength=len(left))
            some = times > 0
            for j in range(out.shape[1]):
                out[left[some], j] = np.bincount(word, self.gram_logs[n - 1][at, j], minlength=len(left))[some] / times[some]
            said[left[some]] = True
            left = left[~some]
        return out, said


class Scorer:
    """A model with the unseen words that one worker has met."""

    def __init__(self, model: Model, keep: int = KEEP):
        self.model, self.keep = model, keep
        self._words, self._scores, self._said = pa.array([], pa.string()), np.zeros((0, model.word_logs.shape[1])), np.zeros(0, bool)

    def _distinct(self, words: pa.StringArray) -> tuple[np.ndarray, np.ndarray]:
        """Scores of distinct words, and whether they say anything."""
        model = self.model
        scores, said = np.zeros((len(words), model.word_logs.shape[1])), np.zeros(len(words), bool)
        at = pc.fill_null(pc.index_in(words, value_set=model.words), -1).to_numpy()
        scores[at >= 0], said[at >= 0] = model.word_logs[at[at >= 0]], True
        rest = np.flatnonzero((at < 0) & (pc.binary_length(words).to_numpy() > 0))
        unseen = words.take(pa.array(rest))
        known = pc.fill_null(pc.index_in(unseen, value_set=self._words), -1).to_numpy()
        old, new = known >= 0, np.flatnonzero(known < 0)
        scores[rest[old]], said[rest[old]] = self._scores[known[old]], self._said[known[old]]
        fresh = unseen.take(pa.array(new))
        found, says = model.backed_off(fresh)
        scores[rest[new]], said[rest[new]] = found, says
        if len(self._words) + len(fresh) > self.keep:
            self._words, self._scores, self._said = unseen, scores[rest], said[rest]
        else:
            self._words = pa.concat_arrays([self._words, fresh])
            self._scores, self._said = np.concatenate([self._scores, found]), np.concatenate([self._said, says])
        return scores, said

    def predict(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        """Language and score of every text."""
        languages, found, score = self.model.languages, [], np.zeros(len(texts))
        for lo, hi in text_slices(texts.cast(pa.string()), SLICE_CHARS):
            best, score[lo:hi] = self._slice(words_of(texts.slice(lo, hi - lo)))
            found += [languages[b] if b >= 0 else "und" for b in best.tolist()]
        return found, score

    def _slice(self, words: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
        n, k = len(words), len(self.model.languages)
        coded = pc.dictionary_encode(words.flatten())
        scores, said = self._distinct(coded.dictionary)
        at = coded.indices.to_numpy()
        offsets = words.offsets.to_numpy() - words.offsets[0].as_py()
        text = np.repeat(np.arange(n), np.diff(offsets))
        letters = np.bincount(text, (pc.binary_length(coded.dictionary).to_numpy() > 0)[at], minlength=n) > 0
        times = np.bincount(text, said[at], minlength=n)
        if not k:
            return np.full(n, -1), np.zeros(n)
        mean = np.stack([np.bincount(text, scores[at, j], minlength=n) for j in range(k)], axis=1) / np.maximum(times, 1)[:, None]
        best = mean.argmax(axis=1)
        share = 1 / np.exp(4 * (mean - mean[np.arange(n), best][:, None])).sum(axis=1)
        return np.where(letters, best, -1), np.where(letters, share, 0.0)


def word_counts(labelled: DataFrame, most: int = MOST_WORDS) -> pa.Table:
    """lang, word, n of the commonest words: those counted at least so often that there are ``most`` at most. labelled: text, lang."""

    @tidied
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lang in pc.unique(batch.column("lang")).to_pylist():
                words = words_of(batch.column("text").filter(pc.equal(batch.column("lang"), lang))).flatten()
                found = pc.value_counts(words.filter(pc.not_equal(words, "")))
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(found), pa.string()), found.field(0), found.field(1)], ["lang", "word", "n"])

    counts = labelled.select("text", "lang").mapInArrow(count, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    rows = stored(counts, "words")
    times = sorted(((r["n"], r["words"]) for r in rows.groupBy("n").agg(F.count("*").alias("words")).collect()), reverse=True)  # different counts are few
    kept = [n for (n, _), upto in zip(times, np.cumsum([words for _, words in times]), strict=True) if upto <= most]
    out = rows.where(F.col("n") >= (kept[-1] if kept else times[0][0] + 1 if times else 1)).toArrow()
    drop_stored(rows)
    return out.sort_by([("lang", "ascending"), ("word", "ascending")])


def train(labelled: DataFrame, sample: int = SAMPLE_DOCUMENTS, most: int = MOST_WORDS) -> Model:
    """Fit on at most ``sample`` documents of each language, of those that have text and lang: the first by a hash of id and text.

    labelled: doc_id, text, lang. A language with fewer documents gives all it has.
    """
    usable = labelled.select(F.col("doc_id").cast("string").alias("id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).where("text IS NOT NULL AND lang IS NOT NULL")
    sizes = {r["lang"]: r["n"] for r in usable.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # a row a language
    if not sizes:
        return Model(pa.table({"lang": pa.array([], pa.string()), "word": pa.array([], pa.string()), "n": pa.array([], pa.int64())}))
    # twice the share first, by the id alone, so that few rows are sorted; then the exact number
    share = F.create_map(*[x for lang, n in sizes.items() for x in (F.lit(lang), F.lit(math.ceil(min(1.0, 2 * sample / n + 64 / n) * (1 << 20))))])
    some = usable.where(F.pmod(F.xxhash64("id"), F.lit(1 << 20)) < F.element_at(share, F.col("lang")))
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("id", F.lit(1)), F.xxhash64("text"), "id"))
    model = Model(word_counts(some.withColumn("place", place).where(F.col("place") <= sample), most))
    release()
    return model


def predict(documents: DataFrame, model: Model, out: tuple[str, str] = ("lang_pred", "score"), keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """The kept columns with the prediction and its score."""
    sent, name = documents.sparkSession.sparkContext.broadcast(model), uuid.uuid4().hex  # bounded by MOST_WORDS

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = worker_slot(("language", name), lambda: Scorer(sent.value))
        for batch in batches:
            found, score = scorer.predict(batch.column("_text"))
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keep], pa.array(found, pa.string()), pa.array(score)], [*keep, *out])

    source = documents.select(*keep, F.col(text).cast("string").alias("_text"))
    fields = ", ".join(f"`{x}` {t}" for x, t in source.select(*keep).dtypes)
    return source.mapInArrow(run, f"{fields}, `{out[0]}` string, `{out[1]}` double")


def keep_identified(documents: DataFrame, model: Model, least: float | None = None) -> DataFrame:
    """The documents, with all their columns, whose language is found with at least this score.

    Unless given, the score must be a half, or with many languages a fifth more than an even share.
    """
    least = min(0.5, 1.2 / max(1, len(model.languages))) if least is None else least
    sent, name = documents.sparkSession.sparkContext.broadcast(model), uuid.uuid4().hex
    at = documents.columns.index("text")

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = worker_slot(("language", name), lambda: Scorer(sent.value))
        for batch in batches:
            found, score = scorer.predict(batch.column(at))
            yield batch.filter(pa.array([x != "und" and s >= least for x, s in zip(found, score.tolist(), strict=True)], pa.bool_()))

    return documents.mapInArrow(run, documents.schema)


def learnable(documents: DataFrame) -> DataFrame:
    """The documents that training may see: those not held out; a null id teaches nothing."""
    return documents.where(F.col("doc_id").isNotNull() & ~held_out("doc_id"))


def held_out(doc_id: str) -> Column:
    """Whether a document belongs to the part of the data that training never sees; a null id does not."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string")), F.lit(4)) == 2, F.lit(False))


def identify(documents: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every document, learned from those not held out (a null id teaches nothing)."""
    return predict(documents, train(learnable(documents))).select("doc_id", held_out("doc_id").alias("held_out"), "lang_pred", "score")
