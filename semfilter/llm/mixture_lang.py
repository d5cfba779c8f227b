"""Language identification by multilingual mixture inference over n-gram likelihoods."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import session_defaults, tidy

#: Buckets that byte trigrams are hashed to, and the count added to each.
BUCKETS, SMOOTHING = 1 << 16, 0.5
#: Rounds of expectation-maximisation over all languages, and over a chosen set.
ROUNDS, SET_ROUNDS = 12, 4
#: Nats per free proportion and log word.
PENALTY = 2.0
#: Words times languages handled at a time; words remembered by one worker.
CELLS, CACHE_WORDS = 1 << 20, 150_000

_WORDS = re.compile(r"[^\W\d_]+")


def words_of(text: str | None) -> list[str]:
    """Runs of letters, lower-cased."""
    return _WORDS.findall(text.lower()) if text else []


def trigrams(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of every byte trigram of the words in blanks, and where each word's begin.

    A word of n bytes has the n trigrams that do not reach into its neighbour.
    """
    raw = np.frombuffer((" " + " ".join(words) + " ").encode("utf-8", "surrogatepass"), np.uint8).astype(np.uint32)
    code = (raw[:-2] << np.uint32(16)) | (raw[1:-1] << np.uint32(8)) | raw[2:]
    inside = raw[1:-1] != 32
    bucket = ((code * np.uint32(0x9E3779B1)) >> np.uint32(16))[inside].astype(np.int64)
    starts = np.flatnonzero(raw[:-2] == 32)
    return bucket, np.cumsum(np.concatenate([[0], inside]))[starts]


@dataclass(frozen=True)
class LanguageModel:
    """Log-probabilities of trigram buckets, a row a language; its size is fixed by the languages."""

    names: tuple[str, ...]
    logp: np.ndarray


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    seen: dict[str, np.ndarray] = {}
    for batch in batches:
        by: dict[str, list[str]] = {}
        for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            by.setdefault(lang, []).extend(words_of(text))
        for lang, words in by.items():
            if words:
                seen.setdefault(lang, np.zeros(BUCKETS, np.int64))
                seen[lang] += np.bincount(trigrams(words)[0], minlength=BUCKETS)
    for lang, counts in seen.items():
        hit = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(hit), pa.string()), pa.array(hit, pa.int32()), pa.array(counts[hit], pa.int64())], ["lang", "bucket", "n"])


def fit(docs: DataFrame, where: str = "crc32(cast(doc_id as string)) % 5 <> 0") -> LanguageModel:
    """Counts trigrams of every labelled document that ``where`` admits, whole texts, and smooths them.

    Workers count into arrays of fixed size; what reaches the driver is one number for each language
    and bucket, whatever the corpus.
    """
    session_defaults(docs.sparkSession)
    use = docs.filter(where).filter("lang IS NOT NULL AND text IS NOT NULL").select(F.col("lang").cast("string").alias("lang"), "text")
    counts = use.mapInArrow(tidy(_count), "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))
    got = counts.toPandas()
    names = tuple(sorted(got["lang"].unique()))
    table = np.full((len(names), BUCKETS), SMOOTHING)
    for k, name in enumerate(names):
        part = got[got["lang"] == name]
        table[k, part["bucket"]] += part["n"]
    logp = np.log(table) - np.log(table.sum(axis=1, keepdims=True)) if names else table
    return LanguageModel(names, logp.astype(np.float32))


def _em(ratio: np.ndarray, doc: np.ndarray, cuts: np.ndarray, share: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """Proportions of each document after some rounds, and its log-likelihood under them (up to a constant)."""
    n = np.diff(np.append(cuts, len(doc)))[:, None]
    for _ in range(rounds):
        joint = ratio * share[doc]
        joint /= np.maximum(joint.sum(axis=1, keepdims=True), 1e-30)
        share = np.add.reduceat(joint, cuts, axis=0) / n
    return share, np.add.reduceat(np.log(np.maximum((ratio * share[doc]).sum(axis=1), 1e-30)), cuts)


def infer(ratio: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Language shares of documents under the set of languages that penalised likelihood selects.

    ``ratio`` has, for each word, its likelihood in each language over the best one's; ``sizes`` the
    words of each document (none is 0). Expectation-maximisation over all languages orders them by
    share; sets of the first one, two, ... languages are refitted, and the best log-likelihood
    less ``PENALTY`` * ln(words) for every further language wins, up to all of them. No set's log-likelihood
    is above 0, so a document is done once the penalty alone is more than its best set lost. The set of
    one is the language most likely for the whole. Returns shares (0 outside the set) and the sets' sizes.
    """
    d, m = len(sizes), ratio.shape[1]
    doc, cuts = np.repeat(np.arange(d), sizes), np.cumsum(sizes) - sizes
    full, _ = _em(ratio, doc, cuts, np.full((d, m), 1 / m, ratio.dtype), ROUNDS)
    whole = np.add.reduceat(np.log(np.maximum(ratio, 1e-30)), cuts, axis=0)
    best = np.zeros((d, m))
    best[np.arange(d), whole.argmax(axis=1)] = 1
    value, count = whole.max(axis=1), np.ones(d, np.int64)
    order = np.argsort(-full, axis=1, kind="stable")
    for k in range(2, m + 1):
        penalty = PENALTY * (k - 1) * np.log(sizes + 1.0)
        at = np.flatnonzero(value < -penalty)
        if not len(at):
            break
        words = np.flatnonzero(np.isin(np.arange(d), at)[doc]) if len(at) < d else slice(None)
        inside = np.zeros((len(at), m), ratio.dtype)
        np.put_along_axis(inside, order[at, :k], 1, axis=1)
        start = full[at] * inside + 1e-6 * inside
        n = sizes[at]
        share, fit_k = _em(ratio[words], np.repeat(np.arange(len(at)), n), np.cumsum(n) - n, start / start.sum(axis=1, keepdims=True), SET_ROUNDS)
        gain = fit_k - penalty[at]
        better = gain > value[at]
        won = at[better]
        best[won], value[won], count[won] = share[better], gain[better], k
    return best, count


def _identify(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = LanguageModel(*shared.value)
        m = len(model.names)
        place: dict[str, int] = {}
        table = np.zeros((1024, max(1, m)), np.float32)
        for batch in batches:
            texts = [words_of(t) for t in batch.column(1).to_pylist()]
            if len(place) > CACHE_WORDS:
                place = {}
            new = list({w for words in texts for w in words if w not in place}) if m else []
            if new:
                bucket, starts = trigrams(new)
                ll = np.add.reduceat(model.logp[:, bucket], starts, axis=1).T
                top = len(place) + len(new)
                if top > len(table):
                    table = np.concatenate([table[: len(place)], np.zeros((top, m), np.float32)])
                table[len(place) : top] = np.exp(ll - ll.max(axis=1, keepdims=True))
                for w in new:
                    place[w] = len(place)
            langs, scores, mixes = [], [], []
            todo: list[list[str]] = []

            def flush() -> None:
                nonlocal todo
                if todo:
                    sizes = np.array([len(w) for w in todo])
                    index = np.fromiter((place[w] for words in todo for w in words), np.int64, int(sizes.sum()))
                    shares, _ = infer(table[index], sizes)
                    for s in shares:
                        k = int(s.argmax())
                        langs.append(model.names[k])
                        scores.append(float(min(1.0, max(0.0, s[k]))))
                        mixes.append({model.names[x]: float(s[x]) for x in np.flatnonzero(s)})
                todo = []

            cells = 0
            for words in texts:
                if words and m:
                    todo.append(words)
                    cells += len(words) * m
                    if cells > CELLS:
                        flush()
                        cells = 0
                else:
                    flush()
                    cells = 0
                    langs.append("und")
                    scores.append(0.0)
                    mixes.append({})
            flush()
            mix = pa.array([list(x.items()) for x in mixes], pa.map_(pa.string(), pa.float64()))
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in (0, *range(2, batch.num_columns))), pa.array(langs, pa.string()), pa.array(scores, pa.float64()), mix], [batch.schema.names[k] for k in (0, *range(2, batch.num_columns))] + ["lang_pred", "score", "mixture"])

    return run


def identify(docs: DataFrame, model: LanguageModel, *carry: str) -> DataFrame:
    """Predicted language of every whole text: ``doc_id, lang_pred, score, mixture`` and columns to carry along.

    Each word comes from one language, with the likelihood of its trigrams there; a document is a
    mixture. ``score`` is the share of the predicted language, ``mixture`` the shares of the selected set.
    Only the text is an input. Null texts and texts without a letter, and all texts if nothing
    could be learned, give ``und`` with score 0 and no mixture. Ties go to the first name.
    """
    session_defaults(docs.sparkSession)
    kinds = dict(docs.dtypes)
    schema = ", ".join([f"doc_id {kinds['doc_id']}", *(f"`{c}` {kinds[c]}" for c in carry), "lang_pred string", "score double", "mixture map<string,double>"])
    return docs.select("doc_id", "text", *carry).mapInArrow(tidy(_identify(docs.sparkSession.sparkContext.broadcast((model.names, model.logp)))), schema)


def known_language(docs: DataFrame) -> DataFrame:
    """Documents in learned languages, one or several, columns as they came; the others go.

    A document is rejected if it has no letter (or no text): every other one has a set of learned
    languages that covers its words. How well they fit is not tested.
    """
    model = fit(docs)
    whole = docs.select("doc_id", "text", F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"))
    return identify(whole, model, "_row").filter("lang_pred <> 'und' OR size(mixture) > 0").select("_row.*")
