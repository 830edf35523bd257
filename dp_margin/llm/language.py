"""Language identification by Bayesian evidence fusion.

The text's likelihood under hashed byte trigrams is combined with the declared markup language, the address suffix and a prior of the host.
All but the trigram model come from grouped aggregation over all rows: soft counts of the text's posterior by host, registered domain,
suffix and declared language. A host's prior is smoothed towards its domain's, that towards the suffix's, and that towards the whole table's.

The trigram model is fitted on a bounded sample of rows with a declared language (SAMPLE_ROWS texts, chosen by their hash, copies once);
everything else covers all rows.

Defined cases: null or empty texts, and texts without letters, have no language, posterior 0, and are rejected; a null declaration, host or
suffix is no evidence; repeated rows, and rows that share a doc_id or have none, are decided each by its own text; extra columns of any name are kept by
``keep_accepted``; an empty table gives no rows. A row's own posterior is one of those that its host's prior and its declaration's likelihood are counted from;
smoothing keeps a host of one row close to its parents.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, materialise, small_or_plain, table, utf8
from .neardup import runs

LANGUAGES = ("de", "en", "es", "fr")
#: Rows of the fitting sample.
SAMPLE_ROWS = 4000
BUCKETS = 1 << 14
#: Trigrams of a text that count as independent evidence at most.
EFFECTIVE = 60
#: Pseudo-rows that a parent level weighs, and pseudo-rows of a declaration's likelihood.
SMOOTHING, DECLARED_SMOOTHING = 20.0, 5.0
#: Least posterior of an accepted document, and least share of letters among its bytes.
LEAST_POSTERIOR, LEAST_LETTERS = 0.5, 0.2

_FOLD = np.arange(256, dtype=np.uint32)
_FOLD[65:91] += 32
_FOLD[[*range(0, 65), *range(91, 97), *range(123, 128)]] = 32
_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123), *range(128, 256)]] = True


def _trigrams(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of the trigram at every byte of the joined texts, and the edges of the texts; runs of non-letters are one mark each."""
    raw = np.frombuffer(b"".join(b" " + t + b" " for t in texts), np.uint8)
    edge = np.concatenate(([0], np.cumsum([len(t) + 2 for t in texts])))
    x = _FOLD[raw]
    h = np.zeros(len(x), np.uint32)
    if len(x) > 2:
        h[2:] = (x[:-2] * np.uint32(0x9E3779B1)) ^ (x[1:-1] * np.uint32(0x85EBCA6B)) ^ (x[2:] * np.uint32(0xC2B2AE35))
        h ^= h >> np.uint32(15)
    blank = np.ones(len(x), bool)
    blank[2:] = (x[2:] == 32) & (x[1:-1] == 32)
    return np.where(blank, np.uint32(BUCKETS), h & np.uint32(BUCKETS - 1)), edge


@dataclass(frozen=True)
class TextModel:
    languages: tuple[str, ...]
    weights: np.ndarray  # (languages, buckets + 1) log-probabilities; the last bucket is no evidence

    def likelihoods(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(texts, languages) tempered log-likelihoods, and the share of letters of each text."""
        out = np.zeros((len(texts), len(self.languages)))
        share = np.zeros(len(texts))
        for lo, hi in runs(texts):
            at, edge = _trigrams(texts[lo:hi])
            used = np.add.reduceat((at < BUCKETS).astype(np.int64), edge[:-1])
            for k in range(len(self.languages)):
                out[lo:hi, k] = np.add.reduceat(self.weights[k][at], edge[:-1], dtype=np.float64)
            out[lo:hi] *= np.minimum(1.0, EFFECTIVE / np.maximum(used, 1))[:, None]
            letters = np.concatenate(([0], np.cumsum(_LETTER[np.frombuffer(b"".join(texts[lo:hi]), np.uint8)])))
            ends = np.concatenate(([0], np.cumsum([len(t) for t in texts[lo:hi]])))
            share[lo:hi] = (letters[ends[1:]] - letters[ends[:-1]]) / np.maximum(ends[1:] - ends[:-1], 1)
        return out, share


def fit_text_model(rows: DataFrame, languages=LANGUAGES, sample: int = SAMPLE_ROWS) -> TextModel:
    """Trigram log-probabilities of each language from a bounded sample of rows (text, declared)."""
    known = rows.where(F.col("declared").isin(*languages) & (F.length("text") > 0)).select("declared", "text", F.xxhash64("text").alias("h"))
    chosen = known.select("h").distinct().orderBy("h").limit(sample)
    drawn = known.join(F.broadcast(chosen), "h", "left_semi").groupBy("h").agg(F.min("declared").alias("declared"), F.min("text").alias("text"))
    bound_batches(rows.sparkSession)

    def tally(batches):
        own = np.zeros((len(languages), BUCKETS + 1), np.int64)
        for b in batches:
            for said, text in zip(b.column(0).to_pylist(), utf8(b.column(1)), strict=True):
                own[languages.index(said)] += np.bincount(_trigrams([text])[0], minlength=BUCKETS + 1)
        at = np.flatnonzero(own.ravel())
        for lo in range(0, len(at), 1 << 12):
            yield pa.record_batch([pa.array(at[lo : lo + (1 << 12)]), pa.array(own.ravel()[at[lo : lo + (1 << 12)]])], ["at", "n"])

    counts = np.full(len(languages) * (BUCKETS + 1), 0.5)
    for r in drawn.select("declared", "text").mapInArrow(tally, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).collect():  # languages x buckets at most
        counts[r["at"]] += r["n"]
    counts = counts.reshape(len(languages), BUCKETS + 1)
    p = np.log(counts[:, :BUCKETS] / counts[:, :BUCKETS].sum(1, keepdims=True))
    return TextModel(tuple(languages), np.concatenate((p, np.zeros((len(languages), 1))), 1).astype(np.float32))


def _posterior(log: np.ndarray) -> np.ndarray:
    p = np.exp(log - log.max(axis=1, keepdims=True))
    return p / p.sum(axis=1, keepdims=True)


def evidence(rows: DataFrame, model: TextModel) -> DataFrame:
    """Soft counts (host, domain, suffix, declared, n, s0, s1, ...): sums of the text's posterior, over all rows, in one aggregation."""
    bound_batches(rows.sparkSession)
    names = [f"s{k}" for k in range(len(model.languages))]

    def run(batches):
        for b in batches:
            ll, share = model.likelihoods(utf8(b.column(0)))
            p = _posterior(ll)[share >= LEAST_LETTERS]
            keep = pa.array(share >= LEAST_LETTERS)
            yield pa.record_batch([*(b.column(j).filter(keep) for j in range(1, 5)), *(pa.array(p[:, k]) for k in range(len(names)))], ["host", "domain", "suffix", "declared", *names])

    schema = "host string, domain string, suffix string, declared string, " + ", ".join(f"{s} double" for s in names)
    soft = rows.select("text", "host", "domain", "suffix", "declared").mapInArrow(run, schema)
    return materialise(soft.groupBy("host", "domain", "suffix", "declared").agg(F.count("*").alias("n"), *(F.sum(s).alias(s) for s in names)))


def _level(soft: DataFrame, keys: list[str], parent: DataFrame | None, up: list[str], k: int, smoothing: float) -> DataFrame:
    """(keys, p0, p1, ...): mean posterior at a level, smoothed towards its parent's."""
    names = [f"s{i}" for i in range(k)]
    own = soft.groupBy(*keys).agg(F.sum("n").alias("n"), *(F.sum(s).alias(s) for s in names)) if keys else soft.agg(F.sum("n").alias("n"), *(F.sum(s).alias(s) for s in names))
    if parent is None:
        return own.select(*keys, *[((F.coalesce(F.col(s), F.lit(0.0)) + 1.0) / (F.coalesce(F.col("n"), F.lit(0)) + k)).alias(f"p{i}") for i, s in enumerate(names)])
    both = own.join(parent, up) if up else own.crossJoin(F.broadcast(parent))  # the parent of the top level is one row
    return both.select(*keys, *[((F.col(s) + smoothing * F.col(f"p{i}")) / (F.col("n") + smoothing)).alias(f"p{i}") for i, s in enumerate(names)])


def host_priors(soft: DataFrame, k: int, smoothing: float = SMOOTHING) -> DataFrame:
    """(host, domain, suffix, p0, ...), the prior of every host; levels are joined by their own keys, never by rows of documents."""
    named = soft.fillna("", ["host", "domain", "suffix"])
    top = _level(named, [], None, [], k, smoothing)
    suffix = _level(named, ["suffix"], top, [], k, smoothing)
    domain = _level(named, ["suffix", "domain"], suffix, ["suffix"], k, smoothing)
    return materialise(_level(named, ["suffix", "domain", "host"], domain, ["suffix", "domain"], k, smoothing))


def declared_likelihoods(soft: DataFrame, k: int, smoothing: float = DECLARED_SMOOTHING) -> DataFrame:
    """(declared, hint): log P(value | language) of every declared value, however many there are."""
    names = [f"s{i}" for i in range(k)]
    own = soft.where("declared IS NOT NULL").groupBy("declared").agg(*(F.sum(s).alias(s) for s in names))
    total = own.agg(F.count("*").alias("values"), *(F.sum(s).alias(f"t{i}") for i, s in enumerate(names)))  # one row
    hint = [F.log((F.col(s) + smoothing / F.col("values")) / (F.col(f"t{i}") + smoothing)) for i, s in enumerate(names)]
    return materialise(own.crossJoin(F.broadcast(total)).select("declared", F.array(*hint).alias("hint")))


def classify(rows: DataFrame, model: TextModel | None = None, keep: list[str] | None = None) -> DataFrame:
    """rows (text, declared, host, domain, suffix) with the columns of ``keep`` and dm_lang, dm_posterior, dm_agrees, dm_accepted."""
    model = model or fit_text_model(rows)
    k, keep = len(model.languages), keep or []
    soft = evidence(rows, model)
    priors = host_priors(soft, k)
    hints = declared_likelihoods(soft, k).withColumnRenamed("declared", "dm_said")
    named = priors.select(F.col("host").alias("dm_host"), F.col("domain").alias("dm_domain"), F.col("suffix").alias("dm_suffix"), F.array(*[F.log(f"p{i}") for i in range(k)]).alias("dm_prior"))
    on = [F.coalesce(F.col(c), F.lit("")) == F.col(f"dm_{c}") for c in ("host", "domain", "suffix")]
    joined = rows.join(small_or_plain(named), on, "left").join(small_or_plain(hints), F.col("declared") == F.col("dm_said"), "left")
    joined = joined.select(*keep, F.col("text").alias("dm_text"), F.col("declared").alias("dm_declared"), "dm_prior", F.col("hint").alias("dm_hint"))
    schema = joined.select(*keep, F.lit("").alias("dm_lang"), F.lit(0.0).alias("dm_posterior"), F.lit(True).alias("dm_agrees"), F.lit(True).alias("dm_accepted")).schema
    for f in schema:
        f.nullable = True
    bound_batches(rows.sparkSession)

    def run(batches):
        for b in batches:
            m = len(keep)
            ll, share = model.likelihoods(utf8(b.column(m)))
            said = b.column(m + 1).to_pylist()
            prior, hint = (np.array([x if x is not None else [0.0] * k for x in b.column(j).to_pylist()]).reshape(-1, k) for j in (m + 2, m + 3))
            p = _posterior(ll + prior + hint) if len(said) else np.zeros((0, k))
            best, spoken = p.argmax(1) if len(said) else [], share >= LEAST_LETTERS
            lang = [model.languages[i] if s else None for i, s in zip(best, spoken, strict=True)]
            top = np.where(spoken, p.max(1) if len(said) else 0.0, 0.0)
            yield pa.record_batch([*b.columns[:m], pa.array(lang, pa.string()), pa.array(top), pa.array([None if s is None or x is None else s == x for s, x in zip(said, lang, strict=True)], pa.bool_()), pa.array(top >= LEAST_POSTERIOR)], schema.names)

    return joined.mapInArrow(run, schema)


def of_documents(docs: DataFrame) -> DataFrame:
    """The evidence columns of documents: the source stands for the host."""
    return docs.select(*[F.col(c).alias(f"dm_own_{i}") for i, c in enumerate(docs.columns)], F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("declared"), F.col("source").cast("string").alias("host"), F.lit(None).cast("string").alias("domain"), F.lit(None).cast("string").alias("suffix"))


def of_pages(pages: DataFrame) -> DataFrame:
    """The evidence columns of web pages: visible text, the html element's language, host, registered domain and suffix."""
    html = F.coalesce("html", F.lit(""))
    text = F.regexp_replace(F.regexp_replace(html, r"(?is)<(script|style|nav|footer|head)\b.*?</\1>|<!--.*?-->", " "), r"(?s)<[^>]*>|&[#\w]+;", " ")
    host = F.lower(F.regexp_extract("url", r"^[a-z]+://([^/:?#]+)", 1))
    said = F.lower(F.regexp_extract(html, r"(?i)<html[^>]*\blang=[\"']?([A-Za-z]{2})", 1))
    some = lambda c: F.when(c != "", c)
    return pages.select("page_id", "url", text.alias("text"), some(said).alias("declared"), some(host).alias("host"), some(F.regexp_extract(host, r"([^.]+\.[^.]+)$", 1)).alias("domain"), some(F.regexp_extract(host, r"([^.]+)$", 1)).alias("suffix"))


def keep_accepted(docs: DataFrame) -> DataFrame:
    """Pipeline form: documents with an accepted language, with all their columns."""
    names = [f"dm_own_{i}" for i in range(len(docs.columns))]
    done = classify(of_documents(docs), keep=names).where("dm_accepted")
    return done.select(*[F.col(n).alias(c) for n, c in zip(names, docs.columns, strict=True)])


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, lang, posterior, agrees, accepted) for every document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    done = classify(of_documents(docs), keep=["dm_own_0"])
    return done.select(F.col("dm_own_0").alias("doc_id"), F.col("dm_lang").alias("lang"), F.round("dm_posterior", 6).alias("posterior"), F.col("dm_agrees").alias("agrees"), F.col("dm_accepted").alias("accepted"))


def lang_id_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same for web pages, where markup, suffixes and hosts all speak."""
    done = classify(of_pages(table(spark, sf_dir, "pages")), keep=["page_id", "url"])
    return done.select("page_id", "url", F.col("dm_lang").alias("lang"), F.round("dm_posterior", 6).alias("posterior"), F.col("dm_agrees").alias("agrees"), F.col("dm_accepted").alias("accepted"))
