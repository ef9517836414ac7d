"""Language identification by Bayesian fusion of text, markup, address and host evidence."""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .joins import met
from .store import written
from .textkern import slices

BITS = 15
CHAR_N = (1, 2, 3)
#: Labelled texts of each language that the model is fitted on at most: those with the smallest hash of their id.
MAX_TRAINING_ROWS = 500
#: A text counts as so many independent n-grams at most.
STRENGTH = 60.0
#: Weight, in documents, of the level above in each smoothed prior.
SMOOTHING = 5.0

_DROP = re.compile(rb"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>")
_LETTERS = re.compile(rb"[^A-Za-z\x80-\xff]+")
_SEED = np.uint64(0x9E3779B97F4A7C15)


def visible(page: bytes | None) -> bytes:
    """Text of a page without markup, scripts and styles."""
    if not page:
        return b""
    return html.unescape(_DROP.sub(b" ", page).decode("utf-8", "replace")).encode()


def grams(text: bytes | None) -> np.ndarray:
    """Hashed n-grams of letters (UTF-8 bytes, A-Z in lower case, one space between words)."""
    plain = _LETTERS.sub(b" ", text or b"").strip().lower()
    if not plain:
        return np.empty(0, np.int64)
    data = np.frombuffer(b" " + plain + b" ", np.uint8).astype(np.uint64)
    out = []
    for n in CHAR_N:
        h = np.full(len(data) - n + 1, n, np.uint64)
        for k in range(n):
            h = h * np.uint64(257) + data[k : k + len(h)]
        out.append((h * _SEED) >> np.uint64(64 - BITS))
    return np.concatenate(out).astype(np.int64)


@dataclass(frozen=True)
class TextModel:
    languages: tuple[str, ...]
    table: np.ndarray  # n-gram -> log-probability by language

    def likelihood(self, text: bytes | None) -> np.ndarray:
        at = grams(text)
        if not len(at):
            return np.zeros(len(self.languages))
        count = np.bincount(at, minlength=1 << BITS)
        seen = np.flatnonzero(count)
        total = count[seen].astype(np.float64) @ self.table[seen]
        return total * min(1.0, STRENGTH / len(at))


def train(docs: DataFrame, max_rows: int = MAX_TRAINING_ROWS) -> TextModel:
    """n-gram frequencies by language over at most ``max_rows`` labelled texts of each, summed on
    the executors: the driver gets a row for each language and hashed n-gram. Every language of the table is a class, however rare.
    Rows without text, language or doc_id take no part; of repeated rows each counts. A table with no labelled row gives a
    model without languages."""
    rows = docs.filter("text is not null and lang is not null and doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "lang", "text")
    nth = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id"))
    ids = rows.select("doc_id", "lang").distinct().withColumn("nth", nth).filter(F.col("nth") <= max_rows).drop("nth")
    chosen = rows.join(ids, ["doc_id", "lang"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in slices(batches, "text"):
            for lang, t in zip(piece.column("lang").to_pylist(), texts):
                count = np.bincount(grams(t), minlength=1 << BITS)
                seen = np.flatnonzero(count)
                # each text weighs the same, so that one very long text can't rule
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(seen), pa.string()), pa.array(seen), pa.array(count[seen] * 1000.0 / max(1, count.sum()))], names=["lang", "gram", "weight"])

    sums = chosen.mapInArrow(run, "lang string, gram long, weight double").groupBy("lang", "gram").agg(F.sum("weight").alias("weight")).toArrow()
    total: dict[str, np.ndarray] = {lang: np.zeros(1 << BITS) for lang in sums.column("lang").unique().to_pylist()}
    for lang, counts in total.items():
        mine = sums.filter(pc.equal(sums.column("lang"), lang))
        counts[mine.column("gram").to_numpy()] = mine.column("weight").to_numpy()
    languages = tuple(sorted(total))
    table = np.zeros((1 << BITS, len(languages)))
    for k, lang in enumerate(languages):
        table[:, k] = np.log((total[lang] + 0.05) / (total[lang].sum() + 0.05 * (1 << BITS)))
    return TextModel(languages, table)


def page_evidence(pages: DataFrame) -> DataFrame:
    """Pages as ``id, text (html), markup, declared, host``: a row per page. declared is the language code of the html tag, in lower
    case; host that of the address. Both are null where they are missing or can't be read."""
    declared = F.lower(F.regexp_extract("html", r"(?i)<html\b[^>]*?\blang\s*=\s*[\"']?([a-z]{2,3})\b", 1))
    host = F.lower(F.call_function("try_parse_url", F.col("url"), F.lit("HOST")))
    return pages.select(F.col("page_id").cast("long").alias("id"), F.col("html").alias("text"), F.lit(True).alias("markup"), F.when(declared != "", declared).alias("declared"), host.alias("host"))


def document_evidence(docs: DataFrame) -> DataFrame:
    """Documents as ``id, text, markup, declared, host``, a row per document: the source stands for the host (null: none)."""
    return docs.select(F.col("doc_id").cast("long").alias("id"), "text", F.lit(False).alias("markup"), F.lit(None).cast("string").alias("declared"), F.lower(F.col("source").cast("string")).alias("host"))


def _softmax(logs: list[Column]) -> list[Column]:
    top = F.greatest(*logs) if len(logs) > 1 else logs[0]
    parts = [F.exp(x - top) for x in logs]
    total = sum(parts[1:], parts[0])
    return [p / total for p in parts]


def identify(rows: DataFrame, model: TextModel, smoothing: float = SMOOTHING) -> DataFrame:
    """``rows`` (id, text, markup, declared, host, and others that are passed on but for text) with
    ``text_lang, lang, probability``.

    Text likelihoods alone give each row soft counts. Summed by group they give how often
    a language's pages declare each code and have each address suffix, and priors of
    host, domain, suffix and corpus, each smoothed towards the next wider one; a row's own counts are
    taken out of its priors. The posterior multiplies all of it. A missing evidence counts as
    no evidence; a row with none gets the commonest language. A row per input row, repeated ones too; an empty
    table gives an empty result; a model without languages gives nulls. Groups are pre-aggregated, hot hosts (a thousand at
    most) are broadcast, and columns of any name are handed on.
    """
    keep = [f for f in rows.schema.fields if f.name != "text"]
    names, languages = [f.name for f in keep], model.languages
    if not languages:
        return rows.select(*names, F.lit(None).cast("string").alias("text_lang"), F.lit(None).cast("string").alias("lang"), F.lit(None).cast("double").alias("probability"))
    size = range(len(languages))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in slices(batches, "text"):
            markup = piece.column("markup").to_pylist()
            logs = [model.likelihood(visible(t) if m else t).tolist() for t, m in zip(texts, markup)]
            yield pa.RecordBatch.from_arrays([piece.column("row"), pa.array(logs, pa.list_(pa.float64()))], names=["row", "logs"])

    packed = rows.select("text", "markup", F.struct(*names).alias("row"))
    scored = packed.mapInArrow(run, T.StructType([T.StructField("row", T.StructType(keep)), T.StructField("logs", T.ArrayType(T.DoubleType()))]))
    soft = _softmax([F.col("logs")[k] for k in size])
    declared, host = F.col("row.declared"), F.col("row.host")
    known = F.when(declared.isin(*languages), declared).when(declared.isNotNull(), F.lit("other"))
    scored = written(scored.select("row", "logs", F.array(*soft).alias("soft"), known.alias("code"), host.alias("host")), "language-evidence")

    def added(groups: DataFrame, key: str, name: str, value: str) -> DataFrame:
        """Sums of the arrays in ``value`` by group, and the number of rows."""
        sums = F.array(*[F.sum(F.col(value)[k]) for k in size]).alias(name)
        return groups.filter(F.col(key).isNotNull()).groupBy(key).agg(sums, F.count("*").alias("n"))

    corpus = scored.agg(F.array(*[F.sum(F.col("soft")[k]) for k in size])).first()[0]
    base = [float(x or 0.0) + 1.0 for x in corpus]
    # one row a host, with the sums of its domain and suffix beside its own
    labels = F.split("host", r"\.")
    n = F.size(labels)
    hosts = added(scored, "host", "by_host", "soft").withColumnRenamed("n", "pages")
    hosts = written(hosts.withColumn("suffix", F.when(n > 1, F.element_at(labels, -1))).withColumn("domain", F.when(n > 1, F.concat_ws(".", F.slice(labels, F.greatest(n - 1, F.lit(1)), 2)))), "hosts")
    n_hosts = hosts.count()
    for key, name in (("domain", "by_domain"), ("suffix", "by_suffix")):
        hosts = written(met(hosts, written(added(hosts, key, name, "by_host"), name), [key], "n", n_hosts, how="left"), f"hosts-{key}")
    out = met(scored, hosts.drop("domain", "suffix"), ["host"], "pages", scored.count(), how="left")
    out = out.join(F.broadcast(added(scored, "code", "by_code", "soft").drop("n")), "code", "left")
    total = sum(base)
    prior = [F.lit(b / total) for b in base]
    logs = [F.col("logs")[k] for k in range(len(languages))]

    def counts(name: str) -> list[Column]:
        return [F.greatest(F.coalesce(F.col(name)[k] - F.col("soft")[k], F.lit(0.0)), F.lit(0.0)) for k in range(len(languages))]

    # how likely a language's rows have this suffix or declare this code, smoothed over languages
    for name in ("by_suffix", "by_code"):
        own = counts(name)
        everyone = sum(own[1:], own[0]) / total
        rates = [(c + F.lit(smoothing) * everyone + 1e-3) / (F.lit(base[k]) + smoothing) for k, c in enumerate(own)]
        logs = [x + F.when(F.col(name).isNotNull(), F.log(r)).otherwise(0.0) for x, r in zip(logs, rates)]
    for name in ("by_domain", "by_host"):
        own = counts(name)
        size = sum(own[1:], own[0])
        prior = [F.when(F.col(name).isNull(), p).otherwise((c + F.lit(smoothing) * p) / (size + smoothing)) for c, p in zip(own, prior)]
    out = out.withColumn("prior", F.array(*prior)).withColumn("fused", F.array(*logs))
    out = out.withColumn("post", F.array(*_softmax([F.col("fused")[k] + F.log(F.col("prior")[k]) for k in range(len(languages))])))
    codes = F.array(*[F.lit(x) for x in languages])

    def best(column: str) -> Column:
        return F.element_at(codes, F.array_position(F.col(column), F.array_max(column)).cast("int"))

    return out.select("row.*", best("soft").alias("text_lang"), best("post").alias("lang"), F.array_max("post").alias("probability"))
