"""Language identification with hyperdimensional profiles.

Every letter owns a random +-1 vector. A letter trigram is the element-wise product (binding) of its
three letter vectors, rotated by their distance from the end; a text is the sum (bundle) of its
trigram vectors; a language prototype is the bundle of all texts labelled with it. A text gets the
language whose prototype has the largest cosine with the text's vector.

Letters are case-folded; every run of other characters is one boundary symbol with a vector of its own. The vector
of a letter of any alphabet is drawn from its code point. Sums are integers, so neither partitioning
nor retries change a result. What reaches the driver is one vector per language (at most
MAX_LANGUAGES x DIM numbers), whatever the corpus size.

Defined results: null or letterless text -> `und`, score 0; without any prototype -> `und`, score 0;
equal cosines -> the alphabetically first language; negative cosine -> score 0; a null doc_id belongs
to the learning rows. Repeated rows are separate rows. Extra columns are ignored.
"""

from __future__ import annotations

from functools import cache, lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_blocks, table, tidied

DIM = 512
MAX_LANGUAGES = 10_000
BITS = 21
#: distinct trigrams of a language that a task holds before it adds up equal ones
HELD = 1 << 20


@cache
def _letters() -> np.ndarray:
    """Code point -> code point of the folded letter, 0 for what is no letter."""
    out = np.zeros(0x110000, np.int64)
    for cp in range(0x110000):
        c = chr(cp)
        if c.isalpha():
            out[cp] = ord(c.lower()[0])
    return out


@lru_cache(1 << 16)
def letter_vector(code: int, dim: int) -> np.ndarray:
    """The +-1 vector of a letter, or of the boundary (0)."""
    return np.random.default_rng([7, code]).integers(0, 2, dim, dtype=np.int8) * np.int8(2) - np.int8(1)


def gram_counts(texts: list[str]):
    """Per text, its distinct trigram codes and their counts; None where it has no letter."""
    joined = "\n" + "\n".join(texts) + "\n"
    codes = _letters()[np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)]
    kept = np.flatnonzero((codes > 0) | np.append(True, codes[:-1] > 0))
    codes = codes[kept]
    grams = (codes[:-2] << 2 * BITS) | (codes[1:-1] << BITS) | codes[2:]
    edges = np.cumsum([1] + [len(t) + 1 for t in texts])
    at = np.searchsorted(kept, edges)
    for k in range(len(texts)):
        low, high = at[k], at[k + 1]
        if high > low and codes[low:high].any():
            # one boundary symbol on either side belongs to the text
            end = high if codes[high - 1] == 0 else high + 1
            yield np.unique(grams[low - 1 : end - 2], return_counts=True)
        else:
            yield None


def bundle(grams: np.ndarray, counts: np.ndarray, dim: int) -> np.ndarray:
    """Sum of counts x bound trigram vectors, exact integers held in floats."""
    mask = (1 << BITS) - 1
    own, at = np.unique(np.concatenate([grams >> 2 * BITS, (grams >> BITS) & mask, grams & mask]), return_inverse=True)
    base = np.stack([letter_vector(c, dim) for c in own.tolist()])
    first, second = np.roll(base, 2, 1), np.roll(base, 1, 1)
    x, y, z = at.reshape(3, -1)
    out, kind = np.zeros(dim), np.float32 if counts.sum() < 1 << 23 else np.float64
    for i in range(0, len(grams), 1 << 14):
        part = slice(i, i + (1 << 14))
        bound = first[x[part]]
        bound *= second[y[part]]
        bound *= base[z[part]]
        out += counts[part].astype(kind) @ bound.astype(kind)
    return out


def added(grams: list[np.ndarray], counts: list[np.ndarray]) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """The same trigrams, each once."""
    own, at = np.unique(np.concatenate(grams), return_inverse=True)
    sums = np.zeros(len(own), np.int64)
    np.add.at(sums, at, np.concatenate(counts))
    return [own], [sums]


def learn(docs: DataFrame, text: str = "text", lang: str = "lang", dim: int = DIM) -> dict[str, np.ndarray]:
    """Prototypes of all languages in docs: one pass, one small vector per language and partition shuffled."""

    def partial(batches):
        found: dict[str, tuple[list, list]] = {}
        for batch in batches:
            for langs, texts in in_blocks(batch["lang"], batch["text"]):
                for name, grams in zip(langs, gram_counts(texts), strict=True):
                    if grams is not None:
                        held = found.setdefault(name, ([], []))
                        held[0].append(grams[0])
                        held[1].append(grams[1])
                for name, held in found.items():
                    if sum(map(len, held[0])) > HELD:
                        found[name] = added(*held)
        for name, held in found.items():
            (grams,), (counts,) = added(*held)
            yield pd.DataFrame({"lang": [name], "hv": [bundle(grams, counts, dim).astype(np.int64)]})

    rows = docs.select(F.col(lang).alias("lang"), F.col(text).alias("text")).filter("lang is not null and text is not null")
    sums = (
        rows.mapInPandas(tidied(partial), "lang string, hv array<bigint>")
        .select("lang", F.posexplode("hv").alias("at", "x"))
        .groupBy("lang", "at")
        .agg(F.sum("x").alias("x"))
    )
    got = sums.groupBy("lang").agg(F.sort_array(F.collect_list(F.struct("at", "x"))).alias("hv")).limit(MAX_LANGUAGES + 1).collect()
    if len(got) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages")
    return {r.lang: np.array([x.x for x in r.hv], np.float64) for r in sorted(got, key=lambda r: r.lang)}


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], text: str = "text", dim: int = DIM) -> DataFrame:
    """docs with lang_pred and score appended (columns of these names are replaced)."""
    names = list(prototypes)
    unit = np.array([v / (np.linalg.norm(v) or 1.0) for v in prototypes.values()]).reshape(len(names), dim)

    def label(batches):
        for batch in batches:
            preds, scores = [], []
            for _, texts in in_blocks(batch[text], batch[text]):
                for grams in gram_counts(texts):
                    if grams is None or not names:
                        preds.append("und")
                        scores.append(0.0)
                        continue
                    v = bundle(*grams, dim)
                    cos = unit @ v / (np.linalg.norm(v) or 1.0)
                    best = int(np.argmax(cos))
                    preds.append(names[best])
                    scores.append(min(1.0, max(0.0, float(cos[best]))))
            batch["lang_pred"], batch["score"] = preds, scores
            yield batch

    docs = docs.drop("lang_pred", "score")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInPandas(tidied(label), f"{fields}, lang_pred string, score double")


def split_column(doc_id: str = "doc_id"):
    """True for held-out documents: crc32 of the id's text leaves 2 on division by 4."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 4 == 2, F.lit(False))


def op3_language_id(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang").withColumn("held_out", split_column())
    prototypes = learn(docs.filter("not held_out"))
    return predict(docs.select("doc_id", "held_out", "text"), prototypes).select("doc_id", "held_out", "lang_pred", "score")
