"""Language of web pages by Bayesian fusion of text, declared language and address.

*Text.* Byte trigrams of the lower-cased visible text, hashed to a fixed number
of buckets, under one smoothed distribution per language, learned from a table
of texts with a language. A text's log-likelihoods are scaled so that it counts
for at most ``evidence`` independent trigrams.
*Host prior.* Each page's text alone gives soft counts of languages, summed by
host, by registered domain, by address suffix and over all pages. A host's
distribution is its counts smoothed towards its domain's, that towards its
suffix's, that towards the whole; a page's own share is taken out of its host's counts.
*Declared language.* The markup's primary language code is evidence through
P(code | language), from the same soft counts, so a code that lies counts little.

The posterior is the normalised product. Columns (page_id, lang, probability,
text_lang, declared, host, host_prior, posterior); posterior lists (lang, p).

Edge cases: null or empty pages have no text evidence and follow their priors;
addresses without a host share the empty one; an undeclared language is a code
of its own; with no training texts the language is null with probability 0;
repeated rows are judged and counted each; ties go to the first language in
order of name; other columns are ignored.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from urllib.parse import urlsplit

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from winjoin.llm import bytetext as B
from winjoin.llm.frames import materialize

BUCKETS = 1 << 13
SLICES = 32
_UNSEEN = re.compile(r"<!--.*?-->|<(script|style|noscript|template)\b[^>]*>.*?</\1\s*>", re.S | re.I)
_ASIDE = re.compile(r"<(nav|header|footer|aside)\b[^>]*>.*?</\1\s*>", re.S | re.I)
_TAG = re.compile(r"<[^>]*>")
_HTML_LANG = re.compile(r"<html\b[^>]*?\blang\s*=\s*[\"']?\s*([A-Za-z]{2,3})\b", re.I)


def visible_text(page: str) -> str:
    """Text of a page without scripts, styles, comments, navigation and tags; entities resolved."""
    return html.unescape(_TAG.sub(" ", _ASIDE.sub(" ", _UNSEEN.sub(" ", page))))


def declared_code(page: str) -> str:
    found = _HTML_LANG.search(page)
    return found.group(1).lower() if found else ""


def address(url: str | None) -> tuple[str, str, str]:
    """Host, registered domain (its last two labels) and suffix (its last label)."""
    try:
        host = (urlsplit(url or "").hostname or "").strip(".").lower()
    except ValueError:
        host = ""
    labels = host.split(".")
    return host, ".".join(labels[-2:]), labels[-1]


def trigram_buckets(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all byte trigrams that lie within a row, and each row's first; no trigram begins with two blanks."""
    raw, offs = B.flat(column)
    raw = B.LOWER[raw]
    raw = np.where(raw <= 32, np.uint8(32), raw)
    if len(raw) < 3:
        return np.zeros(0, np.int64), np.zeros(len(offs), np.int64)
    a = raw.astype(np.uint32)
    code = (a[:-2] << np.uint32(16)) | (a[1:-1] << np.uint32(8)) | a[2:]
    ok = np.ones(len(code), bool)
    for back in (1, 2):  # not over the end of a row, nor from inside a run of blanks
        cut = offs[1:-1] - back
        ok[cut[(cut >= 0) & (cut < len(ok))]] = False
    ok &= ~((raw[:-2] == 32) & (raw[1:-1] == 32))
    at = np.flatnonzero(ok)
    bucket = (code[at] * np.uint32(2654435761)) >> np.uint32(32 - 13)
    return bucket.astype(np.int64), np.searchsorted(at, offs)


def train_text(texts: DataFrame, lang_col: str = "lang", text_col: str = "text", most_languages: int = 256, smoothing: float = 0.5) -> tuple[list[str], np.ndarray]:
    """Languages in order of name and their log distributions over buckets, from all rows with a language."""
    src = texts.select(F.col(f"`{lang_col}`").alias("lang"), F.coalesce(F.col(f"`{text_col}`"), F.lit("")).alias("text")).where("lang IS NOT NULL")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, np.ndarray] = {}
        for batch in batches:
            for p in B.pieces(batch, "text"):
                langs = np.array(p.column(0).to_pylist(), object)
                bucket, first = trigram_buckets(p.column(1))
                row = np.repeat(np.arange(p.num_rows), np.diff(np.append(first[:-1], len(bucket))))
                for lang in set(langs.tolist()):
                    own = np.bincount(bucket[(langs == lang)[row]], minlength=BUCKETS)
                    held[lang] = held[lang] + own if lang in held else own
        rows = [{"lang": k, "slice": s, "n": v.reshape(SLICES, -1)[s].astype(np.int64).tobytes()} for k, v in held.items() for s in range(SLICES)]
        yield pa.RecordBatch.from_pylist(rows, pa.schema([("lang", pa.string()), ("slice", pa.int32()), ("n", pa.binary())]))

    def add(key: tuple, rows: pa.Table) -> pa.Table:
        total = np.zeros(BUCKETS // SLICES, np.int64)
        for n in rows.column("n").to_pylist():
            total += np.frombuffer(n, np.int64)
        return pa.table({"lang": [key[0].as_py()], "slice": pa.array([key[1].as_py()], pa.int32()), "n": pa.array([total.tobytes()], pa.binary())})

    got = src.mapInArrow(count, "lang string, slice int, n binary").groupBy("lang", "slice").applyInArrow(add, "lang string, slice int, n binary")
    rows = got.limit(most_languages * SLICES + 1).collect()  # SLICES rows a language
    langs = sorted({r.lang for r in rows})
    if len(langs) > most_languages:
        raise ValueError(f"more than {most_languages} languages")
    counts = np.zeros((len(langs), SLICES, BUCKETS // SLICES))
    for r in rows:
        counts[langs.index(r.lang), r.slice] = np.frombuffer(r.n, np.int64)
    counts = counts.reshape(len(langs), BUCKETS) + smoothing
    return langs, np.log(counts / counts.sum(axis=1, keepdims=True))


def text_evidence(pages: DataFrame, langs: list[str], table: np.ndarray, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", evidence: float = 40.0) -> DataFrame:
    """Rows (page_id, host, domain, suffix, declared, ll array<double>): scaled log-likelihoods, greatest 0."""
    src = pages.select(F.col(f"`{id_col}`").alias("page_id"), F.col(f"`{url_col}`").alias("url"), F.coalesce(F.col(f"`{html_col}`"), F.lit("")).alias("html"))
    shipped = pages.sparkSession.sparkContext.broadcast(np.ascontiguousarray(table.T))
    size = len(langs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for p in B.pieces(batch, "html"):
                sources = p.column(2).to_pylist()
                bucket, first = trigram_buckets(pa.array([visible_text(h) for h in sources], pa.string()))
                n = np.diff(np.append(first[:-1], len(bucket)))
                ll = np.zeros((p.num_rows, size))
                some = n > 0
                if some.any():
                    ll[some] = np.add.reduceat(shipped.value[bucket], first[:-1][some], axis=0)
                ll *= np.minimum(1.0, evidence / np.maximum(n, 1))[:, None]
                ll -= ll.max(axis=1, keepdims=True) if size else 0
                parts = [address(u) for u in p.column(1).to_pylist()]
                lists = pa.ListArray.from_arrays(pa.array(np.arange(p.num_rows + 1) * size, pa.int32()), pa.array(ll.ravel()))
                yield pa.RecordBatch.from_arrays([p.column(0), *(pa.array([x[j] for x in parts], pa.string()) for j in range(3)), pa.array([declared_code(h) for h in sources], pa.string()), lists], ["page_id", "host", "domain", "suffix", "declared", "ll"])

    return src.mapInArrow(run, f"page_id {src.schema['page_id'].dataType.simpleString()}, host string, domain string, suffix string, declared string, ll array<double>")


def _normal(values: list[Column]) -> list[Column]:
    total = sum(values[1:], values[0])
    return [v / total for v in values]


def fuse(pages: DataFrame, langs: list[str], strength: float = 4.0) -> DataFrame:
    """Posteriors from text evidence and the grouped counts of its own soft labels."""
    if not langs:
        return pages.select("page_id", F.lit(None).cast("string").alias("lang"), F.lit(0.0).alias("probability"), F.lit(None).cast("string").alias("text_lang"), "declared", "host", F.lit(0.0).alias("host_prior"), F.array().cast("array<struct<lang:string,p:double>>").alias("posterior"))
    span = range(len(langs))
    own = [F.exp(F.get("ll", F.lit(i))) for i in span]
    pages = materialize(pages.select("page_id", "host", "domain", "suffix", "declared", "ll", *(v.alias(f"t{i}") for i, v in zip(span, _normal(own)))), "lang-evidence")

    def sums(by: list[str], tag: str) -> DataFrame:
        return pages.groupBy(*by).agg(*(F.sum(f"t{i}").alias(f"{tag}{i}") for i in span))

    hosts = sums(["host", "domain", "suffix"], "h")
    domains = hosts.groupBy("domain", "suffix").agg(*(F.sum(f"h{i}").alias(f"d{i}") for i in span))
    suffixes = domains.groupBy("suffix").agg(*(F.sum(f"d{i}").alias(f"s{i}") for i in span))
    whole = suffixes.agg(*(F.sum(f"s{i}").alias(f"g{i}") for i in span)).first()
    total = sum((whole[f"g{i}"] or 0.0) for i in span)
    base = [((whole[f"g{i}"] or 0.0) + 1.0 / len(langs)) / (total + 1.0) for i in span]

    def smooth(counts: list[Column], prior: list) -> list[Column]:
        n = sum(counts[1:], counts[0])
        return [(c + strength * p) / (n + strength) for c, p in zip(counts, prior)]

    suffixes = suffixes.select("suffix", *(v.alias(f"ps{i}") for i, v in zip(span, smooth([F.col(f"s{i}") for i in span], [F.lit(b) for b in base]))))
    domains = domains.join(suffixes, "suffix").select("domain", *(v.alias(f"pd{i}") for i, v in zip(span, smooth([F.col(f"d{i}") for i in span], [F.col(f"ps{i}") for i in span]))))
    hosts = hosts.join(domains, "domain").select("host", *(f"h{i}" for i in span), *(f"pd{i}" for i in span))
    # codes have two or three letters, so there are less than 20000
    codes = sums(["declared"], "c")
    of_lang = [F.lit((whole[f"g{i}"] or 0.0)) for i in span]
    n_code = sum((F.col(f"c{i}") for i in list(span)[1:]), F.col("c0"))
    share = n_code / F.lit(max(total, 1e-9))
    codes = codes.select("declared", *(((F.col(f"c{i}") + strength * share) / (of_lang[i] + strength)).alias(f"pc{i}") for i in span))
    wide = pages.join(hosts, "host").join(F.broadcast(codes), "declared")
    prior = smooth([F.greatest(F.col(f"h{i}") - F.col(f"t{i}"), F.lit(0.0)) for i in span], [F.col(f"pd{i}") for i in span])
    wide = wide.select("page_id", "host", "declared", *(f"t{i}" for i in span), *(v.alias(f"p{i}") for i, v in zip(span, _normal(prior))), *(f"pc{i}" for i in span))
    joint = wide.select("*", *(v.alias(f"z{i}") for i, v in zip(span, _normal([F.col(f"t{i}") * F.col(f"p{i}") * F.col(f"pc{i}") for i in span]))))

    def best(tag: str) -> Column:
        top = F.greatest(*(F.col(f"{tag}{i}") for i in span)) if len(langs) > 1 else F.col(f"{tag}0")
        out = F.when(F.col(f"{tag}0") == top, F.lit(0))
        for i in list(span)[1:]:
            out = out.when(F.col(f"{tag}{i}") == top, F.lit(i))
        return out

    names = F.array(*(F.lit(x) for x in langs))
    posterior = F.array(*(F.struct(F.lit(x).alias("lang"), F.col(f"z{i}").alias("p")) for i, x in zip(span, langs)))
    joint = joint.withColumn("_b", best("z")).withColumn("_t", best("t"))
    return joint.select(
        "page_id", F.get(names, F.col("_b")).alias("lang"), F.get(F.array(*(F.col(f"z{i}") for i in span)), F.col("_b")).alias("probability"), F.get(names, F.col("_t")).alias("text_lang"),
        "declared", "host", F.get(F.array(*(F.col(f"p{i}") for i in span)), F.col("_b")).alias("host_prior"), posterior.alias("posterior"),
    )


def page_languages(pages: DataFrame, texts: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", lang_col: str = "lang", text_col: str = "text", evidence: float = 40.0, strength: float = 4.0) -> DataFrame:
    langs, table = train_text(texts, lang_col, text_col)
    return fuse(text_evidence(pages, langs, table, id_col, url_col, html_col, evidence), langs, strength)


