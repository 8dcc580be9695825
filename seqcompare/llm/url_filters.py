"""URL filters: fixed rules on host and path, then naive Bayes over the words that hosts and paths are made of.

Host names run words together; a unigram Viterbi splits each run of letters into the likeliest words of a lexicon, whose
counts come from the visible words of all pages. The split is made once for each distinct run: its substrings are joined to
the lexicon, whole, and the runs go back to their urls through joins. The urls that a rule judges are the examples of
``block`` and ``allow``; what the rules themselves name (domains, path segments) is no evidence, so that the model learns
from the words beside it. Multinomial naive Bayes then scores all other urls. Runs common to many urls are scored from a
broadcast table of bounded size (those with a share of ``HEAD_SHARE`` or more); the others, none of which is hot, through
a join.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import batch, tidy, written

#: Runs of letters with a share of this or more are scored from a broadcast: at most 1 / ``HEAD_SHARE`` of them.
HEAD_SHARE = 1e-4
#: Letters of the longest word that a run is split into.
LONGEST = 40
#: What is added to each word's counts.
SMOOTHING = 1.0
#: Log chance of each letter that no word covers.
UNKNOWN = -12.0
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @property
    def text(self) -> str:
        return self.host + self.path


#: The rules of the contract.
RULES = (Rule("block", "net", "/"), Rule("allow", "example.net", "/en/"), Rule("block", "example.com", "/de/"), Rule("allow", "org", "/fr/"))


def parsed(url: Column) -> tuple[Column, Column]:
    """Host and path; both empty for a null url or one without ``://``."""
    at = F.locate("://", url)
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest)), r"^[^?#]*", 0)
    return F.translate(host, _UPPER, _LOWER), path


def ruled(host: Column, path: Column, rules: tuple[Rule, ...] = RULES) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict; null where none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: len(r.text)):
        fits = ((host == r.host) | F.endswith(host, F.lit("." + r.host))) & F.startswith(path, F.lit(r.path))
        name, verdict = F.when(fits, F.lit(r.text)).otherwise(name), F.when(fits, F.lit(r.verdict)).otherwise(verdict)
    return name, verdict


def word_counts(html: DataFrame) -> DataFrame:
    """(word, n): visible words of pages, letters only and not longer than a lexicon word may be."""
    text = F.lower(F.regexp_replace(F.regexp_replace("html", r"(?s)<(script|style)\b.*?</\1>", " "), r"<[^>]*>", " "))
    words = html.where(F.col("html").isNotNull()).select(F.explode_outer(F.split(text, r"[^\p{L}]+")).alias("word"))
    return words.where(f"word is not null and length(word) between 1 and {LONGEST}").groupBy("word").agg(F.count("*").alias("n"))


def runs_of(text: Column) -> Column:
    """Runs of letters, and a 0 for each run of digits."""
    return F.transform(F.regexp_extract_all(F.lower(text), F.lit(r"(\p{L}+|\d+)"), 1), lambda x: F.when(x.rlike(r"^\d"), "0").otherwise(x))


def named(rules: tuple[Rule, ...]) -> list[str]:
    """Words that the rules' hosts and paths are made of."""
    return sorted({w for r in rules for part in (r.host.split("."), r.path.split("/")) for w in part if w})


def best_split(length: int, edges: list[tuple[int, int, float]], unknown: float = UNKNOWN) -> list[tuple[int, int]]:
    """Bounds of the likeliest words of a run: edges are (start, end, log chance); letters no word covers go one by one.

    Of equal splits the one with the longer last word wins.
    """
    best, back = [0.0] + [-math.inf] * length, [0] * (length + 1)
    by_end: list[list[tuple[int, float]]] = [[] for _ in range(length + 1)]
    for start, end, log in edges:
        by_end[end].append((start, log))
    for end in range(1, length + 1):
        for start, log in sorted([*by_end[end], (end - 1, unknown)]):
            if best[start] + log > best[end]:
                best[end], back[end] = best[start] + log, start
    out, at = [], length
    while at:
        out.append((back[at], at))
        at = back[at]
    return out[::-1]


def segmented(runs: DataFrame, counts: DataFrame) -> DataFrame:
    """(run, words) for distinct runs: the likeliest split into words of (word, n), letters that no word covers alone.

    Substrings of up to ``LONGEST`` letters are joined to all words. A run without any is all single letters.
    """
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    size = F.length("run")
    starts = runs.select("run", F.explode(F.sequence(F.lit(0), size - 1)).alias("s"))
    spans = starts.select("run", "s", F.explode(F.sequence(F.lit(1), F.least(F.lit(LONGEST), size - F.col("s")))).alias("l"))
    found = spans.select("run", "s", "l", F.substring("run", F.col("s") + 1, F.col("l")).alias("word")).join(counts, "word")
    edges = found.groupBy("run").agg(F.sort_array(F.collect_list(F.struct("s", (F.col("s") + F.col("l")).alias("e"), F.log(F.col("n") / F.lit(total + 1.0)).alias("log")))).alias("edges"))

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for run, own in zip(b.column("run").to_pylist(), b.column("edges").to_pylist(), strict=True):
                split = best_split(len(run), [(e["s"], e["e"], e["log"]) for e in own or []])
                out.append([run[i:j] for i, j in split])
            yield batch(run=b.column("run"), words=pa.array(out, pa.list_(pa.string())))

    return runs.join(edges, "run", "left").mapInArrow(tidy(step), "run string, words array<string>")


def judged(pages: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """page_id, host, path, rule, verdict, score for every row of pages.

    A null url, or one without ``://``, has an empty host and path: no rule fits, and the method judges it by its prior
    alone. Repeated rows are judged each and counted each. Where rules block nothing, or allow nothing, there is nothing to
    learn and what no rule judges is allowed, with a score of the prior. score is the log odds of ``block``. Other columns
    are not read.
    """
    host, path = parsed(F.col("url"))
    name, verdict = ruled(F.col("host"), F.col("path"), rules)
    rows = pages.select("page_id", host.alias("host"), path.alias("path")).select("page_id", "host", "path", name.alias("rule"), verdict.alias("ruled"))
    no_evidence = F.array(*(F.lit(w) for w in named(rules))).cast("array<string>")
    mine = lambda text, side: F.transform(F.array_except(runs_of(text), no_evidence), lambda x: F.concat(F.lit(side), x))
    urls = rows.withColumns({"row": F.monotonically_increasing_id(), "runs": F.concat(mine(F.col("host"), "h:"), mine(F.col("path"), "p:"))})
    urls = written(urls, "urls")
    blocks, allows = (F.when(F.col("ruled") == v, 1).otherwise(0) for v in ("block", "allow"))
    blocked, allowed = urls.agg(F.coalesce(F.sum(blocks), F.lit(0)), F.coalesce(F.sum(allows), F.lit(0))).first()
    each = urls.select("row", "ruled", F.explode("runs").alias("run"))
    # a row for each distinct run of host or path, with how often it is in blocked and in allowed urls, and in all
    runs = written(each.groupBy("run").agg(F.sum(blocks).alias("block"), F.sum(allows).alias("allow"), F.count("*").alias("n")), "url-runs")
    side, text = F.substring("run", 1, 2).alias("side"), F.expr("substring(run, 3)")
    counts = word_counts(pages.select("html"))
    split = segmented(runs.select(text.alias("run")).distinct(), written(counts, "lexicon"))
    words = runs.select(side, text.alias("run"), "block", "allow", "n").join(split, "run")
    words = written(words.select("side", "run", "block", "allow", "n", F.explode("words").alias("w")).select("side", "run", "block", "allow", "n", F.concat("side", "w").alias("word")), "url-words")
    totals = written(words.groupBy("word").agg(F.sum("block").alias("block"), F.sum("allow").alias("allow")), "url-word-counts")
    in_block, in_allow, kinds = totals.agg(F.coalesce(F.sum("block"), F.lit(0)), F.coalesce(F.sum("allow"), F.lit(0)), F.count("*")).first()
    spread = SMOOTHING * (kinds + 1)
    odds = F.log((F.col("block") + SMOOTHING) / F.lit(in_block + spread)) - F.log((F.col("allow") + SMOOTHING) / F.lit(in_allow + spread))
    learned = F.lit(bool(blocked and allowed))
    scores = words.select("side", "run", "n", "word").join(totals.select("word", F.when(learned, odds).otherwise(0.0).alias("odds")), "word")
    scores = written(scores.groupBy(F.concat("side", "run").alias("run")).agg(F.sum("odds").alias("odds"), F.max("n").alias("n")), "url-run-scores")
    line = HEAD_SHARE * (runs.agg(F.sum("n")).first()[0] or 0)
    head, tail = F.broadcast(scores.where(F.col("n") >= line).select("run", "odds")), scores.where(F.col("n") < line).select("run", "odds")
    token = each.select("row", "run")
    said = token.join(head, "run").unionByName(token.join(head, "run", "left_anti").join(tail, "run"))
    total = said.groupBy("row").agg(F.sum("odds").alias("odds"))
    score = F.coalesce("odds", F.lit(0.0)) + math.log((blocked + 1) / (allowed + 1))
    method = F.when((score > 0) & learned, "block").otherwise("allow")
    return urls.join(total, "row", "left").select("page_id", "host", "path", "rule", F.coalesce("ruled", method).alias("verdict"), score.alias("score"))
