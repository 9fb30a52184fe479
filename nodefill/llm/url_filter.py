"""URL filter: allow and block rules, and naive Bayes over words that a unigram Viterbi splits names into.

Rules have a host and a path. A rule fits its host and all subdomains if the path starts with the rule's; the longest
host wins, then the longest path. Other urls get the method's verdict: host labels and path segments are split at
everything but letters, letters without a gap are split into words by the best sum of unigram log-probabilities, and
multinomial naive Bayes adds up the words' log-odds with the prior's.

Unigrams are counted over the visible words of all pages' html, never over urls, so a name that many urls hold doesn't
become a word for that. The counts are merged into a count-min sketch of DEPTH x 2^CELL_BITS counters, which is what
executors get: no word is cut off, whatever its rank or length, and the size is bounded; in a full sketch rare words
look more frequent than they are. Words of the labelled names have at least SEED_SHARE of all counts.
Naive Bayes learns from the labelled names below and from the hosts of at most LABELLED urls, chosen by hash, that a rule
decides: a host's words, without those of the rules, under the rule's verdict.

Null url or none with `://`: host and path empty, no rule, and the verdict that the prior gives. Without a column `html`,
or with nulls there, those pages give no unigrams. Splits of equal score: the one with the longer last word. Rows with the
same or no page_id are treated one by one. Very long urls are judged whole. Other columns are ignored.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import kernels as K

K.ship(__name__)

DEPTH, CELL_BITS, SHARE_BITS, LONGEST, SEED_SHARE, LABELLED, PRIOR_BLOCK, SMOOTH = 3, 20, 16, 24, 1e-4, 20_000, 0.2, 0.5
SCHEMA = "page_id long, host string, path string, rule string, verdict string, score double, words string"

# Rules (host, path, verdict), and names of sites known to be unwanted or wanted.
RULES = (("com", "/en/", "block"), ("example.com", "/en/7", "allow"), ("net", "/de/", "allow"), ("example.net", "/de/8", "block"), ("org", "/es/", "block"))
UNWANTED = """cheap pills|spam farm|casino bonus|free casino|poker online|bet now|viagra shop|cialis pharmacy|adult cams|sexy girls|xxx video
porn tube|hot singles|payday loan|easy money|get rich|win prize|lottery winner|click here|buy followers|fake watches|replica bags|crack serial
keygen download|warez torrent|free pills|cheap meds|weight loss miracle|forex profit|crypto giveaway|link farm|seo spam|slots jackpot|escort dating"""
WANTED = """daily news|science journal|city library|public school|open data|travel blog|cooking recipes|health guide|music review|art museum
sports report|weather report|history archive|computer club|software manual|code project|garden tips|book review|film festival|local council
university research|language course|map service|train times|bike repair|family photos|nature park|tech forum|photo gallery|work shop
water company|home design|learning center|market report|community radio|mail service|wiki pages|help desk|child care|house plans"""


def seed_names() -> list[tuple[list[str], str]]:
    split = lambda text: [x.split() for x in text.replace("\n", "|").split("|")]
    return [(w, "block") for w in split(UNWANTED)] + [(w, "allow") for w in split(WANTED)]


def train_bayes(names) -> tuple[dict[str, float], float]:
    """Log-odds of block against allow for each word, and of an unseen word, which says nothing: 0."""
    counts = {"block": {}, "allow": {}}
    for words, label in names:
        for w in words:
            counts[label][w] = counts[label].get(w, 0) + 1
    known = {*counts["block"], *counts["allow"]}
    total = {k: sum(v.values()) + SMOOTH * (len(known) + 1) for k, v in counts.items()}
    odds = lambda w: math.log((counts["block"].get(w, 0) + SMOOTH) / total["block"]) - math.log((counts["allow"].get(w, 0) + SMOOTH) / total["allow"])
    return {w: odds(w) for w in sorted(known)}, 0.0


def parts(url: Column) -> tuple[Column, Column]:
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    host = F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    return F.coalesce(F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit("")), F.coalesce(path, F.lit(""))


class Unigrams:
    """Log-probabilities from a count-min sketch of word counts; a word that was never seen has none."""

    def __init__(self, counts: np.ndarray, seeds: dict[str, int]):
        self.counts, self.seeds = counts, seeds  # 12 MB are broadcast
        self.total = int(counts[0].sum(dtype=np.float64)) + sum(seeds.values())
        self.known: dict[str, float | None] = {}
        self.unknown = -math.log(max(2, self.total))

    def get(self, word: str) -> float | None:
        if word not in self.known:
            if len(self.known) > 1_000_000:
                self.known.clear()
            h = xxhash.xxh64_intdigest(word.encode(), seed=42)
            n = min(float(self.counts[d, h >> CELL_BITS * d & (1 << CELL_BITS) - 1]) for d in range(DEPTH)) + self.seeds.get(word, 0)
            self.known[word] = math.log(n / self.total) if n else None
        return self.known[word]


def block_of_cells(key, frame):
    """The counters of one block; at most 2^SHARE_BITS rows."""
    counts = np.zeros(1 << SHARE_BITS, "<f4")
    counts[frame["cell"].to_numpy(np.int64) & (1 << SHARE_BITS) - 1] = frame["n"].to_numpy(np.float32)
    return pd.DataFrame({"depth": [key[0]], "block": [key[1]], "counts": [counts.tobytes()]})


def word_sketch(pages: DataFrame) -> np.ndarray:
    """Counters [depth, cell] of the visible words of all pages: DEPTH x 2^CELL_BITS numbers, however many pages and words.

    Executors turn summed cells into blocks of numbers, so the driver gets the sketch itself and never a row for a cell.
    """
    counts = np.zeros((DEPTH, 1 << CELL_BITS), np.float32)
    if "html" not in pages.columns:
        return counts
    text = F.regexp_replace(F.lower(F.col("html").cast("string")), r"(?s)<(script|style)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>", " ")
    words = pages.select(F.explode(F.regexp_extract_all(text, F.lit("([a-z]+)"), 1)).alias("word")).groupBy("word").agg(F.count("*").alias("n"))
    cell = F.explode(F.array(*[F.struct(F.lit(d).alias("depth"), F.shiftrightunsigned(F.xxhash64("word"), CELL_BITS * d).bitwiseAND((1 << CELL_BITS) - 1).alias("cell")) for d in range(DEPTH)]))
    sums = words.select(cell.alias("at"), "n").groupBy("at.depth", "at.cell").agg(F.sum("n").alias("n"))
    blocks = sums.groupBy("depth", F.shiftright("cell", SHARE_BITS).cast("int").alias("block")).applyInPandas(block_of_cells, "depth int, block int, counts binary")
    for row in blocks.collect():  # DEPTH x 2^CELL_BITS numbers in all
        counts[row["depth"], row["block"] << SHARE_BITS : (row["block"] + 1) << SHARE_BITS] = np.frombuffer(row["counts"], "<f4")
    return counts


def unigram(pages: DataFrame) -> Unigrams:
    counts = word_sketch(pages)
    least = max(1, math.ceil(SEED_SHARE * int(counts[0].sum(dtype=np.float64))))
    return Unigrams(counts, {w: least for words, _ in seed_names() for w in words})


def ruled_names(pages: DataFrame, rules, model: Unigrams) -> list[tuple[list[str], str]]:
    """The words of hosts that a rule decides, with its verdict: each host and verdict once, of at most LABELLED urls."""
    host, path = parts(F.col("url").cast("string"))
    at = pages.select(host.alias("host"), path.alias("path"))
    fits = F.lit(False)
    for h, p, _ in rules:
        fits = fits | (((F.col("host") == h) | F.col("host").endswith("." + h)) & F.col("path").startswith(p))
    rows = at.filter(fits).orderBy(F.xxhash64("host", "path"), "host", "path").limit(LABELLED).collect()
    by_host, own = by_name(rules), {w for h, p, _ in rules for w in re.findall("[a-z]+", (h + p).lower())}
    found = sorted({(r["host"], rule_of(r["host"], r["path"], by_host)[1]) for r in rows})
    named = [([w for run in re.findall("[a-z]+", h) for w in viterbi(run, model) if w not in own and model.get(w) is not None], v) for h, v in found]
    return [(words, v) for words, v in named if words]


def viterbi(run: str, model: Unigrams) -> list[str]:
    """The split of best total log-probability; an unknown word costs more with each letter. Ties: the longer last word."""
    best, back = [0.0], [0]
    for j in range(1, len(run) + 1):
        options = []
        for i in range(max(0, j - LONGEST), j):
            p = model.get(run[i:j])
            options.append((best[i] + (model.unknown - 2.5 * (j - i) if p is None else p), -i))
        score, i = max(options)
        best.append(score)
        back.append(-i)
    out, j = [], len(run)
    while j:
        out.append(run[back[j] : j])
        j = back[j]
    return merge_unknown(out[::-1], model)


def merge_unknown(words: list[str], model) -> list[str]:
    out: list[str] = []
    for w in words:
        if out and model.get(w) is None and model.get(out[-1]) is None:
            out[-1] += w
        else:
            out.append(w)
    return out


def rule_of(host: str, path: str, rules) -> tuple[str, str] | None:
    """The rule with the longest host, then path."""
    labels = host.split(".")
    fits = [(len(h), len(p), h + p, v) for k in range(len(labels)) for h, p, v in rules.get(".".join(labels[k:]), ()) if path.startswith(p)]
    return max(fits)[2:] if fits else None


def by_name(rules) -> dict[str, list]:
    out: dict[str, list] = {}
    for h, p, v in rules:
        out.setdefault(h, []).append((h, p, v))
    return out


def judge_partition(frames, rules, model, odds, unseen, threshold):
    by_host = by_name(rules)
    base = math.log(PRIOR_BLOCK / (1 - PRIOR_BLOCK))
    seen: dict[str, tuple[list[str], float]] = {}
    for frame in frames:
        rows = []
        for page, host, path in zip(frame["page_id"], frame["host"], frame["path"], strict=True):
            words, score = [], base
            for run in re.findall("[a-z]+", (host + "/" + path).lower()):
                if run not in seen:
                    if len(seen) > 200_000:
                        seen.clear()
                    split = viterbi(run, model)
                    seen[run] = split, sum(odds.get(w, unseen) for w in split)
                words += seen[run][0]
                score += seen[run][1]
            found = rule_of(host, path, by_host)
            rule, verdict = found or (None, "block" if score > threshold else "allow")
            rows.append((None if page is None or page != page else int(page), host, path, rule, verdict, 1 / (1 + math.exp(-max(-700.0, min(700.0, score)))), " ".join(words)))
        yield K.id_frame(rows, ["page_id", "host", "path", "rule", "verdict", "score", "words"])


def filter_urls(pages: DataFrame, rules=RULES, threshold: float = 0.0) -> DataFrame:
    """page_id, host, path, rule, verdict, score (probability that naive Bayes gives to block) and the words found."""
    model = unigram(pages)
    odds, unseen = train_bayes(seed_names() + ruled_names(pages, rules, model))
    host, path = parts(F.col("url").cast("string"))
    source = pages.select(F.col("page_id").cast("long").alias("page_id"), host.alias("host"), path.alias("path"))
    shared = pages.sparkSession.sparkContext.broadcast(model)
    return source.mapInPandas(lambda f: judge_partition(f, rules, shared.value, odds, unseen, threshold), SCHEMA)


def op8_host_segmentation_filter(spark, sf_dir: str) -> DataFrame:
    return filter_urls(spark.read.parquet(f"{sf_dir}/pages.parquet"))
