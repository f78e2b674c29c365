"""URL filter [native]: rules first, else logistic regression on hashed character n-grams.

Host and path are cut from the URL, their 3- to 5-grams are hashed into `BUCKETS` weights, and
the mean weight through the logistic function says how likely the URL is to be blocked. Cutting,
hashing, rule matching and scoring are SQL expressions over the table of URLs: no shuffle, no
Python. Only the small labelled table is collected, as bucket numbers made by the same
expressions (its size is checked), and fitted by the driver.

Rules name a host, which also covers its subdomains, and a beginning of the path; the longest
that fits decides, of equally long ones that of the longer host. A table of rules, one row for
each host, is broadcast (at most MOST_RULES rules, which is checked) and looked up by a URL's host
suffix, once for each number of labels that rules' hosts have. So neither the expression nor the
work for a URL grows with the number of rules, but for those of its own host.

Nulls: a null URL, or one without `://`, has an empty host and path, fits no rule, and gets the
model's verdict on the empty text. A score at the threshold blocks. Repeated rows are judged
alike, URLs have any length; an empty table stays empty.
"""

from __future__ import annotations

import json
import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

BUCKETS = 1 << 13
SIZES = (3, 4, 5)
MOST_LABELLED, MOST_RULES = 20_000, 10_000

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def name(self) -> str:
        return self.host + self.path


#: The contract's rules.
RULES = (Rule("com", "/", "allow"), Rule("example.com", "/en/", "block"), Rule("www.example.com", "/en/", "allow"), Rule("net", "/es/", "block"), Rule("net", "/fr/", "block"))

# Words of hosts to be blocked (gambling, drugs, adult, advertising, tracking, spam, malware, piracy), and of others.
BAD = "casino poker roulette jackpot slots betting bets wager lottery bingo pills viagra cialis steroids meds adult porn xxx escort webcam ads advert adserver banner popup track tracker tracking clicks spam spammer malware phishing warez crack keygen torrent replica payday cheap free winner win linkfarm".split()
GOOD = "library school university museum news weather recipes garden travel music science history hospital city sports books maps health forum research art theater cooking nature family market energy bank house water language village river mountain theory things other nation station motion action thunder thanks thorn three shirt short line stone table union father mother weather".split()
CONSONANTS, VOWELS = "bcdfghlmnprstvwz", "aeiou"
#: Places on a site, the same on both sides, so that they say nothing.
PLACES = ("/en/12", "/de/3.html", "/", "/fr/9/", "/es/81", "/en/5#top", "/index.html?page=2", "/a/b?utm_source=feed")


def made_up(n: int, seed: int = 7) -> list[str]:
    """Pronounceable names without a meaning, by a linear congruential rule."""
    out, x = [], seed
    for _ in range(n):
        name = ""
        for k in range(6):
            x = (x * 1103515245 + 12345) % (1 << 31)
            name += (CONSONANTS, VOWELS)[k % 2][(x >> 16) % (16, 5)[k % 2]]
        out.append(name)
    return out


def labelled_names() -> list[tuple[str, int]]:
    """(name, label) of the built-in table's sites: each word alone and joined with others of its side."""
    out = []
    for words, label in ((BAD, 1), (GOOD + made_up(60), 0)):
        for k, a in enumerate(words):
            for j, step in enumerate((5, 11, 17, 23)[: 4 if label else 2]):
                b = words[(k + step) % len(words)]
                out.append(((a, f"{a}-{b}", f"{b}-{a}", f"{a}{b}")[(j + 2 * (k % 2)) % 4], label))
    return sorted(dict(out).items())


def _after_scheme(url: Column) -> Column:
    """What follows the first `://`; empty without one."""
    return F.when(url.contains("://"), F.substring(url, F.instr(url, "://") + 3, F.length(url))).otherwise(F.lit(""))


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(_after_scheme(url), r"\A([^/?#]*)", 1), UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(_after_scheme(url), r"\A[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_table(spark: SparkSession, rules: tuple[Rule, ...]) -> tuple[DataFrame, list[int]]:
    """(rule_host, fits): a row for each host, its rules by path; and the numbers of labels of hosts."""
    if len(rules) > MOST_RULES:
        raise ValueError(f"at most {MOST_RULES} rules are supported")
    if len({r.name for r in rules}) < len(rules):
        raise ValueError("two rules for one host and path")
    by: dict[str, list[tuple[int, int, str, str, str]]] = {}
    for r in rules:
        by.setdefault(r.host, []).append((len(r.name), len(r.host), r.path, r.name, r.verdict))
    kind = "struct<rule_host: string, fits: array<struct<size: int, host_size: int, path: string, name: string, verdict: string>>>"
    names = ("size", "host_size", "path", "name", "verdict")
    text = json.dumps([{"rule_host": h, "fits": [dict(zip(names, x, strict=True)) for x in fits]} for h, fits in sorted(by.items())])
    rows = spark.range(1).select(F.explode(F.from_json(F.lit(text), f"array<{kind}>")).alias("r")).select("r.*")
    return rows, sorted({h.count(".") + 1 for h in by})


def with_rule(rows: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Rows (host, path) with `__rule`: the longest rule that fits; null where none does."""
    table, labels = rule_table(rows.sparkSession, rules)
    found = []
    for n in labels:
        own = table.select(F.col("rule_host").alias(f"__host{n}"), F.col("fits").alias(f"__fits{n}"))
        rows = rows.join(F.broadcast(own), F.substring_index("host", ".", -n) == F.col(f"__host{n}"), "left").drop(f"__host{n}")
        found.append(F.coalesce(F.filter(f"__fits{n}", lambda r: F.startswith(F.col("path"), r["path"])), F.array().cast(own.schema[f"__fits{n}"].dataType)))
    if not found:
        return rows.withColumn("__rule", F.lit(None).cast("struct<name: string, verdict: string>"))
    return rows.withColumn("__rule", F.array_max(F.concat(*found))).drop(*[f"__fits{n}" for n in labels])


def buckets(host: Column, path: Column) -> Column:
    """Bucket numbers of all n-grams of host and path, repeats included."""
    text = F.concat(F.lit("^"), host, F.lit("$"), path, F.lit("$"))
    grams = [F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(text) - n + 1)), lambda i, n=n: F.pmod(F.xxhash64(F.substring(text, i, F.lit(n))), F.lit(BUCKETS)).cast("int")) for n in SIZES]
    return F.concat(*grams)


def probability(grams: Column, weights: list[float], bias: float) -> Column:
    table = F.split(F.lit(",".join(f"{w:.6g}" for w in weights)), ",").cast("array<double>")
    total = F.aggregate(grams, F.lit(0.0), lambda a, b: a + F.get(table, b))
    return 1 / (1 + F.exp(-(F.lit(bias) + total / F.sqrt(F.size(grams)))))


def fit(rows: list[tuple[list[int], int]], rounds: int = 12, rate: float = 0.3, penalty: float = 1e-4) -> tuple[list[float], float]:
    """Weights and bias by steps of an example each, scaled by what a weight has moved so far; plain Python over a small table.

    Examples come in a fixed order that mixes them.
    """
    weights, moved, bias, data = [0.0] * BUCKETS, [1e-6] * BUCKETS, 0.0, []
    for grams, y in rows:
        counts: dict[int, float] = {}
        for g in grams:
            counts[g] = counts.get(g, 0.0) + 1 / math.sqrt(len(grams))
        data.append((list(counts.items()), y))
    data = [data[k] for k in sorted(range(len(data)), key=lambda k: (k * 0x9E3779B1) % (1 << 32))]
    for _ in range(rounds):
        for x, y in data:
            d = 1 / (1 + math.exp(-max(-30.0, min(30.0, bias + sum(weights[k] * v for k, v in x))))) - y
            bias -= 0.02 * rate * d
            for k, v in x:
                g = d * v + penalty * weights[k]
                moved[k] += g * g
                weights[k] -= rate * g / math.sqrt(moved[k])
    return weights, bias


def labelled_urls(spark: SparkSession) -> DataFrame:
    """(url, label): the built-in table, 1 for what is to be blocked; each site under four subdomains, at places of all kinds."""
    urls, count = [], [0, 0]
    for name, label in labelled_names():
        for sub in ("", "www.", "m.", "blog."):
            k = count[label] = count[label] + 1
            urls.append((f"{('http', 'https')[k % 2]}://{sub}{name}.example.{('com', 'org', 'net')[k % 3]}{PLACES[(k * 3 + k // 8) % len(PLACES)]}", label))
    rows = ", ".join(f"('{u}', {y})" for u, y in urls)
    return spark.sql(f"select * from values {rows} as t(url, label)")


def train(labelled: DataFrame) -> tuple[list[float], float]:
    named = labelled.where("label in (0, 1)").select(host_of(F.col("url")).alias("h"), path_of(F.col("url")).alias("p"), "url", "label").orderBy("url", "label").limit(MOST_LABELLED + 1)
    rows = named.select(buckets(F.col("h"), F.col("p")).alias("g"), "label").collect()
    if len(rows) > MOST_LABELLED:
        raise ValueError(f"the labelled table is collected; it may have {MOST_LABELLED} rows at most")
    return fit([(r["g"], int(r["label"])) for r in rows])


def judge(pages: DataFrame, labelled: DataFrame, rules: tuple[Rule, ...] = RULES, threshold: float = 0.5) -> DataFrame:
    """page_id, host, path, rule, verdict, block_score for every row."""
    weights, bias = train(labelled)
    cut = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    scored = with_rule(cut, rules).withColumn("block_score", probability(buckets(F.col("host"), F.col("path")), weights, bias))
    own = F.when(F.col("block_score") >= threshold, F.lit("block")).otherwise(F.lit("allow"))
    return scored.select("page_id", "host", "path", F.col("__rule.name").alias("rule"), F.coalesce(F.col("__rule.verdict"), own).alias("verdict"), "block_score")
