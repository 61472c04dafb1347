"""URL filter: rules by host and path first, else logistic regression on hashed character n-grams of both."""

from __future__ import annotations

import csv
import zlib
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import LOWER, UPPER

#: Rules of the shared test setting: host and path in one string, and the verdict. Fixed values.
RULES = {"com/en/": "block", "example.com/en/7": "allow", "net/de/": "allow", "example.net/de/8": "block", "org/es/": "block"}
SLOTS, SHORTEST, LONGEST = 1 << 15, 3, 5
#: Urls with fewer n-grams weigh as if they had so many: little is known of them.
LIGHT = 60
#: Share of harmless urls that may be blocked: unwanted urls are rarer than in the labelled table.
WRONG = 0.05
#: The small labelled table: unwanted (0 or 1) and url, written by hand from common knowledge of what block lists and
#: web directories hold; its path is a parameter of labelled().
LABELS = Path(__file__).with_name("url_labels.csv")


def labelled(path: Path | str = LABELS) -> list[tuple[str, str, int]]:
    """The training table: (host, path, 1 for unwanted)."""
    rows = []
    with open(path, newline="", encoding="utf-8") as f:
        for r in csv.DictReader(f):
            host, slash, rest = r["url"].partition("://")[2].partition("/")
            rows.append((host.lower(), slash + rest, int(r["unwanted"])))
    return rows


def slots(host: str, path: str) -> list[int]:
    """The distinct slots of the n-grams of host and path, each marked with where it is from."""
    found = set()
    for mark, text in ((b"h", f"^{host}$"), (b"p", f"^{path}$")):
        data = text.encode()
        for n in range(SHORTEST, LONGEST + 1):
            found.update(zlib.crc32(mark + data[i : i + n]) % SLOTS for i in range(len(data) - n + 1))
    return sorted(found)


def fit(rows: list[tuple[str, str, int]], rounds: int = 1000, rate: float = 0.5, decay: float = 1e-4) -> tuple[np.ndarray, float]:
    """Full-batch gradient descent. What no row has seen stays at weight 0."""
    sets = [np.array(slots(h, p)) for h, p, _ in rows]
    y = np.array([r[2] for r in rows], float)
    flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    scale = 1 / np.sqrt([max(LIGHT, len(s)) for s in sets])
    w, b = np.zeros(SLOTS), 0.0
    for _ in range(rounds):
        z = np.bincount(owner, w[flat], len(sets)) * scale + b
        d = (1 / (1 + np.exp(-z)) - y) * scale / len(sets)
        w -= rate * len(sets) / 20 * (np.bincount(flat, d[owner], SLOTS) + decay * w)
        b -= rate * (d / scale).sum()
    return w, b


def probability(host: str, path: str, model: tuple[np.ndarray, float]) -> float:
    """That a url is unwanted."""
    at = slots(host, path)
    return float(1 / (1 + np.exp(-model[0][at].sum() / np.sqrt(max(LIGHT, len(at))) - model[1])))


def held_out(rows: list[tuple[str, str, int]], folds: int = 5) -> np.ndarray:
    """Log odds of every row under a model learnt from the other folds."""
    out = np.zeros(len(rows))
    for k in range(folds):
        model = fit([r for i, r in enumerate(rows) if i % folds != k])
        p = np.array([probability(*r[:2], model) for r in rows[k::folds]])
        out[k::folds] = np.log(p / (1 - p))
    return out


def calibrated(rows: list[tuple[str, str, int]], wrong: float = WRONG) -> tuple[np.ndarray, float]:
    """A model whose bias is lowered until at most a share of wrong of the harmless rows, each held out in turn, is blocked."""
    w, b = fit(rows)
    harmless = held_out(rows)[[not r[2] for r in rows]]
    return w, b - max(0.0, float(np.quantile(harmless, 1 - wrong)))


def split(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url; both empty without '://' or for null."""
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    rest = F.when(at > 0, url.substr(at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(rest.substr(F.length(host) + 1, F.length(rest)), "^[^?#]*", 0)
    return F.translate(host, UPPER, LOWER), path


def matching_rule(host: Column, path: Column, rules: dict[str, str]) -> Column:
    """The longest rule that fits, else null: its host or a subdomain of it, and a path that starts with its path."""
    out = F.lit(None).cast("string")
    for rule in sorted(rules, key=lambda r: (len(r), r)):  # later ones take precedence
        at = rule.find("/") if "/" in rule else len(rule)
        here = ((host == rule[:at]) | host.endswith("." + rule[:at])) & path.startswith(rule[at:])
        out = F.when(here, F.lit(rule)).otherwise(out)
    return out


def judged(pages: DataFrame, rules: dict[str, str] | None = None, model: tuple[np.ndarray, float] | None = None) -> DataFrame:
    """page_id, host, path, rule, verdict and the method's score of every url.

    A null url has empty host and path and is judged as such; repeated urls get the same verdict; urls of any length are
    judged whole; other columns are not read; an empty table gives an empty result.
    """
    rules = RULES if rules is None else rules
    shared = pages.sparkSession.sparkContext.broadcast(model or calibrated(labelled()))  # SLOTS numbers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scores, known = [], {}
            for key in zip(batch.column("host").to_pylist(), batch.column("path").to_pylist()):
                if key not in known:
                    known[key] = probability(*key, shared.value)
                scores.append(known[key])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, pa.float64())], names=[*batch.schema.names, "score"])

    host, path = split(F.col("url"))
    d = pages.select("page_id", host.alias("host"), path.alias("path"))
    d = d.select("*", matching_rule(F.col("host"), F.col("path"), rules).alias("rule"))
    d = d.mapInArrow(run, f"page_id {d.schema[0].dataType.simpleString()}, host string, path string, rule string, score double")
    verdict = F.when(F.col("score") >= 0.5, "block").otherwise("allow")
    for rule, says in rules.items():
        verdict = F.when(F.col("rule") == rule, says).otherwise(verdict)
    return d.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "score")
