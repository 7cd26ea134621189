"""Random loads grown along existing data: stars of up to ``max_star`` patterns, paths of up to ``max_path``."""

from __future__ import annotations

import random

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from loadshard.sources.mapping import TYPE


def _quote(text: str, kind: str) -> str:
    if kind == "iri":
        return f"<{text}>"
    return text if kind == "num" else '"' + text.replace("\\", "\\\\").replace('"', '\\"') + '"'


def _pick(rows: DataFrame, rng: random.Random) -> dict | None:
    """One row, the first under a random hash; nothing is collected but it."""
    found = rows.orderBy(F.xxhash64("s", "p", "o", F.lit(rng.randrange(1 << 30)))).limit(1).collect()
    return found[0].asDict() if found else None


def random_queries(triples: DataFrame, count: int, seed: int = 1, max_star: int = 6, max_path: int = 4, constant_share: float = 0.3) -> list[tuple[str, str, int]]:
    """(query id, text, weight). Each query starts from a triple of a random property and grows by further triples of
    its subject (star) or of its object (path), so none is empty; objects become constants with ``constant_share``."""
    rng = random.Random(seed)
    properties = sorted(r[0] for r in triples.select("p").distinct().collect())
    out = []
    while len(out) < count:
        start = _pick(triples.where(F.col("p") == rng.choice(properties)), rng)
        if start is None:
            continue
        path = rng.random() < 0.4
        size = rng.randint(1, max_path if path else max_star)
        steps, seen, at = [start], {start["p"]}, start
        while len(steps) < size:
            subject = at["o"] if path else start["s"]
            if path and at["o_kind"] != "iri":
                break
            nxt = _pick(triples.where((F.col("s") == subject) & ~F.col("p").isin(sorted(seen))), rng)
            if nxt is None:
                break
            steps.append(nxt)
            seen.add(nxt["p"])
            at = nxt
        body = []
        for i, t in enumerate(steps):
            s = f"?v{i}" if path else "?v0"
            last = not path or i == len(steps) - 1
            fixed = last and (t["p"] == TYPE or rng.random() < constant_share) and t["o_kind"] != "ts"
            body.append(f"{s} <{t['p']}> " + (_quote(t["o"], t["o_kind"]) if fixed else f"?v{i + 1}" if path else f"?o{i}"))
        out.append((f"r{len(out) + 1:02d}", "SELECT * { " + " . ".join(body) + " }", 1))
    return out


def split(load: list[tuple[str, str, int]], share: float = 0.5, seed: int = 1) -> tuple[list, list]:
    """A training and a test part of a load."""
    mixed = list(load)
    random.Random(seed).shuffle(mixed)
    at = round(len(mixed) * share)
    return sorted(mixed[:at]), sorted(mixed[at:])
