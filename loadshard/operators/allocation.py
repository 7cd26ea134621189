"""Greedy placement of fragments on sites, the remainder's split, replication, and choice of the number of sites."""

from __future__ import annotations

import random
import warnings
from dataclasses import dataclass, field
from math import log2

from pyspark.sql import Column
from pyspark.sql import functions as F

from loadshard.operators.fragments import Fragment, Fragmentation, fragment_edges

FORMS = ("smoothed", "literal", "balance", "affinity", "damped", "random", "round_robin")


@dataclass
class Site:
    number: int
    capacity: float = float("inf")
    fragments: list[int] = field(default_factory=list)
    load: int = 0
    used: float = 0.0


@dataclass
class Placement:
    n: int
    site_of: dict[int, int]
    sites: list[Site]
    split: set[int]  # fragments dealt over all sites by a hash of the subject
    uniform: float
    trace: list[tuple[int, list[float], int]]
    copies: dict[int, set[int]] = field(default_factory=dict)

    def sites_of(self, frag: int) -> list[int]:
        return list(range(1, self.n + 1)) if frag in self.split else sorted({self.site_of[frag], *self.copies.get(frag, ())})

    @property
    def imbalance(self) -> float:
        return max((s.load for s in self.sites), default=0) / self.uniform if self.uniform else 0.0


def benefit(affinity: list[int], load: float, uniform: float, form: str = "smoothed") -> float:
    """What a site gains from a fragment: a balance factor in (0, 2], falling with the site's load, times the joins
    with fragments it already has. affinity: a weight for each fragment there."""
    balance = 2 * uniform / (uniform + load) if uniform + load else 2.0
    if form == "literal":
        return balance * sum(w + 1 for w in affinity)
    if form == "balance":
        return balance
    if form == "affinity":
        return 1.0 + sum(affinity)
    if form == "damped":
        return balance * (1 + log2(1 + sum(affinity)))
    return balance * (1 + sum(affinity))


def allocate(fragments: list[Fragment], edges: dict[tuple[int, int], int], n: int, form: str = "smoothed", capacity: float = float("inf"), bytes_per_triple: float = 1.0, seed: int | None = None, remainder_ratio: float = 2.0) -> Placement:
    """Heaviest fragments first, each to the best site that has room; ties go to the lower fragment and site number,
    or by ``seed`` to any. A remainder beyond ``remainder_ratio`` times the others' mean size is split over all sites
    afterwards. Where no site has room the least used one takes the fragment, with a warning."""
    sites = [Site(i + 1, capacity) for i in range(n)]
    rest = [f for f in fragments if not f.remainder]
    mean = sum(f.size for f in rest) / len(rest) if rest else 0
    split = {f.number for f in fragments if f.remainder and (not rest or f.size > remainder_ratio * mean)}
    placed = [f for f in fragments if f.number not in split]
    uniform = sum(f.load for f in placed) / n
    for s in sites:  # room for the split fragments' shares is kept from the start
        s.used = sum(f.size for f in fragments if f.number in split) * bytes_per_triple / n
    rng = random.Random(seed)
    trace = []
    for turn, f in enumerate(sorted(placed, key=lambda f: (-f.load, f.number))):
        need = f.size * bytes_per_triple
        scores = [benefit([edges.get((min(f.number, g), max(f.number, g)), 0) for g in s.fragments], s.load, uniform, form) for s in sites]
        room = [s for s in sites if s.used + need <= s.capacity]
        if not room:
            warnings.warn(f"no site has room for fragment {f.number}", stacklevel=2)
            best = min(sites, key=lambda s: (s.used, s.number))
        elif form == "random":
            best = rng.choice(room)
        elif form == "round_robin":
            best = room[turn % len(room)]
        else:
            top = max(scores[s.number - 1] for s in room)
            tied = [s for s in room if scores[s.number - 1] == top]
            best = tied[0] if seed is None else rng.choice(tied)
        best.fragments.append(f.number)
        best.load += f.load
        best.used += need
        trace.append((f.number, scores, best.number))
    return Placement(n, {f: s.number for s in sites for f in s.fragments}, sites, split, uniform, trace)


def place(fr: Fragmentation, n: int, form: str = "smoothed", edge_mode: str = "edge_sum", **more) -> Placement:
    return allocate(fr.fragments, fragment_edges(fr, edge_mode), n, form, **more)


def hash_site(n: int, key: str = "s") -> Column:
    """Site of a split fragment's triple: by subject (stars stay together) or by the whole triple, from MD5 so that
    other engines can tell it too."""
    value = F.col("s") if key == "s" else F.concat_ws("\x01", "s", "p", "o")
    return (F.conv(F.substring(F.md5(value), 1, 8), 16, 10).cast("long") % n + 1).cast("int")


def site_column(p: Placement, key: str = "s") -> Column:
    """site_id of rows with frag_id; fragments not placed (met later by inserts) are dealt like the remainder."""
    known = [x for f, s in p.site_of.items() if f not in p.split for x in (F.lit(f), F.lit(s))]
    return F.coalesce(F.try_element_at(F.create_map(*known), F.col("frag_id")), hash_site(p.n, key)) if known else hash_site(p.n, key)


def second_round(p: Placement, fr: Fragmentation, budget: float) -> Placement:
    """Replication: fragments, by gain for each stored triple, are copied to the site where they join most, while the
    copies keep within ``budget`` triples. A scan reads one copy only."""
    edges = fragment_edges(fr)
    by = {f.number: f for f in fr.fragments}
    options = []
    for f, home in p.site_of.items():
        for s in p.sites:
            gain = sum(edges.get((min(f, g), max(f, g)), 0) for g in s.fragments)
            if s.number != home and gain:
                options.append((-gain / max(1, by[f].size), f, s.number))
    copies: dict[int, set[int]] = {}
    left = budget
    for _, f, s in sorted(options):
        if by[f].size <= left:
            copies.setdefault(f, set()).add(s)
            left -= by[f].size
    return Placement(p.n, dict(p.site_of), p.sites, set(p.split), p.uniform, p.trace, copies)


def rebalance(p: Placement, fr: Fragmentation, tolerance: float = 1.5) -> list[tuple[int, int, int]]:
    """(fragment, from, to) moves that bring sites beyond ``tolerance`` times the uniform load back, best benefit first."""
    edges = fragment_edges(fr)
    by = {f.number: f for f in fr.fragments}
    load = {s.number: sum(by[f].load for f in by if p.site_of.get(f) == s.number) for s in p.sites}
    home = dict(p.site_of)
    uniform = sum(load.values()) / p.n
    moves = []
    for s in sorted(load, key=lambda s: -load[s]):
        while load[s] > tolerance * uniform:
            mine = [f for f, h in home.items() if h == s and by[f].load]
            options = []
            for f in mine:
                for t in load:
                    if t != s and load[t] + by[f].load < load[s]:
                        near = [edges.get((min(f, g), max(f, g)), 0) for g, h in home.items() if h == t]
                        options.append((benefit(near, load[t], uniform), by[f].load, -f, t))
            if not options:
                break
            _, _, f, t = max(options)
            f = -f
            home[f] = t
            load[s] -= by[f].load
            load[t] += by[f].load
            moves.append((f, s, t))
    return moves
