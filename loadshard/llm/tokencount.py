"""Token counts by a compiled finite-state transducer.

Byte-pair encoding of a pretoken is read left to right: the last token of each prefix's encoding is the
longest vocabulary suffix that stands next to the last token before it. What later bytes can see of a prefix
is bounded by the longest suffix that still opens a vocabulary entry, so a state is that suffix with the last
tokens (and relative counts) at its cuts; a transition on a byte carries the change of the token count. States
are numbered as they are first met. Whole pretokens are kept as composed paths.

Between a non-blank and a blank there is always a pretoken boundary. A chunk's state map is therefore fixed by
its open head, the count of its closed middle and its open tail; such maps compose associatively, and a
parallel prefix scan of them gives the counts of texts that are cut into chunks.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from loadshard.llm.common import table, unused

#: Fixed values of the byte-level vocabularies: pretoken pattern and printable stand-ins of bytes.
PRETOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
PLAIN_BYTES = [*range(33, 127), *range(161, 173), *range(174, 256)]


def byte_letters() -> dict[str, int]:
    rest = [b for b in range(256) if b not in set(PLAIN_BYTES)]
    return {chr(b): b for b in PLAIN_BYTES} | {chr(256 + i): b for i, b in enumerate(rest)}


class Transducer:
    """Compiled counter of one byte-level BPE vocabulary."""

    def __init__(self, path: str, keep_paths: int = 1 << 20, keep_states: int = 1 << 17):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_letters()
        as_bytes = lambda s: bytes(letters[c] for c in s)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
        self.rank = {(as_bytes(a), as_bytes(b)): i for i, (a, b) in enumerate(pairs)}
        self.vocab = {as_bytes(s) for s in spec["model"]["vocab"] if all(c in letters for c in s)}
        self.parts: dict[bytes, tuple[bytes, bytes]] = {}
        for a, b in self.rank:
            self.parts.setdefault(a + b, (a, b))
        self.opens = {t[:k] for t in self.vocab for k in range(1, len(t) + 1)}
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.cut = regex.compile("|".join(map(regex.escape, self.special))) if self.special else None
        self.pretoken = regex.compile(PRETOKEN)
        self.memo, self.whole, self.keep_paths, self.keep_states = {}, {}, keep_paths, keep_states
        self.forget()

    def forget(self) -> None:
        """Starts the numbering of states anew; bounds memory, never results."""
        self.states = [(b"", ((b"", 0),))]
        self.ids = {self.states[0]: 0}
        self.next: dict[int, tuple[int, int]] = {}
        self.memo.clear()

    def stands_beside(self, left: bytes, right: bytes) -> bool:
        """Whether encoding left + right gives exactly these two tokens: no merge across the border comes
        before the merges that build the sides."""
        if (hit := self.memo.get((left, right))) is not None:
            return hit
        limit, a, b, out = 1 << 60, left, right, True
        while True:
            r = self.rank.get((a, b), 1 << 60)
            if r < limit:
                out = False
                break
            ra = self.rank[self.parts[a]] if a in self.parts else -1
            rb = self.rank[self.parts[b]] if b in self.parts else -1
            if ra < 0 and rb < 0:
                break
            # undo the later of the two border merges; a border merge of the same rank as the right side's
            # stands further left and would have been made before it
            if ra > rb:
                limit, a = ra, self.parts[a][1]
            else:
                limit, b = rb + 1, self.parts[b][0]
        self.memo[left, right] = out
        return out

    def step(self, state: int, byte: int) -> tuple[int, int]:
        """(next state, change of the token count), compiled when first asked for."""
        suffix, cuts = self.states[state]
        grown = suffix + bytes([byte])
        for at in range(len(grown)):
            token = grown[at:]
            if token in self.vocab:
                last, count = cuts[at]
                if last is not None and (not last or self.stands_beside(last, token)):
                    break
        else:
            raise ValueError(f"no token ends {grown!r}")
        here = count + 1
        drop = next(k for k in range(len(grown) + 1) if k == len(grown) or grown[k:] in self.opens)
        kept = [*cuts, (token, here)][drop:]
        reached = (grown[drop:], tuple((t, c - here) for t, c in kept))
        to = self.ids.setdefault(reached, len(self.states))
        if to == len(self.states):
            self.states.append(reached)
        out = self.next[state << 8 | byte] = (to, here - cuts[-1][1])
        return out

    def count_pretoken(self, piece: str) -> int:
        return self.walk(piece.encode("utf-8", "surrogatepass"))

    def walk(self, raw: bytes) -> int:
        if len(self.states) > self.keep_states:
            self.forget()
        state, total, known = 0, 0, self.next
        for byte in raw:
            state, change = known.get(state << 8 | byte) or self.step(state, byte)
            total += change
        return total

    def count(self, text: str) -> int:
        """Tokens of a text; special strings count one and part the text."""
        if self.cut is not None and any(s in text for s in self.special):
            found = self.cut.findall(text)
            return len(found) + sum(self.count_plain(p) for p in self.cut.split(text))
        return self.count_plain(text)

    def count_plain(self, text: str) -> int:
        known, total = self.whole, 0
        for piece in self.pretoken.findall(text):
            n = known.get(piece)
            if n is None:
                n = self.count_pretoken(piece)
                if len(known) < self.keep_paths and len(piece) < 64:
                    known[piece] = n
            total += n
        return total

    # chunk state maps ------------------------------------------------------------------------------

    def chunk_map(self, chunk: str) -> tuple[str, int | None, str]:
        """(open head, count of the closed middle, open tail); a chunk without a sure boundary: (chunk, None, "")."""
        first = FIRST_BOUNDARY.search(chunk)
        if first is None:
            return chunk, None, ""
        last = LAST_BOUNDARY.search(chunk)
        cut, end = first.end(), last.end()
        return chunk[:cut], self.count(chunk[cut:end]) if end > cut else 0, chunk[end:]

    def compose(self, a: tuple, b: tuple) -> tuple:
        if a[1] is None and b[1] is None:
            # the seam of two open pieces may itself be a boundary
            return self.chunk_map(a[0] + b[0])
        if a[1] is None:
            seam = self.chunk_map(a[0] + b[0])
            return (seam[0], b[1], b[2]) if seam[1] is None else (seam[0], seam[1] + self.count(seam[2]) + b[1], b[2])
        if b[1] is None:
            seam = self.chunk_map(a[2] + b[0])
            return (a[0], a[1], seam[0]) if seam[1] is None else (a[0], a[1] + self.count(seam[0]) + seam[1], seam[2])
        return a[0], a[1] + self.count(a[2] + b[0]) + b[1], b[2]

    def total(self, state_map: tuple) -> int:
        head, middle, tail = state_map
        return self.count(head) + (0 if middle is None else middle + self.count(tail))


FIRST_BOUNDARY = regex.compile(r"\S(?=\s)")
LAST_BOUNDARY = regex.compile(r"(?r)\S(?=\s)")


@lru_cache(2)
def transducer(path: str) -> Transducer:
    return Transducer(path)


def vocabulary_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def token_counts(docs: DataFrame, vocabulary: str, text_col: str = "text", chunk_chars: int = 1 << 16, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns, n_bytes and n_tokens (with an underscore where ``keep`` has such a name) for each row.

    Texts over ``chunk_chars`` code points are cut into chunks whose maps are counted one by one and composed
    by a scan in which halves are composed pairwise. Null texts count as empty (0, 0); repeated rows each have
    their row; an empty table gives no rows; ``vocabulary`` is a path that executors can open."""
    n_bytes, n_tokens, given = unused(list(keep), "n_bytes", "n_tokens", "text_")
    rows = docs.select(*keep, F.coalesce(F.octet_length(text_col).cast("long"), F.lit(0).cast("long")).alias(n_bytes), F.coalesce(text_col, F.lit("")).alias(given))
    schema = rows.drop(given).withColumn(n_tokens, F.lit(0).cast("long")).schema

    def counted(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        t = transducer(vocabulary)
        for b in batches:
            counts = [t.count(x) if len(x) <= chunk_chars else scan(t, x, chunk_chars) for x in b[given]]
            yield b.drop(columns=given).assign(**{n_tokens: counts})

    return rows.mapInPandas(counted, schema)


def scan(t: Transducer, text: str, chunk_chars: int) -> int:
    maps = [t.chunk_map(text[i : i + chunk_chars]) for i in range(0, len(text), chunk_chars)]
    while len(maps) > 1:
        maps = [t.compose(*maps[i : i + 2]) if i + 1 < len(maps) else maps[i] for i in range(0, len(maps), 2)]
    return t.total(maps[0])


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = token_counts(table(spark, sf_dir, "documents"), vocabulary_path())
    return out.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > 1024).alias("over_limit"))
