"""Documents that are hard on operators, and plain versions of what operators compute."""

from __future__ import annotations

import hashlib
from collections import Counter, defaultdict

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, TEXT string, extra int"
SMALL = "/root/testdata/sf0.001"


def prose(seed: int, n: int) -> str:
    x, out = seed * 7919 + 13, []
    for _ in range(n):
        x = (x * 1103515245 + 12345) % (1 << 31)
        out.append("".join(chr(97 + (x >> s) % 26) for s in (3, 8, 13, 18, 23)[: 2 + x % 4]))
    return " ".join(out)


def hostile_rows() -> list[tuple]:
    base = prose(1, 120)
    texts = [
        (0, base), (1, base), (2, base + " and one more word"), (3, base.upper()), (4, None), (5, ""), (6, " \n\t "), (7, "one two"), (8, "One  two"),
        (9, prose(2, 60) + "\n" + prose(3, 40)), (10, prose(4, 50) + prose(3, 40)), (11, "Crème brûlée ▁ “naïve” 日本語 😀 <|endoftext|> x"), (12, "w" * 5000), (13, prose(5, 20000)),
        (14, "ééé" * 60 + prose(6, 30)), (15, "ééé" * 60 + prose(7, 30)), (16, "ab " * 300), (None, base), (None, None), (18, prose(8, 12)), (18, prose(8, 12)), (19, prose(9, 12)), (20, "  a\u0085b"),
    ]
    return [(i, t, "en", None if k % 5 == 0 else f"s{k % 3}", len(t or ""), "clash", k) for k, (i, t) in enumerate(texts)]


def hostile(spark):
    return spark.createDataFrame(hostile_rows(), SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def small_documents(spark):
    return spark.read.parquet(f"{SMALL}/documents.parquet")


def near_components(texts: dict[int, str | None]) -> dict[int, tuple[int, int]]:
    """By id: (set size, component)."""

    def shingles(t):
        w = (t or "").encode().lower().split()
        return set(zip(*(w[i:] for i in range(5)))) if len(w) >= 5 else {tuple(w)} if w else set()

    sets = {i: shingles(t) for i, t in texts.items()}
    up = {i: i for i in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    holders = defaultdict(list)
    for i in sorted(sets):
        common = Counter(j for g in sets[i] for j in holders[g])
        for j, n in common.items():
            if 100 * n >= 75 * (len(sets[i]) + len(sets[j]) - n):
                a, b = sorted((root(i), root(j)))
                up[b] = a
        for g in sets[i]:
            holders[g].append(i)
    return {i: (len(sets[i]), root(i)) for i in sets}


def repeated_bytes(rows: list[tuple[int, str | None]], length: int = 100) -> dict[int, tuple[int, int, int, str]]:
    """By id, for rows in order of ids: bytes, removed, spans, digest of what stays."""
    seen, out = set(), {}
    for i, t in rows:
        data = (t or "").encode()
        gone = bytearray(len(data))
        for p in range(len(data) - length + 1):
            w = data[p : p + length]
            if w in seen:
                gone[p : p + length] = b"\1" * length
            else:
                seen.add(w)
        kept = bytes(c for c, g in zip(data, gone) if not g)
        out[i] = (len(data), sum(gone), sum(g and not (k and gone[k - 1]) for k, g in enumerate(gone)), hashlib.sha256(kept).hexdigest())
    return out
