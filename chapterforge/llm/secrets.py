"""Secret scan: fixed patterns, then probabilistic automata inferred from the credentials these find.

Grammar inference: for each kind, a prefix tree of a bounded sample of credentials (over classes of characters) is
turned into a probabilistic automaton by merging states whose outgoing frequencies are compatible under a Hoeffding bound.
Candidates are all runs of 8 or more credential characters (without full stops and hyphens at their ends) that hold a letter and a digit
and overlap no base span; letters alone are words, digits alone numbers. One more automaton learns what is ordinary, from the candidates of
all texts. A candidate is a secret if a format's automaton gives it at least the mean log-probability per character that all but one in a
hundred of the sample's held-out fifth have, and more than the ordinary one gives it. ``planted_report`` measures recall by format.

Spans are in code points, end exclusive. Defined results: null and empty texts have none; a repeated row is scanned
again; kinds with fewer than 20 credentials have no automaton, and without any only the fixed patterns count; ties with the ordinary
automaton are no secrets; texts of any length are scanned whole; an empty table gives no rows; columns other than id and text are not
read by the scan, whatever their names, and are kept as they are by the mask.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_batches, frugal, rows_of, written

# fixed values: the base patterns, their kinds in order, and how long a match must be
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]{12,}")
HEX = re.compile(r"[0-9a-f]{32,}")
KINDS = ("assign", "access", "hex", "learned")
NAMES = ("passw", "secret", "token", "api")

CANDIDATE = re.compile(r"[A-Za-z0-9+/_=.-]{8,}")
MIXED = re.compile(r"(?=.*[0-9])(?=.*[A-Za-z])")
LEAST = 8


def candidates(text: str, spans: list) -> list[tuple[int, int]]:
    """(start, end) of the runs that overlap none of ``spans``, which are in order of their starts."""
    out, k, latest = [], 0, 0
    for m in CANDIDATE.finditer(text):
        a, b = m.span()
        while a < b and text[a] in ".-":
            a += 1
        while b > a and text[b - 1] in ".-":
            b -= 1
        if b - a < LEAST or not MIXED.match(text, a, b):
            continue
        while k < len(spans) and spans[k][0] < b:
            latest, k = max(latest, spans[k][2]), k + 1
        if latest <= a:
            out.append((a, b))
    return out


def base_spans(text: str) -> list[tuple[int, int, int, str]]:
    """(start, kind's place, end, credential) of the fixed patterns, in order."""
    low, found = text.lower(), []
    if any(n in low for n in NAMES):
        found += [(m.start(), 0, m.end(), m[2]) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    found += [(m.start(), 1, m.end(), m[0]) for m in ACCESS.finditer(text)]
    found += [(m.start(), 2, m.end(), m[0]) for m in HEX.finditer(text)]
    return sorted(found)


#: classes of characters: digits, letters that are hexadecimal digits or not, small or capital; marks stand for themselves
_CLASSES = str.maketrans({c: k for k, group in {"0": "123456789", "a": "bcdef", "z": "ghijklmnopqrstuvwxyz", "A": "BCDEF", "Z": "GHIJKLMNOPQRSTUVWXYZ"}.items() for c in group})


def symbols(text: str) -> str:
    return text.translate(_CLASSES)


class Automaton:
    """Probabilistic deterministic automaton, inferred by merging states of a prefix tree."""

    def __init__(self, samples: list[str], alpha: float = 0.05):
        self.moves: list[dict[str, int]] = [{}]
        self.count: list[Counter] = [Counter()]  # of each state: its moves' symbols, and None where a sample ends
        for s in samples:
            at = 0
            for c in s:
                self.count[at][c] += 1
                if c not in self.moves[at]:
                    self.moves[at][c] = len(self.moves)
                    self.moves.append({})
                    self.count.append(Counter())
                at = self.moves[at][c]
            self.count[at][None] += 1
        self._bound = math.sqrt(0.5 * math.log(2 / alpha))
        self._infer()
        self.kinds = len({c for x in self.count for c in x}) + 1

    def _alike(self, p: int, q: int) -> bool:
        stack = [(p, q)]
        while stack:
            p, q = stack.pop()
            n, m = sum(self.count[p].values()), sum(self.count[q].values())
            if not n or not m:
                continue
            room = self._bound * (1 / math.sqrt(n) + 1 / math.sqrt(m))
            for c in self.count[p].keys() | self.count[q].keys():
                if abs(self.count[p][c] / n - self.count[q][c] / m) > room:
                    return False
            stack += [(self.moves[p][c], self.moves[q][c]) for c in self.moves[p].keys() & self.moves[q].keys()]
        return True

    def _fold(self, p: int, q: int) -> None:
        """Add the tree below q to p."""
        stack = [(p, q)]
        while stack:
            p, q = stack.pop()
            self.count[p].update(self.count[q])
            for c, t in self.moves[q].items():
                if c in self.moves[p]:
                    stack.append((self.moves[p][c], t))
                else:
                    self.moves[p][c] = t

    def _infer(self) -> None:
        settled, edge = [0], [(0, c) for c in sorted(self.moves[0])]
        while edge:
            # the most frequent frontier state first: its frequencies are the surest
            edge.sort(key=lambda e: (sum(self.count[self.moves[e[0]][e[1]]].values()), e[1]))
            at, c = edge.pop()
            q = self.moves[at][c]
            for p in settled:
                if self._alike(p, q):
                    self.moves[at][c] = p
                    self._fold(p, q)
                    break
            else:
                settled.append(q)
            known = set(settled)
            edge = [(s, x) for s in settled for x, t in self.moves[s].items() if t not in known]
        self.states = settled

    def rate(self, s: str) -> float:
        """Mean natural log-probability for each symbol and the end; unseen symbols have a small one."""
        at, total = 0, 0.0
        for i, c in enumerate([*s, None]):
            held = self.count[at]
            n = sum(held.values())
            total += math.log((held[c] + 0.01) / (n + 0.01 * self.kinds))
            if c is None:
                break
            nxt = self.moves[at].get(c)
            if nxt is None:
                return (total + (len(s) - i) * math.log(0.001)) / (len(s) + 1)
            at = nxt
        return total / (len(s) + 1)


class SecretModel:
    def __init__(self, credentials: dict[str, list[str]], ordinary: list[str]):
        self.formats = []
        for kind in sorted(credentials):
            texts = [symbols(t) for t in credentials[kind]]
            if len(texts) >= 20:
                machine = Automaton([t for i, t in enumerate(texts) if i % 5])
                rates = sorted(machine.rate(t) for i, t in enumerate(texts) if i % 5 == 0)
                self.formats.append((machine, rates[len(rates) // 100]))
        self.ordinary = Automaton([symbols(t) for t in ordinary]) if ordinary else None
        self.memo: dict[str, bool] = {}

    def secret(self, text: str) -> bool:
        s = symbols(text)
        known = self.memo.get(s)
        if known is None:
            if len(self.memo) > 50_000:
                self.memo.clear()
            known = self._judge(s)
            if len(s) <= 256:
                self.memo[s] = known
        return known

    def _judge(self, s: str) -> bool:
        found = [r for m, least in self.formats if (r := m.rate(s)) >= least]
        return bool(found) and (self.ordinary is None or max(found) > self.ordinary.rate(s))

    def spans(self, text: str) -> tuple[list, list]:
        """Base spans, and all spans, as (start, kind's place, end)."""
        base = [x[:3] for x in base_spans(text)]
        if not self.formats:
            return base, base
        return base, sorted(base + [(a, 3, b) for a, b in candidates(text, base) if self.secret(text[a:b])])


def said(spans: list) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def learn_formats(rows: DataFrame, per_kind: int = 500) -> SecretModel:
    """From ``per_kind`` distinct credentials of each kind, and twice as many ordinary candidates: the first by a hash.

    All texts are read; a batch's distinct findings alone move. Ordinary candidates are told apart by their classes of characters.
    """

    def harvest(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            found: set = set()
            for text in pdf["text"]:
                base = base_spans(text)
                found.update((KINDS[k], c) for _, k, _, c in base)
                found.update(("ordinary", symbols(text[a:b])) for a, b in candidates(text, base) if b - a <= 256)
            yield pd.DataFrame(sorted(found), columns=["kind", "text"])

    found = written(rows.select("text").mapInPandas(frugal(harvest), "kind string, text string").distinct(), "credentials")
    first = lambda kind, n: [r["text"] for r in found.filter(F.col("kind") == kind).orderBy(F.xxhash64("text"), "text").limit(n).collect()]
    return SecretModel({k: first(k, per_kind) for k in KINDS[:3]}, first("ordinary", 2 * per_kind))


def scan_secrets(docs: DataFrame, per_kind: int = 500, text_column: str = "text") -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_learned of each row."""
    arrow_batches(docs.sparkSession)
    rows = rows_of(docs, text_column=text_column)
    held = docs.sparkSession.sparkContext.broadcast(learn_formats(rows, per_kind))

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            out = []
            for doc_id, text in zip(pdf["doc_id"].astype("Int64"), pdf["text"]):
                base, spans = held.value.spans(text)
                n = Counter(k for _, k, _ in spans)
                out.append((doc_id, n[0], n[1], n[2], hashlib.sha256(said(base).encode()).hexdigest(), said(spans), n[3]))
            done = pd.DataFrame(out, columns=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_learned"])
            done["doc_id"] = done["doc_id"].astype("Int64")
            yield done

    return rows.mapInPandas(frugal(scan), "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_learned long")


def masked(text: str, spans: list, mark: str = "[SECRET]") -> str:
    """``text`` with each stretch that spans cover replaced."""
    out, at = [], 0
    for a, _, b in spans:
        if a >= at:
            out += [text[at:a], mark]
        at = max(at, b)
    return "".join([*out, text[at:]])


def mask_secrets(docs: DataFrame, per_kind: int = 500, mark: str = "[SECRET]") -> DataFrame:
    """``docs``, secrets in ``text`` replaced by a mark and ``n_chars`` (if it is there) counted anew; null texts stay null."""
    arrow_batches(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(learn_formats(rows_of(docs), per_kind))

    def mask(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            yield pd.Series([None if t is None else masked(t, held.value.spans(t)[1], mark) for t in texts], dtype=object)

    out = docs.withColumn("text", F.pandas_udf(frugal(mask), "string", F.PandasUDFType.SCALAR_ITER)("text"))
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def planted_report(docs: DataFrame, formats: dict[str, list[str]], per_kind: int = 500) -> list[tuple[str, int, int]]:
    """For each format, (name, credentials, found) of bare credentials, each put between two words of its own text, by what ``docs`` teaches."""
    model = learn_formats(rows_of(docs), per_kind)
    lead = "the value is "
    return [(name, len(texts), sum((len(lead), 3, len(lead) + len(t)) in model.spans(f"{lead}{t} here")[1] for t in texts)) for name, texts in formats.items()]
