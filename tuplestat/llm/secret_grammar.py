"""Secret scan: fixed patterns, and probabilistic automata inferred from labelled credentials.

Grammar inference: labelled credentials of one format go into a prefix tree whose states count
visits, ends and exits by character class. States whose ending and exit frequencies cannot be
told apart (a Hoeffding bound at level `alpha`, applied down the subtrees) are merged, which
closes loops and generalises; what is left is a deterministic probabilistic automaton. A
candidate string is scored by its log-likelihood per character under the best automaton against
a background model of ordinary words, numbers and identifiers.

Labelled credentials come from `labelled_credentials` (publicly documented formats filled by a
seeded generator) and may be replaced by the caller's own. The fit is tiny and runs on the
driver; its result is a table of transitions of a few kilobytes.

Candidates are all runs of 12 or more of the characters that credentials are made of, letters alone
too, without the marks at their ends; where a pattern's span covers part of a run, what is left on
either side is a candidate. The likelihood alone decides.

Spans are half-open ranges of code points. The patterns' spans always stay; the automata add
spans (kind `grammar`) of candidates that score high enough. Nulls are empty texts
without spans; repeated rows each give a row; an empty table gives an empty result. Only the
id and text columns are read.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
import string
from collections import defaultdict, deque
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import batch_of, bounded_batches, id_text, slices, thrifty

# The contract's patterns. ASCII letters only, in either case where it says so.
ASSIGN = re.compile(
    r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A
)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")  # a maximal run, as the greedy pattern with a length test finds it
KINDS = ("assign", "access", "hex", "grammar")
ASSIGN_VALUE, ACCESS_LENGTH = 8, 16

LEAST_LENGTH = 12
CANDIDATE = re.compile(r"[A-Za-z0-9+/_.=-]{%d,}" % LEAST_LENGTH)
MARKS = ".=-/"


# ------------------------------------------------------------------ automata


def symbol(c: str) -> str:
    """Character class: digits, letters a-f and g-z in either case, each mark by itself."""
    if "0" <= c <= "9":
        return "9"
    if "a" <= c <= "z":
        return "f" if c <= "f" else "z"
    if "A" <= c <= "Z":
        return "F" if c <= "F" else "Z"
    return c


CLASS_OF = {ord(c): symbol(c) for c in string.ascii_letters + string.digits}
SEEN_CLASSES = 50_000  # sequences of at most 64 classes: some megabytes
SIZE = {"9": 10, "f": 6, "z": 20, "F": 6, "Z": 20}


class Automaton:
    """Counts on states and moves; merged in place while it is being inferred."""

    def __init__(self):
        self.visits, self.ends = [0], [0]
        self.moves: list[dict[str, list[int]]] = [{}]  # symbol -> [target, count]

    def add(self, word: str) -> None:
        state = 0
        self.visits[0] += 1
        for c in word:
            move = self.moves[state].get(c)
            if move is None:
                move = self.moves[state][c] = [len(self.visits), 0]
                self.visits.append(0)
                self.ends.append(0)
                self.moves.append({})
            move[1] += 1
            state = move[0]
            self.visits[state] += 1
        self.ends[state] += 1

    def alike(self, a: int, b: int, alpha: float) -> bool:
        """No tested frequency of the two subtrees differs by more than the Hoeffding bound."""
        todo = [(a, b)]
        wide = math.sqrt(0.5 * math.log(2 / alpha))
        while todo:
            p, q = todo.pop()
            n, m = self.visits[p], self.visits[q]
            if not n or not m:
                continue
            bound = wide * (1 / math.sqrt(n) + 1 / math.sqrt(m))
            if abs(self.ends[p] / n - self.ends[q] / m) > bound:
                return False
            for c in self.moves[p].keys() | self.moves[q].keys():
                x, y = self.moves[p].get(c), self.moves[q].get(c)
                if abs((x[1] if x else 0) / n - (y[1] if y else 0) / m) > bound:
                    return False
                if x and y:
                    todo.append((x[0], y[0]))
        return True

    def fold(self, source: tuple[int, str], blue: int, red: int) -> None:
        """Lead the only move into `blue` to `red` and add blue's subtree onto red's."""
        self.moves[source[0]][source[1]][0] = red
        todo = [(red, blue)]
        while todo:
            r, b = todo.pop()
            self.visits[r] += self.visits[b]
            self.ends[r] += self.ends[b]
            for c, (target, count) in self.moves[b].items():
                if c in self.moves[r]:
                    self.moves[r][c][1] += count
                    todo.append((self.moves[r][c][0], target))
                else:
                    self.moves[r][c] = [target, count]


def infer(words: list[str], alpha: float = 1e-3) -> Automaton:
    """Prefix tree of `words` (already symbols) with compatible states merged, red-blue order."""
    tree = Automaton()
    for w in words:
        tree.add(w)
    red = [0]
    blue = deque((0, c) for c in sorted(tree.moves[0]))
    while blue:
        state, c = blue.popleft()
        target = tree.moves[state][c][0]
        if target in red:
            continue
        home = next((r for r in red if tree.alike(r, target, alpha)), None)
        if home is None:
            red.append(target)
            blue.extend((target, x) for x in sorted(tree.moves[target]))
        else:
            tree.fold((state, c), target, home)
            blue.extend((home, x) for x in sorted(tree.moves[home]) if tree.moves[home][x][0] not in red)
    return tree


@dataclass
class Scorer:
    """Log2 probabilities: per state, moves by symbol and ending; unseen moves share a floor."""

    table: list[dict[str, tuple[int, float]]]
    ends: list[float]
    floor: float = -9.0

    @classmethod
    def of(cls, a: Automaton) -> "Scorer":
        table, ends = [], []
        for s in range(len(a.visits)):
            n = a.visits[s] + 1
            table.append({c: (t, math.log2(k / n) - math.log2(SIZE.get(c, 1))) for c, (t, k) in a.moves[s].items()})
            ends.append(math.log2((a.ends[s] + 0.01) / n))
        return cls(table, ends)

    def score(self, text: str) -> float:
        state, total = 0, 0.0
        for c in text:
            move = self.table[state].get(symbol(c))
            if move is None:  # a symbol that this state never saw: pay, and stay
                total += self.floor
                continue
            state, gain = move
            total += gain
        return total + self.ends[state]


def labelled_credentials(seed: int = 11, each: int = 400) -> dict[str, list[str]]:
    """Credentials of public formats, by format, from a seeded generator."""
    rng = random.Random(seed)
    pick = lambda chars, n: "".join(rng.choice(chars) for _ in range(n))
    upper, lower, digits = string.ascii_uppercase, string.ascii_lowercase, string.digits
    alnum, hexes = upper + lower + digits, "0123456789abcdef"
    url64 = alnum + "-_"
    return {
        "access": ["AKIA" + pick(upper + "234567", 16) for _ in range(each)],
        "hex": [pick(hexes, rng.choice((18, 24, 32, 40, 64))) for _ in range(each)],
        "prefixed": [rng.choice(("ghp_", "gho_", "ghs_")) + pick(alnum, 36) for _ in range(each)],
        "live": [rng.choice(("sk_live_", "pk_live_", "rk_live_")) + pick(alnum, 24) for _ in range(each)],
        "chat": [f"xoxb-{pick(digits, 12)}-{pick(digits, 12)}-{pick(alnum, 24)}" for _ in range(each)],
        "map": ["AIza" + pick(url64, 35) for _ in range(each)],
        "signed": [f"eyJ{pick(url64, 33)}.eyJ{pick(url64, 60)}.{pick(url64, 43)}" for _ in range(each)],
        "random": [pick(alnum + "+/", rng.choice((32, 40, 43, 44))) for _ in range(each)],
    }


def ordinary_strings(seed: int = 12, each: int = 3000) -> list[str]:
    """The background: words and compounds, numbers, dotted and dashed names, capitals, versions."""
    rng = random.Random(seed)
    syllables = [a + b for a in "bcdfghjklmnprstvwz" for b in ("a", "e", "i", "o", "u", "an", "er", "in", "ou", "st")]
    word = lambda k: "".join(rng.choice(syllables) for _ in range(k))
    out = []
    for _ in range(each):
        w = [word(rng.randint(2, 5)) for _ in range(4)]
        out += [
            word(rng.randint(6, 10)),
            "-".join(w),
            "_".join(w),
            ".".join(w[:3]) + ".com",
            "/".join(w),
            word(8).upper(),
            word(8).capitalize() + word(3).capitalize(),
            str(rng.randrange(10**15, 10**19)),
            f"{rng.randrange(1990, 2030)}-{rng.randrange(1, 13):02}-{rng.randrange(1, 29):02}T{rng.randrange(24):02}",
            w[0] + str(rng.randrange(10000)),
            f"{rng.randrange(1990, 2030)}-{rng.randrange(1, 13):02}-{rng.randrange(1, 29):02}T{rng.randrange(24):02}{rng.randrange(60):02}00.{rng.randrange(1000):03}Z",
            f"/{w[0]}/{w[1]}{rng.randrange(1, 9)}.{rng.randrange(20)}/{w[2]}-{w[3]}",
            f"{w[0]}{rng.randrange(9)}.{rng.randrange(30)}.{rng.randrange(9)}-{w[1]}.{rng.randrange(20000000, 20300000)}",
            f"{word(2).upper()}{rng.randrange(10)}{word(4).upper()}{rng.randrange(10)}{word(2).upper()}",
        ]
    return out


class Bigrams:
    """Background model: character-class bigrams with add-one counts, spread within classes."""

    def __init__(self, strings: list[str]):
        count: dict[str, dict[str, int]] = defaultdict(lambda: defaultdict(int))
        for s in strings:
            last = "^"
            for c in s:
                x = symbol(c)
                count[last][x] += 1
                last = x
        self.table = {
            a: {b: math.log2((k + 1) / (sum(m.values()) + 11)) - math.log2(SIZE.get(b, 1)) for b, k in m.items()}
            for a, m in count.items()
        }
        self.least = {a: math.log2(1 / (sum(m.values()) + 11)) for a, m in count.items()}

    def score(self, text: str) -> float:
        total, last = 0.0, "^"
        for c in text:
            x = symbol(c)
            row = self.table.get(last, {})
            total += row[x] if x in row else self.least.get(last, -8.0) - math.log2(SIZE.get(x, 1))
            last = x
        return total


class SecretModel:
    """Automata by format and the background; `gain` is bits per character over the background."""

    def __init__(self, labelled: dict[str, list[str]], ordinary: list[str], alpha: float = 1e-3):
        self.formats = {
            name: Scorer.of(infer(["".join(map(symbol, w)) for w in words], alpha)) for name, words in labelled.items()
        }
        self.background = Bigrams(ordinary)
        self.seen: dict[str, float] = {}

    def gain(self, text: str) -> float:
        """Scores depend on character classes only, so each sequence of classes is scored once (while
        it stays in a table of bounded size)."""
        classes = text.translate(CLASS_OF)
        found = self.seen.get(classes)
        if found is None:
            best = max(s.score(text) for s in self.formats.values())
            found = (best - self.background.score(text)) / max(len(text), 1)
            if len(text) <= 64:
                if len(self.seen) >= SEEN_CLASSES:
                    self.seen.clear()
                self.seen[classes] = found
        return found


def fit_model(labelled: dict[str, list[str]] | None = None) -> SecretModel:
    return SecretModel(labelled or labelled_credentials(), ordinary_strings())


# ------------------------------------------------------------------ spans


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the patterns' matches; kind is a place in KINDS."""
    found = []
    if ":" in text or "=" in text:
        for m in ASSIGN.finditer(text):
            if m.end(2) - m.start(2) >= ASSIGN_VALUE:
                found.append((m.start(), 0, m.end()))
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LENGTH]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


DIGIT = re.compile("[0-9]")
LETTER = re.compile("[A-Za-z]")


def grammar_spans(text: str, base: list[tuple[int, int, int]], model: SecretModel, least: float):
    """Candidates (see the module's docstring) that score at least `least` bits a character."""
    out, at = [], 0
    for m in CANDIDATE.finditer(text):
        lo, hi = m.span()
        while at < len(base) and base[at][2] <= lo:
            at += 1
        for x, _, y in base[at:]:  # pieces of the run before each span that reaches into it
            if x >= hi:
                break
            if y > lo:
                judge(text, lo, x, model, least, out)
                lo = max(lo, y)
        judge(text, lo, hi, model, least, out)
    return out


def judge(text: str, lo: int, hi: int, model: SecretModel, least: float, out: list) -> None:
    """Add text[lo:hi] without marks at its ends to `out` if it is long and likely enough."""
    if hi - lo < LEAST_LENGTH:
        return
    core = text[lo:hi].lstrip(MARKS)
    lo, core = hi - len(core), core.rstrip(MARKS)
    if len(core) >= LEAST_LENGTH and model.gain(core) >= least:
        out.append((lo, 3, lo + len(core)))


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def secret_scan(
    docs: DataFrame, model: SecretModel | None = None, least: float = 0.6, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, n_grammar, base_sha256, spans of every row of `docs`."""
    model = model or fit_model()
    schema = pa.schema(
        [("doc_id", pa.int64())]
        + [(f"n_{k}", pa.int64()) for k in KINDS]
        + [("base_sha256", pa.string()), ("spans", pa.string())]
    )

    def run(batches):
        for part in slices(batches):
            rows = []
            for t in part.column(1).to_pylist():
                t = t or ""
                base = base_spans(t)
                every = sorted(base + grammar_spans(t, base, model, least))
                n = [sum(k == x for _, x, _ in every) for k in range(4)]
                rows.append((*n, hashlib.sha256(joined(base).encode()).hexdigest(), joined(every)))
            yield batch_of(schema, part.column(0), *zip(*rows))

    kinds = ", ".join(f"n_{k} long" for k in KINDS)
    return id_text(docs, id_col, text_col).mapInArrow(run, f"doc_id long, {kinds}, base_sha256 string, spans string")


def redacted(text: str, spans: list[tuple[int, int, int]], mark: str) -> str:
    out, at = [], 0
    for a, _, b in spans:
        if a >= at:
            out += [text[at:a], mark]
        at = max(at, b)
    return "".join(out) + text[at:]


def redact(text: Column, model: SecretModel | None = None, least: float = 0.6, mark: str = "[secret]") -> Column:
    """`text` with every span replaced by `mark`; overlapping spans become one mark; null stays null."""
    model = model or fit_model()
    bounded_batches(SparkSession.getActiveSession())

    @F.arrow_udf("string")
    def hide(column: pa.Array) -> pa.Array:
        def one(t):
            if t is None:
                return None
            base = base_spans(t)
            spans = sorted(base + grammar_spans(t, base, model, least))
            return redacted(t, spans, mark) if spans else t

        thrifty()
        return pa.array(map(one, column.to_pylist()), pa.string())

    return hide(text)
