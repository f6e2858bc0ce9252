"""Secret scans: candidates by pattern, false positives removed by a random forest.

Candidates are whole-text matches: long runs of key characters with a digit, values set to a name like token or
password, and private-key blocks. Each is described by its length, how its characters follow one another,
how much of it dictionary words cover, its path and the words near it. The forest is trained on labelled
findings: the caller's own, or ``example_findings``, made by rule from public secret formats and from
usual look-alikes (placeholders, digests named as such, identifiers, numbers).

Training takes at most ``MOST_FINDINGS`` labelled findings. Every document is scanned whole.

Defined cases: a null or empty text has no finding; overlapping candidates are one; repeated rows are scanned each; a null path is
an empty one; an empty table gives an empty result; extra columns are carried by ``redact`` and ignored by ``scan``.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkfold.llm.common import tidy

MOST_FINDINGS = 6_000
REDACTED = "[SECRET]"
_NAMED = re.compile(r"(?i)(?:api[_-]?key|access[_-]?key|auth|bearer|credential|passw(?:or)?d|pwd|secret|token)\w{0,20}[\"']?\s{0,3}(?::=|=>|[:=])\s{0,3}[\"']?([^\s\"',;<>]{6,})")
_RUN = re.compile(r"[A-Za-z0-9+/_=\-]{16,}")
_BLOCK = re.compile(r"-----BEGIN [A-Z ]*PRIVATE KEY-----[\s\S]*?(?:-----END [A-Z ]*PRIVATE KEY-----|\Z)")
#: Prefixes of public key formats.
PREFIXES = ("AKIA", "ASIA", "ghp_", "gho_", "ghs_", "github_pat_", "glpat-", "xoxb-", "xoxp-", "sk_live_", "rk_live_", "AIza", "eyJ", "npm_", "pypi-", "SG.", "-----BEGIN")
#: Words that secrets do not hold, and words near a finding that speak for or against it.
DICTIONARY = tuple("about after all and any application are back been before build can change class client code config content could count data date default description document each example file first from function group have header how id image index into item just key length like line link list main make message method module more most name new not null number object one only option other our output page parameter password path placeholder please product project public read request response result return sample secret section see server service set should show some source start state string style system table test text that the their them then there these they this time title token type under update url use user value version very want was way web what when where which will with word work would write your".split())
SPEAKS_FOR = ("api", "key", "token", "secret", "password", "passwd", "pwd", "auth", "bearer", "credential", "private", "access", "login")
SPEAKS_AGAINST = ("example", "sample", "test", "dummy", "placeholder", "fake", "sha1", "sha256", "md5", "checksum", "hash", "digest", "commit", "revision", "uuid", "guid", "etag", "integrity", "fixture", "mock", "docs")
_WORDS = re.compile("|".join(sorted((w for w in DICTIONARY if len(w) > 2), key=len, reverse=True)))
_NEAR = re.compile(r"[a-z0-9]+")
FEATURES = ("length", "digits", "upper", "lower", "symbols", "turns", "entropy", "doubled", "hex", "vowels", "cover", "prefixed", "for_before", "against_before", "against_inside", "against_path", "named", "quoted", "distinct", "longest_letters")


@dataclass
class Candidate:
    start: int
    end: int
    kind: str


def candidates(text: str) -> list[Candidate]:
    """Candidates in order; overlapping ones are merged, the first kind stays."""
    found = [Candidate(m.start(), m.end(), "block") for m in _BLOCK.finditer(text)] if "-----BEGIN" in text else []
    found += [Candidate(m.start(1), m.end(1), "named") for m in _NAMED.finditer(text)]
    found += [Candidate(m.start(), m.end(), "run") for m in _RUN.finditer(text) if any(map(str.isdigit, m[0]))]
    rank = {"block": 0, "named": 1, "run": 2}
    found.sort(key=lambda c: (c.start, rank[c.kind], -c.end))
    out: list[Candidate] = []
    for c in found:
        if out and c.start < out[-1].end:
            out[-1].end = max(out[-1].end, c.end)
        else:
            out.append(c)
    return out


def _kind(c: str) -> int:
    return 0 if c.isdigit() else 1 if c.isupper() else 2 if c.islower() else 3


def _near(text: str) -> list[str]:
    """The words of a stretch of text, cut at underscores too; addresses and host names are none."""
    return [x for w in text.lower().split() if "@" not in w and "://" not in w and "." not in w[:-1] for x in _NEAR.findall(w)]


def describe(text: str, c: Candidate, path: str | None = None) -> list[float]:
    """The features named in FEATURES."""
    value = text[c.start : c.end]
    n, low = len(value), value.lower()
    kinds = [_kind(x) for x in value]
    share = lambda k: kinds.count(k) / n
    counts: dict[str, int] = {}
    for x in value:
        counts[x] = counts.get(x, 0) + 1
    entropy = -sum(v / n * math.log2(v / n) for v in counts.values())
    turns = sum(a != b for a, b in zip(kinds, kinds[1:], strict=False)) / max(n - 1, 1)
    doubled = sum(a == b for a, b in zip(value, value[1:], strict=False)) / max(n - 1, 1)
    letters = max((len(x) for x in re.findall(r"[a-z]+", low)), default=0)
    before, after = _near(text[max(0, c.start - 80) : c.start])[-5:], _near(text[c.end : c.end + 40])[:3]
    has = lambda words, marks: float(sum(w in marks for w in words))
    holds = lambda whole, marks: float(sum(m in whole for m in marks))
    quotes = float(text[max(0, c.start - 1) : c.start] in ("'", '"'))
    return [
        math.log2(n), share(0), share(1), share(2), share(3), turns, entropy, doubled, sum(x in "0123456789abcdef" for x in low) / n, sum(x in "aeiou" for x in low) / n,
        sum(len(m) for m in _WORDS.findall(low)) / n, float(value.startswith(PREFIXES)), has(before[-3:], SPEAKS_FOR), has(before, SPEAKS_AGAINST) + has(after, SPEAKS_AGAINST), holds(low, SPEAKS_AGAINST),
        holds((path or "").lower(), SPEAKS_AGAINST), float(c.kind != "run"), quotes, len(counts) / min(n, 64), float(letters),
    ]


class Forest:
    """A random forest on numeric features: bootstrap rows, random features at each split, Gini gain over quantile cuts."""

    def __init__(self, x: np.ndarray, y: np.ndarray, trees: int = 40, depth: int = 9, seed: int = 5) -> None:
        draw = np.random.default_rng(seed)
        self.trees = []
        self.share = float(y.mean()) if len(y) else 0.0
        if not len(y) or self.share in (0.0, 1.0):
            return
        cuts = [np.unique(np.quantile(x[:, j], np.linspace(0.02, 0.98, 33))) for j in range(x.shape[1])]
        for _ in range(trees):
            rows = draw.integers(0, len(y), len(y))
            nodes: list[list] = []
            self._grow(x[rows], y[rows].astype(float), cuts, draw, depth, nodes)
            self.trees.append(np.array(nodes, float))

    def _grow(self, x, y, cuts, draw, depth, nodes) -> int:
        me = len(nodes)
        nodes.append([-1, 0.0, 0, 0, y.mean()])
        if depth == 0 or len(y) < 8 or y.min() == y.max():
            return me
        best = (1e-9, None, None)
        here = y.mean() * (1 - y.mean()) * len(y)
        for j in draw.choice(x.shape[1], max(1, int(x.shape[1] ** 0.5) + 1), replace=False):
            if not len(cuts[j]):
                continue
            under = x[:, j][:, None] <= cuts[j][None, :]
            n, s = under.sum(0), under.T @ y
            m, t = len(y) - n, y.sum() - s
            ok = (n > 1) & (m > 1)
            if ok.any():
                gain = np.where(ok, here - s * (1 - s / np.maximum(n, 1)) - t * (1 - t / np.maximum(m, 1)), -1)
                k = int(gain.argmax())
                if gain[k] > best[0]:
                    best = (gain[k], j, cuts[j][k])
        if best[1] is None:
            return me
        under = x[:, best[1]] <= best[2]
        left = self._grow(x[under], y[under], cuts, draw, depth - 1, nodes)
        right = self._grow(x[~under], y[~under], cuts, draw, depth - 1, nodes)
        nodes[me][:4] = [best[1], best[2], left, right]
        return me

    def score(self, x: np.ndarray) -> np.ndarray:
        """The trees' mean share of secrets."""
        if not self.trees:
            return np.full(len(x), self.share)
        total = np.zeros(len(x))
        for nodes in self.trees:
            at = np.zeros(len(x), int)
            while True:
                feature = nodes[at, 0].astype(int)
                inner = feature >= 0
                if not inner.any():
                    break
                value = x[np.arange(len(x)), np.maximum(feature, 0)]
                at = np.where(inner, np.where(value <= nodes[at, 1], nodes[at, 2], nodes[at, 3]).astype(int), at)
            total += nodes[at, 4]
        return total / len(self.trees)


def example_findings(n: int = 4_000, seed: int = 11) -> list[tuple[str, int, int, str, int]]:
    """(text, start, end, path, label) of labelled findings, made by rule and the same each time."""
    draw = np.random.default_rng(seed)
    pick = lambda xs: xs[int(draw.integers(len(xs)))]
    chars = lambda alphabet, k: "".join(alphabet[i] for i in draw.integers(0, len(alphabet), k))
    lower, digits = "abcdefghijklmnopqrstuvwxyz", "0123456789"
    hexed, mixed = digits + "abcdef", lower + lower.upper() + digits
    syllables = ("an", "er", "the", "ou", "re", "tion", "en", "ble", "ing", "ed", "st", "ea", "on", "at", "or", "de", "que", "la", "sch", "ver")
    word = lambda: "".join(pick(syllables) for _ in range(int(draw.integers(1, 5))))
    prose = lambda k: " ".join(word() for _ in range(k))
    secrets = (
        lambda: chars(hexed, int(pick((32, 40, 64)))), lambda: "AKIA" + chars(lower.upper() + digits, 16), lambda: "ghp_" + chars(mixed, 36), lambda: "xoxb-" + chars(digits, 11) + "-" + chars(mixed, 24),
        lambda: "sk_live_" + chars(mixed, 24), lambda: "AIza" + chars(mixed + "-_", 35), lambda: chars(mixed + "+/", int(pick((40, 44, 64, 88)))), lambda: "eyJ" + chars(mixed, 60), lambda: chars(mixed + "!#%", int(draw.integers(10, 20))), lambda: chars(mixed, int(pick((20, 24, 32)))),
    )
    likes = (
        lambda: pick(("your", "my", "example", "sample")) + pick(("_", "-")) + pick(("token", "key", "secret")) + pick(("", "_here", "-123456789012")), lambda: "x" * int(draw.integers(8, 40)), lambda: "0" * int(draw.integers(8, 40)),
        lambda: word() + "_" + word() + "_" + word() + "_" + chars(digits, 3), lambda: chars(digits, int(pick((16, 17, 20)))), lambda: word().title() + word().title() + word().title() + chars(digits, 2), lambda: "/".join(word() for _ in range(4)) + "/" + chars(digits, 4), lambda: "-".join(word() for _ in range(4)) + "-" + chars(digits, 4), lambda: "123456789012345678901234567890"[: int(draw.integers(16, 30))], lambda: word() + "!!" + word(), word,
    )
    digest = lambda: chars(hexed, int(pick((32, 40, 64))))
    uuid = lambda: "-".join(chars(hexed, k) for k in (8, 4, 4, 4, 12))
    out = []
    for i in range(n):
        path, quote = pick(("", "src/main.py", "config/app.yml", "web/page", "notes.txt")), pick(('"', "'", ""))
        name = pick(("token", "api_key", "secret", "password", "access_key", "auth_token", "client_secret"))
        case, joined = i % 8, pick((" = ", "=", ": "))
        if case < 3:
            head, value, label = f"{name}{joined}{quote}", pick(secrets)(), 1
        elif case == 3:
            value, label, quote = pick(secrets[1:6])(), 1, ""
            head = pick(("", "set ", "use "))
        elif case == 4:
            head, value, label, quote = pick(("commit ", "sha256:", "md5 checksum ", "revision ", "uuid ", "integrity digest ", "etag: ")), pick((digest, uuid))(), 0, ""
        elif case == 5:
            head, value, label = f"{name}{joined}{quote}", pick(likes)(), 0
        elif case == 6:
            head, value, label, quote = "", pick(likes)(), 0, pick(("", ",", "."))
        else:
            path, head, value, label = pick(("docs/example.md", "tests/fixture.json", "sample/mock.txt")), f"example {name}{joined}{quote}", pick((*likes, digest))(), 0
        before = prose(int(draw.integers(0, 12)))
        if draw.random() < 0.2:
            before += f" {word()}.{chars(digits, 2)}@mail{chars(digits, 1)}.example.com {pick(('', word()))}".rstrip()
        text = f"{before} {head}{value}{quote} {prose(int(draw.integers(0, 8)))}"
        start = len(before) + 1 + len(head)
        out.append((text, start, start + len(value), path, label))
    return out


def train(findings: list[tuple[str, int, int, str, int]] | None = None, most: int = MOST_FINDINGS) -> Forest:
    """A forest from labelled findings, at most ``most`` of them."""
    rows = (findings if findings is not None else example_findings())[:most]
    x, y = [], []
    for text, start, end, path, label in rows:
        own = next((c for c in candidates(text) if c.start <= start < c.end), Candidate(start, end, "run"))
        x.append(describe(text, own, path))
        y.append(label)
    return Forest(np.array(x).reshape(len(y), len(FEATURES)), np.array(y))


def _findings(texts: list[str | None], paths: list[str | None], forest: Forest) -> list[list[tuple]]:
    found = [candidates(t) if t else [] for t in texts]
    rows = [describe(t, c, p) for t, p, cs in zip(texts, paths, found, strict=True) for c in cs]
    scores = iter(forest.score(np.array(rows)).tolist() if rows else [])
    return [[(c.start, c.end, c.kind, next(scores)) for c in cs] for cs in found]


_FOUND = "array<struct<start:int,end:int,kind:string,score:double,secret:boolean>>"
_FOUND_ARROW = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("kind", pa.string()), ("score", pa.float64()), ("secret", pa.bool_())]))


def scan(docs: DataFrame, path: str = "source", forest: Forest | None = None, threshold: float = 0.5) -> DataFrame:
    """doc_id, n_candidates, n_secrets, findings of every row."""
    model = forest or train()

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                found = _findings(part.column(1).to_pylist(), part.column(2).to_pylist(), model)
                rows = [[{"start": s, "end": e, "kind": k, "score": round(p, 9), "secret": p >= threshold} for s, e, k, p in x] for x in found]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(x) for x in rows], pa.int64()), pa.array([sum(y["secret"] for y in x) for x in rows], pa.int64()), pa.array(rows, _FOUND_ARROW)], ["doc_id", "n_candidates", "n_secrets", "findings"])

    where = F.col(path).cast("string") if path in docs.columns else F.lit(None).cast("string")
    return docs.select("doc_id", "text", where.alias("_path")).mapInArrow(tidy(run), f"doc_id long, n_candidates long, n_secrets long, findings {_FOUND}")


def redact(docs: DataFrame, path: str = "source", forest: Forest | None = None, threshold: float = 0.5, mark: str = REDACTED) -> DataFrame:
    """``docs`` with each secret replaced by ``mark``; n_chars, where there is one, follows the text."""
    model, has_path = forest or train(), path in docs.columns

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                i = part.schema.get_field_index("text")
                texts = part.column(i).to_pylist()
                paths = [None if p is None else str(p) for p in part.column(part.schema.get_field_index(path)).to_pylist()] if has_path else [None] * len(texts)
                changed = {}
                for k, found in enumerate(_findings(texts, paths, model)):
                    for s, e, _, p in reversed(found):
                        if p >= threshold:
                            changed[k] = changed.get(k, texts[k])[:s] + mark + changed.get(k, texts[k])[e:]
                if changed:
                    columns = part.columns
                    columns[i] = pa.array([changed.get(k, t) for k, t in enumerate(texts)], part.schema.field(i).type)
                    if (j := part.schema.get_field_index("n_chars")) >= 0:
                        n = part.column(j).to_pylist()
                        columns[j] = pa.array([len(changed[k]) if k in changed else x for k, x in enumerate(n)], part.schema.field(j).type)
                    part = pa.RecordBatch.from_arrays(columns, schema=part.schema)
                yield part

    return docs.mapInArrow(tidy(run), docs.schema)
