"""Secret scanning: fixed patterns, and a linear-chain CRF that adds spans.

Tokens are runs of A-Z, a-z, 0-9 and + / _ . = - or single other marks. The CRF tags
each as begin, inside or outside from its shape, its neighbours and features of the
file, trained by gradient steps on the log-likelihood (forward-backward) and decoded
by Viterbi. What can be tagged is a token of LEAST characters or more that is not a
plain word (it holds a digit, one of + / _ =, a capital after a small letter, or 24
letters), and any token of AFTER_MARK characters or more that follows a colon or an
equals sign. All others are outside, so a text is decoded over the chains of such tokens
with nothing but marks between them, exactly as over the whole chain.

The patterns' own matches would only teach the tagger the patterns. So the texts of the
training sample also get planted secrets, random strings of several alphabets and
lengths between words that the patterns do not know or none at all, and planted decoys
(numbers of cards, phones and versions, dates, addresses, paths, names of variables),
and half of the matches lose the words before them. An unmatched string of the corpus
counts as no secret unless a first tagger takes it for one. The sample has MAX_DOCS documents,
drawn by a hash of the id, and at most MAX_CHAINS chains of each, drawn by a hash.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Kinds in order, with their patterns, and the least length of a match
#: (of group 2 for the first).
KINDS = ("assign", "access", "hex", "tagged")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
#: Bounds on the training sample: documents, and chains of each.
MAX_DOCS, MAX_CHAINS = 4000, 24
#: Least lengths of a token that can be tagged, anywhere and after a mark.
LEAST, AFTER_MARK = 8, 6
#: Characters of a text that features look at, before and after a token.
BEFORE, AFTER = 40, 12
DIGITS = re.compile(r"[0-9]+")
SEED = re.compile(r"[0-9+/_=]|[a-z](?=[A-Z])|[A-Za-z]{24}")
MARKED = re.compile(r"[:=][\"'\x20]{0,3}(?=[A-Za-z0-9+/_.=-]{6})")
RUN = re.compile(r"[A-Za-z0-9+/_.=-]*")
ATOM = re.compile(r"[A-Za-z0-9+/_.=-]+|[^\sA-Za-z0-9+/_.=-]")
BODY = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_.=-")


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the pattern matches, sorted."""
    found = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m.group(2)) >= 6]
    found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def candidates(text: str) -> list[tuple[int, int]]:
    """The tokens that can be tagged, as (start, end) in order; a dot or dash at the end
    is left out, as it ends a sentence more often than a secret, and so is what stands
    before an equals sign."""
    found: dict[int, int] = {}
    for pattern, least in ((SEED, LEAST), (MARKED, AFTER_MARK)):
        end = 0
        for m in pattern.finditer(text):
            start = m.start() if pattern is SEED else m.end()
            if start < end:
                continue
            while start > end and text[start - 1] in BODY:
                start -= 1
            end = RUN.match(text, start).end()
            stop = end
            while stop > start and text[stop - 1] in ".-":
                stop -= 1
            start += text[start:stop].rstrip("=").rfind("=") + 1
            if stop - start >= least:
                found[start] = max(stop, found.get(start, 0))
    return sorted(found.items())


def chains(text: str) -> Iterator[list[tuple[int, int]]]:
    """Runs of such tokens with no more than three marks and blanks between them."""
    run: list[tuple[int, int]] = []
    for start, end in candidates(text):
        if run and start < run[-1][1]:
            continue
        if run and (start - run[-1][1] > 3 or any(c.isalnum() for c in text[run[-1][1] : start])):
            yield run
            run = []
        run.append((start, end))
    if run:
        yield run


def shape(token: str) -> list[str]:
    n, c = len(token), Counter(token)
    entropy = -sum(v / n * math.log2(v / n) for v in c.values())
    kinds = "".join(k for k, r in (("d", r"[0-9]"), ("l", r"[a-z]"), ("U", r"[A-Z]"), ("s", r"[+/_.=-]")) if re.search(r, token))
    return [f"n{min(n // 4, 12)}", f"c{kinds}", f"h{round(entropy * 2)}", f"x{bool(re.fullmatch(r'[0-9a-f]+', token))}", f"p{token[:4] if token[:4].isupper() else ''}", f"d{round(5 * sum(c[x] for x in '0123456789') / n)}", f"turns{min(len(re.findall(r'[0-9][A-Za-z]|[A-Za-z][0-9]', token)), 8)}"]


def features(text: str, spans: list[tuple[int, int]], file: list[str]) -> list[list[str]]:
    out = []
    for start, end in spans:
        before = ATOM.findall(text[max(0, start - BEFORE) : start])[-3:]
        after = ATOM.findall(text[end : end + AFTER])[:1]
        near = [f"b{i}{w.lower() if len(w) < 12 and not any(x.isdigit() for x in w) else '#'}" for i, w in enumerate(reversed(before))]
        out.append(["bias", *shape(text[start:end]), *near, *(f"a{w if not w[0].isalnum() else '#'}" for w in after), *file])
    return out


def file_features(text: str) -> list[str]:
    n = max(1, len(text))
    return [f"fd{min(9, round(20 * len(DIGITS.findall(text)) * 10 / n))}", f"fl{min(9, int(math.log2(n)))}"]


class Tagger:
    """States 0 outside, 1 begin, 2 inside; weights by feature, and transitions."""

    def __init__(self):
        self.w: dict[str, list[float]] = {}
        self.t = [[0.0, 0.0, -9.0], [0.0, 0.0, 0.0], [0.0, 0.0, 0.0]]

    def scores(self, feats: list[str]) -> list[float]:
        s = [0.0, 0.0, 0.0]
        for f in feats:
            if w := self.w.get(f):
                s[0] += w[0]
                s[1] += w[1]
                s[2] += w[2]
        return s

    def decode(self, chain: list[list[str]]) -> list[int]:
        """Viterbi; the chain starts and ends next to an outside token."""
        best, back = self.t[0], []
        best = list(best)
        for i, feats in enumerate(chain):
            e = self.scores(feats)
            if i == 0:
                best = [best[k] + e[k] for k in range(3)]
                continue
            step = [max(range(3), key=lambda j: best[j] + self.t[j][k]) for k in range(3)]
            best = [best[step[k]] + self.t[step[k]][k] + e[k] for k in range(3)]
            back.append(step)
        k = max(range(3), key=lambda j: best[j] + self.t[j][0])
        out = [k]
        for step in reversed(back):
            k = step[k]
            out.append(k)
        return out[::-1]

    def learn(self, chain: list[list[str]], gold: list[int], rate: float) -> None:
        """One step along the gradient of the log-likelihood of gold."""
        e = [self.scores(f) for f in chain]
        n, t = len(chain), self.t
        up = lambda v: (m := max(v)) + math.log(sum(math.exp(x - m) for x in v))
        a = [[t[0][k] + e[0][k] for k in range(3)]]
        for i in range(1, n):
            a.append([up([a[-1][j] + t[j][k] for j in range(3)]) + e[i][k] for k in range(3)])
        b = [[t[k][0] for k in range(3)]]
        for i in range(n - 1, 0, -1):
            b.append([up([t[k][j] + e[i][j] + b[-1][j] for j in range(3)]) for k in range(3)])
        b.reverse()
        z = up([a[-1][k] + t[k][0] for k in range(3)])
        for i, feats in enumerate(chain):
            p = [math.exp(min(0.0, a[i][k] + b[i][k] - z)) for k in range(3)]
            for f in feats:
                w = self.w.setdefault(f, [0.0, 0.0, 0.0])
                for k in range(3):
                    w[k] += rate * ((gold[i] == k) - p[k] - 0.002 * w[k])
        for i in range(1, n):
            for j in range(3):
                for k in range(3):
                    p = math.exp(min(0.0, a[i - 1][j] + t[j][k] + e[i][k] + b[i][k] - z))
                    t[j][k] += rate * ((gold[i - 1] == j and gold[i] == k) - p)


def train(samples: list[tuple[list[list[str]], list[int]]], epochs: int = 6, seed: int = 7) -> Tagger:
    import random

    rng, tagger = random.Random(seed), Tagger()
    for epoch in range(epochs):
        rng.shuffle(samples)
        for chain, gold in samples:
            drop = rng.random() < 0.5  # without the words before it
            seen = [[f for f in feats if not f.startswith("b")] for feats in chain] if drop and any(gold) else chain
            tagger.learn(seen, gold, 0.2 / (1 + epoch))
    return tagger


#: What stands before planted secrets, and the alphabets of these.
LEADS = ("", "", "key ", "auth: ", "credential = ", "Bearer ", "pwd=", "login with ", "private_key: '", "export KEY=", "use \"", "signature ", "session: ", "--auth ", "hash <")
ALPHABETS = ("0123456789abcdef", "0123456789ABCDEF", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", "abcdefghijklmnopqrstuvwxyz0123456789_-")


def secret(rng) -> str:
    """A random secret: a string over an alphabet, some with a prefix or padding."""
    letters = rng.choice(ALPHABETS)
    body = "".join(rng.choice(letters) for _ in range(rng.choice((16, 20, 24, 32, 36, 40, 48, 64))))
    head = rng.choice(("", "", "", "sk_", "pk-", "ab1_", "v1."))
    return head + body + ("==" if "+" in letters and rng.random() < 0.5 else "")


def decoy(rng) -> str:
    """A random string that looks like a secret and is none."""
    digits = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randrange(3, 9)))
    return rng.choice((
        lambda: digits(16), lambda: digits(rng.randrange(8, 14)), lambda: f"20{digits(2)}-0{rng.randrange(1, 10)}-1{digits(1)}", lambda: f"+1-{digits(3)}-{digits(3)}-{digits(4)}",
        lambda: f"{word()}.{digits(2)}@mail{digits(1)}.{word()}.com", lambda: f"https://www.{word()}.com/{word()}/{digits(3)}", lambda: f"/usr/{word()}/{word()}/{word()}.{word()[:3]}", lambda: f"{word()}{word().title()}{word().title()}",
        lambda: f"{word()}_{word()}_{word()}", lambda: f"{word()}-{word()}-{digits(4)}", lambda: f"{digits(1)}.{digits(2)}.{digits(2)}-{word()}", lambda: word() * 5, lambda: f"{digits(2)}.{digits(2)}.{digits(3)}.{digits(2)}", lambda: f"{word().title()}{digits(4)}",
    ))()


def planted(text: str, rng, n: int = 4) -> tuple[str, list[tuple[int, int]], list[tuple[int, int]]]:
    """The text with n planted strings between its words, the places of the secrets among
    them, and those of the decoys."""
    gaps = sorted({m.start() for m in re.finditer(r"[ \n]", text)})
    at = sorted(rng.sample(gaps, min(n, len(gaps)))) if gaps else [0]
    out, spans, decoys, done, size = [], [], [], 0, 0
    for place in at:
        real = rng.random() < 0.5
        lead = rng.choice(LEADS) if real or rng.random() < 0.3 else ""
        body = secret(rng) if real else decoy(rng)
        before = f"{text[done:place]} {lead}"
        (spans if real else decoys).append((size + len(before), size + len(before) + len(body)))
        tail = {"'": "'", '"': '"', "<": ">"}.get(lead[-1:], "")
        out.append(before + body + tail)
        size += len(out[-1])
        done = place
    return "".join(out) + text[done:], spans, decoys


def labelled(text: str, spans: list[tuple[int, int]] = (), decoys: list[tuple[int, int]] = ()) -> list[tuple[list[list[str]], list[int], bool]]:
    """Chains of a text with tags from its pattern matches and from the given spans, and
    whether they are sure: they hold a match, a span or a decoy. What else looks like a
    secret may be one that nobody has marked."""
    known = [(s, e) for s, _, e in base_spans(text)] + list(spans)
    file, out = file_features(text), []
    for run in chains(text):
        gold, last = [], None
        for start, end in run:
            hit = next((b for b in known if b[0] < end and start < b[1]), None)
            gold.append(0 if hit is None else 2 if hit is last else 1)
            last = hit
        sure = any(gold) or any(a < run[-1][1] and run[0][0] < b for a, b in decoys)
        out.append((features(text, run, file), gold, sure))
    return out


def sample_of(text: str, most: int = MAX_CHAINS) -> list[tuple[list[list[str]], list[int], bool]]:
    """At most `most` labelled chains of a text, and of the text with plants those that
    hold one, drawn by a hash; the same for the same text."""
    import random

    rng = random.Random(hashlib.sha256(text.encode("utf-8", "replace")).digest())
    found = labelled(text) + [x for x in labelled(*planted(text, rng)) if x[2]]
    return found if len(found) <= most else rng.sample(found, most)


def taught(samples: list[tuple[list[list[str]], list[int], bool]]) -> Tagger:
    """Trained on the sure chains, then on all but those others in which the first
    tagger sees a secret: an unmarked secret must not teach that it is none."""
    first = train([(f, g) for f, g, sure in samples if sure])
    return train([(f, g) for f, g, sure in samples if sure or not any(first.decode(f))])


def fit(docs: DataFrame, max_docs: int = MAX_DOCS) -> Tagger | None:
    """A tagger from a bounded sample of docs; None if it has no chain."""
    n = docs.count()
    draw = F.pmod(F.xxhash64("doc_id", F.lit("secrets")), F.lit(1 << 30)) / float(1 << 30)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = [(i.as_py(), k, *chain) for i, t in zip(b.column(0), b.column(1), strict=True) for k, chain in enumerate(sample_of(t.as_py() or ""))]
            kinds = [pa.int64(), pa.int32(), pa.list_(pa.list_(pa.string())), pa.list_(pa.int32()), pa.bool_()]
            yield pa.RecordBatch.from_arrays([pa.array([m[c] for m in made], k) for c, k in enumerate(kinds)], names=["doc_id", "k", "feats", "gold", "sure"])

    # Half of the bound on average: no draw of a hash comes near the double of it.
    chosen = docs.where(draw < max_docs / 2 / max(1, n)).select(F.col("doc_id").cast("long"), "text")
    rows = chosen.mapInArrow(run, "doc_id long, k int, feats array<array<string>>, gold array<int>, sure boolean").collect()
    rows.sort(key=lambda r: (r["doc_id"] is None, r["doc_id"] or 0, r["k"], r["feats"]))
    return taught([(r["feats"], r["gold"], r["sure"]) for r in rows]) if any(any(r["gold"]) for r in rows) else None


def find(text: str, tagger: Tagger | None) -> tuple[list, list, int]:
    """The pattern matches; these with the tagger's further spans, sorted; and how many
    matches the tagger finds too. A tagged span that meets a match adds nothing."""
    base = base_spans(text)
    tagged, file = [], None
    for run in chains(text) if tagger else ():
        file = file or file_features(text)
        start = None
        tags = tagger.decode(features(text, run, file))
        for (s, e), tag, after in zip(run, tags, [*tags[1:], 0], strict=True):
            if tag:
                start = s if tag == 1 or start is None else start
                if after != 2:
                    tagged.append((start, 3, e))
                    start = None
    extra = [x for x in tagged if not any(b[0] < x[2] and x[0] < b[2] for b in base)]
    agreed = sum(any(b[0] < x[2] and x[0] < b[2] for x in tagged) for b in base)
    return base, sorted(base + extra), agreed


def written(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def scan(docs: DataFrame, tagger: Tagger | None) -> DataFrame:
    """One row per row of docs: doc_id, n_assign, n_access, n_hex, base_sha256 (of the
    pattern matches as kind:start:end, by start, then kind), spans (all of them),
    n_tagged (those that the tagger adds) and n_agreed (matches that it finds too). Starts and ends count code points. A null text counts as
    empty; rows that share an id are scanned each; other columns are not read."""
    shared = docs.sparkSession.sparkContext.broadcast(tagger)
    names = ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_tagged", "n_agreed"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cols: list[list] = [[] for _ in names[1:]]
            for t in b.column(1):
                base, spans, agreed = find(t.as_py() or "", shared.value)
                n = Counter(k for _, k, _ in spans)
                for c, v in zip(cols, (n[0], n[1], n[2], hashlib.sha256(written(base).encode()).hexdigest(), written(spans), n[3], agreed), strict=True):
                    c.append(v)
            kinds = [pa.int64()] * 3 + [pa.string()] * 2 + [pa.int64()] * 2
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names=names)

    schema = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_tagged long, n_agreed long"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema)
