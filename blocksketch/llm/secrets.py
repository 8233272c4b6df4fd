"""Secret scan: rule findings, plus those of a character network over every other key-like token and its context.

Base findings come from three patterns and always stay. Candidates are every run of 16 or more key characters, whatever
they are (CANDIDATE), and every value of 6 or more characters behind a key-like name (NAMED: pwd=, pass:, auth=,
credential is, Bearer and the like), which is taken without its name; a run around such a value leaves its other pieces
as candidates if they still have 16 characters. What overlaps a base finding is no candidate. A small convolutional network in numpy reads the
candidate with CONTEXT characters on both sides, in pieces of PIECE characters whose features are pooled, so a long
candidate is read whole. A candidate whose calibrated probability reaches the threshold of its group (the candidate's
characters: hex, word characters, others) is a finding of kind "cnn".

Training: findings labelled by construction, drawn by a fixed seed (labelled_findings(), TRAIN_ROWS of them): keys of
known shapes and passwords in assignments, headers, URLs and prose, against identifiers, numbers, paths, dates, checksums
said to be such, plain values behind key-like names, long words, and prose. The network is given what candidates() finds
in these texts, as in a scan. By PARTS, the first rows fit the weights, the next calibrate (a logistic map of the
network's output), the next set each group's threshold, which is the highest that still finds RECALL of the group's
secrets, and the last are held out: recall and precision are reported on them. A secret that no candidate covers counts
as missed; one that a base finding covers is not the network's and is left out.

Defined results: a null text is empty and has no findings. Repeated rows are scanned each. Empty tables give empty
tables. Other columns are not read. Offsets are code points, end exclusive.
"""

from __future__ import annotations

import bisect
import functools
import hashlib
import random
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import columns

#: The base patterns, with the group that has the least length and that length.
BASE = (
    ("assign", re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A), 2, 6),
    ("access", re.compile(r"AKIA[A-Z0-9]+"), 0, 20),
    ("hex", re.compile(r"[0-9a-f]+"), 0, 24),
)
_HEX = re.compile(r"[0-9a-f]{24,}")  # the same runs, without those that fail
LEAST = 16
CANDIDATE = re.compile(rf"[A-Za-z0-9+/_=.~-]{{{LEAST},}}")
NAMED = re.compile(r"""(?:key|auth\w{0,12}|cred\w{0,12}|pass\w{0,12}|pwd|pw|pin|secret|token|bearer|signature|sig|webhook|session\w{0,8}|login|jwt|otp)["']?(?:\x20{0,3}[:=]\x20{0,3}|\x20(?:is|was)\x20|(?<=bearer)\x20)["']?([A-Za-z0-9!#$%*+/=@^_~.-]{6,})""", re.I | re.A)
CONTEXT, PIECE, WIDTH, CHANNELS, FILTERS = 24, 96, 5, 10, 32
TRAIN_ROWS, PARTS, RECALL, SEED = 14000, (0.5, 0.6, 0.85), 0.99, 7
_ALNUM = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, rank of kind, kind, end) of the base findings in order."""
    out = []
    for rank, (kind, pattern, group, least) in enumerate(BASE):
        for m in (_HEX if kind == "hex" else pattern).finditer(text):
            if m.end(group) - m.start(group) >= least:
                out.append((m.start(), rank, kind, m.end()))
    return sorted(out)


def candidates(text: str, taken: list[tuple]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    starts, ends = [], []  # stretches of base findings, united
    for s, e in sorted((s, e) for s, _, _, e in taken):
        if ends and s <= ends[-1]:
            ends[-1] = max(ends[-1], e)
        else:
            starts.append(s)
            ends.append(e)
    free = lambda a, b: (t := bisect.bisect_right(ends, a)) == len(starts) or starts[t] >= b
    named = []
    for m in NAMED.finditer(text):
        a, b = m.span(1)
        while b > a and text[b - 1] in ".!":  # the end of a sentence
            b -= 1
        if b - a >= 6 and free(a, b):
            named.append((a, b))
    t = 0
    for m in CANDIDATE.finditer(text):
        a, b = m.span()
        while t < len(named) and named[t][1] <= a:
            t += 1
        if not free(a, b):
            continue
        k = t
        while k < len(named) and named[k][0] < b:
            if named[k][0] - a >= LEAST:
                out.append((a, named[k][0]))
            a, k = max(a, named[k][1]), k + 1
        if b - a >= LEAST:
            out.append((a, b))
    return sorted(out + named)


def group_of(x: str) -> int:
    return 0 if re.fullmatch(r"[0-9a-fA-F]+", x) else 1 if x.isalnum() else 2


def labelled_findings(rows: int = TRAIN_ROWS, seed: int = SEED) -> list[tuple[str, int, int, int]]:
    """(text, start, end, label)."""
    r = random.Random(seed)
    pick = lambda chars, n: "".join(r.choices(chars, k=n))
    low, hexa = _ALNUM[26:52], "0123456789abcdef"
    word = lambda: pick(low, r.randint(2, 9))
    spoken = lambda: pick(low + r.choice(["", "", "éèàçùüößñóí" * 2]), r.randint(2, 9)) + r.choice(["", "", "", "", ",", "."])
    prose = lambda: " ".join(spoken() for _ in range(r.randint(0, 6)))

    def secret() -> tuple[str, str]:
        name = r.choice(["key", "auth", "credential", "client_key", "access_key", "private_key", "pwd", "pass", "bearer", "signature", "webhook"])
        if r.random() < 0.25:  # short values stand behind names
            value = r.choice([
                lambda: pick(_ALNUM, r.randint(8, 15)), lambda: pick(_ALNUM + "!#$%@^*", r.randint(8, 15)) + pick(_ALNUM, 1), lambda: word().title() + pick("0123456789", r.randint(2, 4)) + pick("!#$%@*", r.randint(1, 2)) + pick(_ALNUM, 2),
                lambda: pick(hexa, r.randint(4, 7)) + pick("0123456789", 2) + pick(hexa, r.randint(4, 7)),
            ])()
            lead = r.choice([f"{name}={{}}", f"{name}: {{}}", f'"{name}": "{{}}"', f"{name.upper()}='{{}}'", f"my {name} is {{}} ,", f"https://{word()}.example/?{name}={{}}"])
            return lead, value
        value = r.choice([
            lambda: pick(_ALNUM, r.randint(16, 64)), lambda: pick(_ALNUM, r.randint(16, 24)), lambda: pick(_ALNUM + "+/", r.randint(30, 60)) + "=" * r.randint(0, 2), lambda: r.choice(["ghp_", "gho_", "glpat-", "sk_live_", "rk_live_", "xoxb-", "npm_", "SG.", "sk-"]) + pick(_ALNUM, r.randint(20, 48)),
            lambda: pick(hexa.upper(), r.choice([32, 40, 64])), lambda: "eyJ" + pick(_ALNUM, 30) + "." + pick(_ALNUM + "_-", r.randint(30, 90)) + "." + pick(_ALNUM + "_-", 43), lambda: "AIza" + pick(_ALNUM + "_-", 35),
        ])()
        lead = r.choice([f"{name}={{}}", f'{name}: "{{}}"', f"{name.upper()}={{}}", "Authorization: Bearer {}", "https://" + word() + ".example/?" + name + "={}", "{}", f"export {name.upper()}='{{}}'", f"my {name} is {{}} ,"])
        return lead, value

    def plain() -> tuple[str, str]:
        kind = r.randrange(19)
        name = r.choice(["key", "auth", "credential", "client_key", "access_key", "pwd", "pass", "bearer", "signature", "webhook", "pin", "session", "login", "author", "passage", "authority"])
        mark = r.choice(["{}={{}}", "{}: {{}}", '"{}": "{{}}"', "the {} is {{}} ,", "{}: {{}} " + word()]).format(name)
        camel = "".join(word().title() for _ in range(4))
        date = f"{r.randint(1990, 2030)}-{r.randint(1, 12):02}-{r.randint(1, 28):02}"
        return [
            ("{}", word() + "_" + word() + "_" + str(r.randint(10, 9999)) + word()), ("{}", f"{date}T{r.randint(0, 23):02}.{r.randint(0, 59):02}.00Z"), ("see {}", "/" + "/".join([word(), word(), str(r.randint(10, 99)), word()]) + ".html"), ("https://{}", f"{word()}.example.com/{word()}/{r.randint(10, 9999)}"), ("version {}", f"{word()}-{word()}-{r.randint(1, 20)}.{r.randint(0, 30)}.{r.randint(0, 9)}-{word()}"),
            ("id {}", "-".join(pick(hexa, n) for n in (8, 4, 4, 4, 12))), ("sha256: {} checksum", pick(hexa.upper(), 64)), ("{}", word() + word() + word() + str(r.randint(10, 99)) + word()), ("{}", "=" * r.randint(8, 20) + word() + str(r.randint(10, 99)) + "-" * 12), ("order {}", "ORD-" + date + "-" + pick("0123456789", 8)),
            (mark, pick(low, r.randint(6, 12))), (mark, r.choice([date, word() + "-" + word(), word() + "_" + word(), word() + "/" + word() + ".txt", "/" + word() + "/" + word(), word().title() + word()])),
            ("{}", word() + camel + pick(low, 8)), ("{}", pick(low, r.randint(16, 30))), ("{}", r.choice("=-_.~") * r.randint(16, 60)), (r.choice(["no {}", "{}", word() + ": {}"]), pick("0123456789", r.randint(16, 24))), ("{}", pick(low, r.randint(16, 24)).upper()),
            (r.choice(["{}", "{}", "card {}", "account: {}", "{}."]), pick("0123456789", 16)), ("{}", r.choice(" -").join(pick("0123456789", 4) for _ in range(4)) + pick("0123456789", 4)),
        ][kind]

    out = []
    for i in range(rows):
        label = i % 2
        lead, value = secret() if label else plain()
        a, b = lead.split("{}")
        before = prose() + r.choice([" ", "\n", ""]) + a
        out.append((before + value + b + r.choice([" ", "\n", ". ", ""]) + prose(), len(before), len(before) + len(value), label))
    return out


def labelled_candidates(rows: list[tuple[str, int, int, int]]) -> tuple[list[tuple[str, int, int]], np.ndarray, np.ndarray]:
    """What a scan would show the network of labelled_findings(): candidates, whether each covers a secret, and its row; and, as candidates without a text, the secrets that neither a candidate nor a base finding covers."""
    shown, label, own = [], [], []
    for i, (text, a, b, secret) in enumerate(rows):
        base = base_spans(text)
        found = False
        for s, e in candidates(text, base):
            hit = bool(secret) and s <= a and b <= e
            found |= hit
            if hit or not secret or e <= a or s >= b:  # a piece of a secret is neither
                shown.append((text, s, e))
                label.append(hit)
                own.append(i)
        if secret and not found and not any(s <= a and b <= e for s, _, _, e in base):
            shown.append(("", 0, 0))
            label.append(True)
            own.append(i)
    return shown, np.array(label, dtype=float), np.array(own)


def encode(text: str, start: int, end: int) -> np.ndarray:
    """Character codes from 1 to 96 (0: none), plus 97 inside the candidate."""
    a, b = max(0, start - CONTEXT), min(len(text), end + CONTEXT)
    x = np.frombuffer(text[a:b].encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.int64)
    x = np.where((x >= 32) & (x < 127), x - 31, 96)
    x[start - a : end - a] += 97
    return x


class Network:
    """Embedding, one convolution, rectifier, largest and mean feature, logistic output; trained by Adam."""

    def __init__(self, seed: int = SEED):
        g = np.random.default_rng(seed)
        self.w = {"e": g.normal(0, 0.3, (194, CHANNELS)), "c": g.normal(0, 0.15, (WIDTH * CHANNELS, FILTERS)), "b": np.zeros(FILTERS), "o": g.normal(0, 0.1, 2 * FILTERS), "z": np.zeros(1)}
        self.w["e"][0] = 0

    def pieces(self, codes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """Rows of PIECE codes, overlapping by WIDTH - 1, and each row's candidate."""
        rows, own = [], []
        for i, x in enumerate(codes):
            for a in range(0, max(1, len(x) - WIDTH + 1), PIECE - WIDTH + 1):
                rows.append(np.pad(x[a : a + PIECE], (0, max(0, PIECE - len(x[a : a + PIECE])))))
                own.append(i)
        return np.array(rows), np.array(own)

    def features(self, rows: np.ndarray, own: np.ndarray, n: int):
        x = self.w["e"][rows]
        win = np.lib.stride_tricks.sliding_window_view(x, WIDTH, axis=1).transpose(0, 1, 3, 2).reshape(len(rows), PIECE - WIDTH + 1, -1)
        h = np.maximum(win @ self.w["c"] + self.w["b"], 0)
        top, total, size = np.zeros((n, FILTERS)), np.zeros((n, FILTERS)), np.zeros(n)
        np.maximum.at(top, own, h.max(1))
        live = (rows[:, : PIECE - WIDTH + 1] > 97)[:, :, None]  # the mean is over the candidate
        np.add.at(total, own, (h * live).sum(1))
        np.add.at(size, own, live.sum((1, 2)))
        return win, h, live, np.concatenate([top, total / np.maximum(size, 1)[:, None]], 1), size

    def logits(self, codes: list[np.ndarray]) -> np.ndarray:
        out = []
        for a in range(0, len(codes), 256):
            rows, own = self.pieces(codes[a : a + 256])
            out.append(self.features(rows, own, len(codes[a : a + 256]))[3] @ self.w["o"] + self.w["z"])
        return np.concatenate(out) if out else np.empty(0)

    def fit(self, codes: list[np.ndarray], y: np.ndarray, epochs: int = 6, batch: int = 128, rate: float = 0.01) -> None:
        g, m = np.random.default_rng(SEED), {k: [np.zeros_like(v), np.zeros_like(v)] for k, v in self.w.items()}
        t = 0
        for _ in range(epochs):
            order = g.permutation(len(codes))
            for a in range(0, len(order), batch):
                at = order[a : a + batch]
                rows, own = self.pieces([codes[i] for i in at])
                win, h, live, f, size = self.features(rows, own, len(at))
                d = (1 / (1 + np.exp(-(f @ self.w["o"] + self.w["z"]))) - y[at]) / len(at)
                df = d[:, None] * self.w["o"]
                best = h == f[own][:, None, :FILTERS]
                dh = (best / np.maximum(best.sum(1, keepdims=True), 1) * df[own][:, None, :FILTERS] + live * (df[:, FILTERS:] / np.maximum(size, 1)[:, None])[own][:, None]) * (h > 0)
                dx = (dh @ self.w["c"].T).reshape(*dh.shape[:2], WIDTH, CHANNELS)
                de = np.zeros_like(self.w["e"])
                for k in range(WIDTH):
                    np.add.at(de, rows[:, k : k + dh.shape[1]], dx[:, :, k])
                de[0] = 0
                grads = {"e": de, "c": np.einsum("bli,blf->if", win, dh, optimize=True), "b": dh.sum((0, 1)), "o": f.T @ d, "z": np.array([d.sum()])}
                t += 1
                for k, gr in grads.items():
                    m[k][0] = 0.9 * m[k][0] + 0.1 * gr
                    m[k][1] = 0.999 * m[k][1] + 0.001 * gr * gr
                    self.w[k] = self.w[k] - rate * (m[k][0] / (1 - 0.9**t)) / (np.sqrt(m[k][1] / (1 - 0.999**t)) + 1e-8)


@functools.cache
def trained(rows: int = TRAIN_ROWS, seed: int = SEED, recall: float = RECALL) -> dict:
    """{weights, slope, offset, limits by group; recall, recall by group, precision, and the share of secrets that never become candidates, on the held-out rows}."""
    data = labelled_findings(rows, seed)
    shown, y, own = labelled_candidates(data)
    live = np.array([bool(t) for t, *_ in shown])
    groups = np.array([group_of(data[i][0][data[i][1] : data[i][2]]) if not t else group_of(t[a:b]) for i, (t, a, b) in zip(own, shown)])
    part = np.digitize(own, [rows * x for x in PARTS])
    codes = lambda which: [encode(*shown[k]) for k in np.flatnonzero(which)]
    net = Network(seed)
    net.fit(codes((part == 0) & live), y[(part == 0) & live])
    middle = (part == 1) & live
    z, slope, offset = net.logits(codes(middle)), 1.0, 0.0
    for _ in range(200):  # a logistic map of the output, by gradient steps
        e = 1 / (1 + np.exp(-np.clip(slope * z + offset, -40, 40))) - y[middle]
        slope, offset = slope - 0.02 * float((e * z).mean()), offset - 0.2 * float(e.mean())
    late = part >= 2
    p = np.zeros(len(shown))  # a secret that is no candidate has no chance
    p[late & live] = 1 / (1 + np.exp(-np.clip(slope * net.logits(codes(late & live)) + offset, -40, 40)))
    limits = {}
    for g in range(3):
        mine = np.sort(p[(part == 2) & (groups == g) & (y == 1)])
        limits[g] = highest_limit(mine, recall) if len(mine) else 0.5
        if limits[g] <= 0:
            raise ValueError("more secrets are no candidates than the recall allows")
    held = part == 3
    said = held & (p >= np.array([limits[g] for g in groups]))
    secret = held & (y == 1)
    by_group = {g: float(said[secret & (groups == g)].mean()) for g in range(3) if (secret & (groups == g)).any()}
    return {"weights": net.w, "slope": slope, "offset": offset, "limits": limits, "recall": float(said[secret].mean()), "recall_by_group": by_group, "precision": float(y[said].mean()) if said.any() else 0.0, "no_candidate": float((~live[secret]).mean())}


def highest_limit(p: np.ndarray, recall: float) -> float:
    """The highest threshold that at least the share recall of the secrets' probabilities, in rising order, reach."""
    return float(p[min(len(p) - 1, int((1 - recall) * len(p) + 1e-9))])


def find(texts: list[str | None], model: dict) -> list[list[tuple[int, int, str, int]]]:
    """(start, rank of kind, kind, end) of each text's findings in order."""
    net = Network()
    net.w = model["weights"]
    found, codes, where = [], [], []
    for i, text in enumerate(texts):
        text = text or ""
        base = base_spans(text)
        found.append(base)
        for a, e in candidates(text, base):
            codes.append(encode(text, a, e))
            where.append((i, a, e, group_of(text[a:e])))
            if len(codes) == 4096:  # a long text may hold many
                _judge(net, model, codes, where, found)
                codes, where = [], []
    _judge(net, model, codes, where, found)
    return [sorted(f) for f in found]


def _judge(net: Network, model: dict, codes: list[np.ndarray], where: list[tuple], found: list[list]) -> None:
    p = 1 / (1 + np.exp(-np.clip(model["slope"] * net.logits(codes) + model["offset"], -40, 40)))
    for (i, a, e, g), q in zip(where, p):
        if q >= model["limits"][g]:
            found[i].append((a, len(BASE), "cnn", e))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", model: dict | None = None) -> DataFrame:
    """(doc_id, findings array<struct<kind, start, end>>) by start, then kind: a row for each row of docs."""
    model = model or trained()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        for b in batches:
            out = [[{"kind": k, "start": a, "end": e} for a, _, k, e in f] for f in find(b["text"].to_pylist(), model)]
            yield pa.RecordBatch.from_arrays([b["doc_id"], pa.array(out, kind)], ["doc_id", "findings"])

    d = columns(docs, doc_id=id_col, text=text_col)
    return d.mapInArrow(run, f"doc_id {dict(d.dtypes)['doc_id']}, findings array<struct<kind: string, start: long, end: long>>")


def digest(found: DataFrame) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans) of scan()'s rows; spans are kind:start:end."""
    from pyspark.sql import functions as F

    said = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    count = lambda kind: F.size(F.filter("findings", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    base = F.filter("findings", lambda s: s["kind"] != "cnn")
    return found.select("doc_id", *[count(k) for k, *_ in BASE], F.sha2(said(base), 256).alias("base_sha256"), said(F.col("findings")).alias("spans"))


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return digest(scan(table(spark, sf_dir, "documents")))
