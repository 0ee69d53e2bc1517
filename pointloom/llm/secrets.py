"""Secret scans: fixed patterns, and a linear-chain conditional random field that adds spans.

Texts are cut at ASCII white space into tokens. Every token is tagged begin, inside or outside of a secret from its own
shape, the two tokens before it and the one after it, and statistics of the file, decoded by Viterbi. Scores depend on token types, so each distinct
token of a batch is described once and whole batches are scored with array indexing. A token whose outside score
beats the others by more than any pair of transitions can win back is outside in every best path; the chain is cut
at such tokens and only the stretches between them need the recursion, which changes no result.

The weights are fitted here, by gradient ascent on the exact conditional likelihood, from sentences generated
with a fixed seed: code and prose with and without secrets of the families ``SECRETS``, and look-alikes ``OTHERS`` that are
none (addresses, identifiers, hashes, numbers, mail, markup, shouting, long words). Families of ``UNSEEN`` are never fitted:
:func:`found_shares` measures them. No document is needed, so the fit is the same everywhere, and done once a process.

Base spans always stay. A span of the field is added, as kind ``crf``, where it overlaps no base span; punctuation around
a token and a ``name=`` before it are not part of the span, and of credentials in an address only the password is.

Defined cases: null and empty texts have no spans (counts 0, digest of the empty string); a null doc_id is kept; an
empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import functools
import hashlib
import random
import re
import string
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pointloom.llm.common import lean

# The base patterns; letters of the names in either case, ASCII only.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile("AKIA[A-Z0-9]+")
HEX = re.compile("[0-9a-f]{24,}")  # greedy, so the same as all runs of 24 or more
#: Distinct tokens that a task remembers before it starts anew.
MAX_TYPES = 500_000
#: Tokens that are scored at a time; a text is never cut.
STEP = 400_000
KINDS = ("assign", "access", "hex", "crf")
NAMES = ("password", "passwd", "pwd", "secret", "token", "apikey", "api_key", "api-key", "auth", "bearer", "credential", "private", "access_key", "passphrase")
_TOKEN = re.compile("[^\x20\x09-\x0d]+")
_CORE = re.compile(r"""^[("'`\[<{]*(?:[A-Za-z_.\-]{2,30}["']?[:=]["']?)?(.*?)[)"'`,;\]>}.]*$""", re.S)

#: The password in an address: scheme://user:password@host.
_LOGIN = re.compile(r"[A-Za-z][A-Za-z0-9+.\-]*://[^\s:/@]*:([^\s/@]+)@")
_UUID = re.compile(r"[0-9A-Fa-f]{8}(?:-[0-9A-Fa-f]{4}){3}-[0-9A-Fa-f]{12}")

BEGIN, INSIDE, OUTSIDE = 0, 1, 2


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the fixed patterns."""
    found = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


# token features ------------------------------------------------------------------------------------------------

_LENGTHS = (4, 8, 12, 16, 20, 32, 48)
N_OWN = 42
_ENDS = ".,;!?*$&%#"
N_SIDE = 7
N_FILE = 7


def _runs(core: str) -> float:
    """Share of neighbouring characters of different classes; random strings change class often."""
    kind = ["d" if c.isdigit() else "u" if c.isupper() else "l" if c.islower() else "p" for c in core]
    return sum(a != b for a, b in zip(kind, kind[1:])) / max(1, len(kind) - 1)


def _opens(token: str) -> bool:
    """Whether a value may follow; two equal signs are the padding of a value."""
    return token[-1:] in (":", "=") and token[-2:] != "=="


def own_features(token: str) -> tuple[int, ...]:
    """Indexes of the features that the token has: its shape."""
    word = token.rstrip(_ENDS)
    if len(word) < 16 and word.isalpha():
        return (0, 1 if word.islower() else 2) if word.isascii() else (0, 22)
    core = _CORE.match(token)[1]
    low, n = token.lower(), len(core)
    out = [0]
    digits, upper, lower = (sum(map(f, core)) for f in (str.isdigit, str.isupper, str.islower))
    other = n - digits - upper - lower
    long = max((len(x) for x in re.split("[^A-Za-z0-9]+", core)), default=0)
    named = any(x in low for x in NAMES)
    out.append(8 + sum(n >= k for k in _LENGTHS))
    if digits and (upper or lower):
        out.append(3)
    if digits and upper and lower:
        out.append(4)
    if n and digits == n:
        out.append(5)
    if n and not digits:
        out.append(6)
    if n >= 12 and _runs(core) > 0.3 and digits:
        out.append(7)
    if n >= 16 and len(set(core)) >= 12 and digits:
        out.append(16)
    if n >= 6 and all(c in string.hexdigits for c in core):
        out.append(17)
    if named:
        out.append(18)
    if re.match(r"^[\"'(]*[A-Za-z_.\-]{2,30}[\"']?[:=]", token):
        out.append(19)
    if "@" in core:
        out.append(20)
    if "://" in core or low.startswith("www."):
        out.append(21)
    if not token.isascii():
        out.append(22)
    if re.fullmatch(r"[0-9.,:/+()\-%$]*", core):
        out.append(23)
    if re.match(r"^[A-Za-z]{2,6}[0-9]?[-_.][A-Za-z0-9]", core) and long >= 16 and digits:
        out.append(24)
    if n and other / n > 0.3:
        out.append(25)
    if _opens(token):
        out.append(26)
    if core.startswith("-----") or "PRIVATE" in core:
        out.append(27)
    if named and n >= 8 and digits:
        out.append(28)
    if re.search(r"[<>{}();|]", core):
        out.append(29)
    if re.search(r"([A-Za-z])\1\1|[a-z]{12}", core):
        out.append(30)
    if n >= 20 and not other and upper and digits:
        out.append(31)
    if _UUID.search(core):
        out.append(32)
    if _LOGIN.search(token):
        out.append(33)
    if long >= 20 and digits and upper and lower:
        out.append(34)
    if long < 12:
        out.append(35)
    if core.count("/") > 1 or core.startswith(("./", "~/", "\\")):
        out.append(36)
    if n >= 20 and sum(c in "+/" for c in core) and upper and lower and digits:
        out.append(37)
    if re.match(r"^(0x|#|sha\d|md5|rev|v\d|urn)", core.lower()):
        out.append(38)
    if re.search(r"[a-z]{4,}[A-Z][a-z]{3,}|[a-z]{4,}[-_][a-z]{4,}|[aeiou][bcdfghlmnprst][aeiou][a-z]{3,}", core):
        out.append(39)
    if re.fullmatch("[A-Z0-9-]+", core) and n >= 8:
        out.append(40)
    if 6 <= n < 20 and digits and (upper or lower) and other <= 2 and _runs(core) > 0.35:
        out.append(41)
    return tuple(out)


def side_features(token: str) -> tuple[int, ...]:
    """What a token says about those beside it."""
    low, out = token.lower(), []
    word = low.rstrip(_ENDS)
    if word.isalpha() and word not in NAMES:
        out = [6] if word in ("is", "was", "are", "be", "as", "to", "ist", "est", "es") else [0]
        return (*out, 5) if token[-1] in ".;," else tuple(out)
    if any(x in low for x in NAMES):
        out.append(1)
        if _opens(token):
            out.append(2)
    if token in ("=", ":", ":=", "=>"):
        out.append(3)
    if _opens(token):
        out.append(4)
    if token[-1:] in ".;,":
        out.append(5)
    return tuple(out)


def file_marks(token: str, own: tuple[int, ...]) -> tuple[int, int, int]:
    """What a token counts for in the file: a mark of code, the name of a secret, a long mixed string."""
    return int(_opens(token) or token[-1:] in (";", "{", "}")), int(18 in own), int(16 in own)


def file_features(marks: np.ndarray, n_tokens: np.ndarray) -> np.ndarray:
    """One row a file, from its sums of :func:`file_marks`: always, some or many marks of code, long, short, names of secrets, and
    many mixed strings (a list of keys or identifiers)."""
    code, names, mixed = marks.T
    return np.stack([np.ones(len(n_tokens)), code * 20 > n_tokens, code * 5 > n_tokens, n_tokens > 2000, n_tokens < 40, names * 50 > n_tokens, mixed * 10 > n_tokens], axis=1).astype(float)


class Field:
    """Weights of tags by the features of the token, of the one before, of the second before, of the next and of the file, and of
    tag pairs; row 3 starts a chain."""

    def __init__(self, own, before, second, after, file, pair):
        self.own, self.before, self.second, self.after, self.file, self.pair = own, before, second, after, file, pair

    def tables(self, types: _Types) -> tuple[np.ndarray, ...]:
        """Score rows of each distinct token in its four places."""
        own = np.array([self.own[list(f)].sum(axis=0) for f in types.own_kinds]).reshape(-1, 3)[np.array(types.own, np.int64)]
        side = np.array(types.side, np.int64)
        return own, *(np.array([w[list(f)].sum(axis=0) for f in types.side_kinds]).reshape(-1, 3)[side] for w in (self.before, self.second, self.after))

    def viterbi(self, emit: np.ndarray) -> np.ndarray:
        """The best tags of one chain of scores (n, 3)."""
        pair, best, back = self.pair[:3], emit[0] + self.pair[3], []
        for row in emit[1:]:
            step = best[:, None] + pair
            back.append(step.argmax(axis=0))
            best = step.max(axis=0) + row
        tags = [int(best.argmax())]
        for b in reversed(back):
            tags.append(int(b[tags[-1]]))
        return np.array(tags[::-1])

    def tags(self, emit: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Best tags of many chains laid end to end; ``starts`` are their first positions. See the module's head."""
        out = np.full(len(emit), OUTSIDE)
        margin = emit[:, OUTSIDE] - np.maximum(emit[:, BEGIN], emit[:, INSIDE])
        sure = margin > 2 * (self.pair.max() - self.pair.min())
        open_ = np.flatnonzero(~sure)
        if not len(open_):
            return out
        first = np.zeros(len(emit) + 1, bool)
        first[starts] = True
        groups = np.split(open_, np.flatnonzero((np.diff(open_) > 1) | first[open_[1:]]) + 1)
        for g in groups:
            lo, hi = g[0], g[-1] + 1
            # a sure neighbour on either side is part of the chain that is decoded
            lo -= not first[lo]
            hi += hi < len(emit) and not first[hi]
            part = emit[lo:hi].copy()
            if not first[lo]:
                part[0] += self.pair[OUTSIDE] - self.pair[3]
            out[lo:hi] = self.viterbi(part)
        return out


# fitting -------------------------------------------------------------------------------------------------------

_MIXED, _HEXA = string.ascii_letters + string.digits, "0123456789abcdef"


def _pick(rng: random.Random, chars: str, lo: int, hi: int | None = None) -> str:
    return "".join(rng.choice(chars) for _ in range(rng.randint(lo, hi or lo)))


def _uuid(rng):
    return "-".join(_pick(rng, _HEXA, k) for k in (8, 4, 4, 4, 12))


#: Families of secrets: a token for each.
SECRETS = {
    "access key": lambda r: "AKIA" + _pick(r, string.ascii_uppercase + string.digits, 16),
    "code host": lambda r: "ghp_" + _pick(r, _MIXED, 30, 36),
    "model key": lambda r: "sk-" + _pick(r, _MIXED, 24, 48),
    "chat bot": lambda r: "xoxb-" + _pick(r, string.digits, 10, 12) + "-" + _pick(r, _MIXED, 20, 24),
    "base64": lambda r: _pick(r, _MIXED + "+/", 28, 60) + "==",
    "signed claims": lambda r: "eyJ" + _pick(r, _MIXED, 20, 40) + "." + _pick(r, _MIXED, 20, 40),
    "map key": lambda r: "AIza" + _pick(r, _MIXED + "-_", 35),
    "forge": lambda r: "glpat-" + _pick(r, _MIXED, 20),
    "bare mixed": lambda r: _pick(r, _MIXED, 24, 44),
}
#: Families of tokens that are no secrets.
OTHERS = {
    "address": lambda r: ".".join(str(r.randrange(256)) for _ in range(4)), "number": lambda r: str(r.randrange(10**6)), "long number": lambda r: _pick(r, string.digits, 12, 19),
    "mail": lambda r: _pick(r, "abcdefgh", 3, 9) + "." + _pick(r, string.digits, 2) + "@mail" + _pick(r, string.digits, 1) + ".example.com",
    "link": lambda r: "https://" + _pick(r, string.ascii_lowercase, 4, 9) + ".org/" + _pick(r, _MIXED, 3, 12), "phone": lambda r: "+" + _pick(r, string.digits, 9, 12),
    "bar": lambda r: "|", "tag": lambda r: "<" + _pick(r, "abdivspan", 1, 5) + ">", "colour": lambda r: "#" + _pick(r, _HEXA, 6),
    "date": lambda r: f"{r.randint(1990, 2030)}-{r.randint(10, 12)}-{r.randint(10, 28)}", "long word": lambda r: _pick(r, "etaoinshrdlu", 14, 28),
    "version": lambda r: "v" + _pick(r, string.digits, 1, 2) + "." + _pick(r, string.digits, 1, 2), "shouting": lambda r: _pick(r, "ETAOINSHR", 6, 22) + "!!",
    "name with number": lambda r: _pick(r, string.ascii_lowercase, 3, 7) + _pick(r, string.digits, 1, 3), "setting": lambda r: _pick(r, string.ascii_lowercase, 2, 8) + "=" + r.choice(("true", "10", "none", "left")),
    "call": lambda r: _pick(r, string.ascii_lowercase, 2, 8) + "();", "uuid": lambda r: r.choice((_uuid(r), _uuid(r).upper())), "commit": lambda r: _pick(r, _HEXA, r.choice((7, 8, 10, 12, 40))),
    "digest": lambda r: r.choice(("sha256:", "md5:", "")) + _pick(r, _HEXA, r.choice((32, 40, 64))), "path": lambda r: "/" + "/".join(_pick(r, string.ascii_lowercase + "_", 2, 9) for _ in range(r.randint(2, 5))) + r.choice((".py", "2.txt", "/v1", "")),
    "hardware": lambda r: ":".join(_pick(r, _HEXA, 2) for _ in range(6)), "instant": lambda r: f"{r.randint(1990, 2030)}-0{r.randint(1, 9)}-{r.randint(10, 28)}T{r.randint(10, 23)}:{r.randint(10, 59)}:{r.randint(10, 59)}Z",
    "order": lambda r: _pick(r, string.ascii_uppercase, 2, 4) + "-" + _pick(r, string.digits, 4, 10), "camel": lambda r: "get" + "".join(_pick(r, "etaoinshrdlu", 4, 8).capitalize() for _ in range(r.randint(1, 3))) + r.choice(("", "2")),
    "snake": lambda r: "_".join(_pick(r, "etaoinshrdlu", 4, 8) for _ in range(r.randint(2, 4))) + r.choice(("", "_v2")), "pointer": lambda r: "0x" + _pick(r, _HEXA, r.choice((8, 12, 16))),
    "file with number": lambda r: _pick(r, "etaoinshrdlu", 4, 9) + _pick(r, string.digits, 2, 8) + r.choice((".jpg", ".csv", ".tar.gz")), "amount": lambda r: "$" + _pick(r, string.digits, 1, 3) + "," + _pick(r, string.digits, 3),
}
#: Families that are never fitted: secrets, and tokens that are none.
UNSEEN = {
    "package host": lambda r: "npm_" + _pick(r, _MIXED, 36), "hub": lambda r: "hf_" + _pick(r, _MIXED, 34), "mail sender": lambda r: "SG." + _pick(r, _MIXED + "-_", 22) + "." + _pick(r, _MIXED + "-_", 43),
    "shop": lambda r: "shppa_" + _pick(r, _MIXED, 32), "index": lambda r: "pypi-AgEI" + _pick(r, _MIXED + "-_", 60), "payment": lambda r: "rk_live_" + _pick(r, _MIXED, 24),
    "messenger": lambda r: _pick(r, string.digits, 9) + ":AA" + _pick(r, _MIXED + "-_", 33), "storage": lambda r: _pick(r, _MIXED + "+/", 86) + "==",
}
UNSEEN_OTHERS = {
    "uuid in braces": lambda r: "{" + _uuid(r) + "}", "urn": lambda r: "urn:uuid:" + _uuid(r), "commit range": lambda r: _pick(r, _HEXA, 7) + ".." + _pick(r, _HEXA, 7), "commit in brackets": lambda r: "(" + _pick(r, _HEXA, 40) + ")",
    "preprint": lambda r: "arXiv:" + _pick(r, string.digits, 4) + "." + _pick(r, string.digits, 5), "coordinates": lambda r: f"{r.uniform(-90, 90):.6f},{r.uniform(-180, 180):.6f}", "book": lambda r: "978-" + "-".join(_pick(r, string.digits, k) for k in (1, 4, 4, 1)),
    "decimal": lambda r: f"{r.random():.17f}", "part": lambda r: _pick(r, string.ascii_uppercase, 3) + _pick(r, string.digits, 4) + _pick(r, string.ascii_uppercase, 1),
}


def _word(rng: random.Random) -> str:
    w = _pick(rng, "etaoinshrdlucmfwypvbgkjqxz", 1, 11)
    w = rng.choice((w, w, w, w.capitalize(), w.upper(), w + rng.choice(".,;:!?"), w + "ßéñü"[rng.randrange(4)]))
    return w + (rng.choice(("!!", "***", "$$$", "&&&", "%%%", "###")) if rng.random() < 0.08 else "")


def login(rng: random.Random, scheme: str) -> str:
    return f"{scheme}://{_pick(rng, string.ascii_lowercase, 3, 8)}:{_pick(rng, _MIXED + '-_!', 6, 20)}@{_pick(rng, string.ascii_lowercase, 3, 8)}.example.com" + rng.choice(("", ":5432", "/db", ":6379/0"))


def _secret(rng: random.Random) -> tuple[list[str], list[int]]:
    body = rng.choice(list(SECRETS.values()))(rng)
    weak = _pick(rng, _MIXED + "-_", 6, 20) if rng.random() < 0.6 else _pick(rng, _HEXA, 16, 64) if rng.random() < 0.5 else body
    quote, name = rng.choice(("", "", '"', "'")), rng.choice(NAMES)
    form = rng.randrange(7)
    if form <= 1:
        return [quote + body + quote + rng.choice(("", ".", ",", ";"))], [BEGIN]
    if form == 2:
        return [name + rng.choice("=:") + quote + weak + quote], [BEGIN]
    if form == 3:
        return [name, rng.choice("=:"), quote + weak + quote], [OUTSIDE, OUTSIDE, BEGIN]
    if form == 4:
        return [name, rng.choice(("is", "was")), _mixed_word(rng, quote)], [OUTSIDE, OUTSIDE, BEGIN]
    if form == 5:
        return [login(rng, rng.choice(("postgres", "https", "redis", "ftp")))], [BEGIN]
    parts = [body[k : k + 24] for k in range(0, len(body), 24)]
    return [name + ":", *parts], [OUTSIDE, BEGIN] + [INSIDE] * (len(parts) - 1)


def _mixed_word(rng: random.Random, quote: str = "") -> str:
    """Six or more random characters, letters and digits among them."""
    w = list(_pick(rng, _MIXED, 6, 20))
    w[0], w[-1] = rng.choice(string.digits), rng.choice(string.ascii_letters)
    rng.shuffle(w)
    return quote + "".join(w) + quote


def _generated(rng: random.Random) -> tuple[list[str], list[int]]:
    """One sentence of tokens and tags; some sentences are lists of look-alikes or code."""
    tokens, tags = [], []
    listing = rng.random() < 0.15
    family = rng.choice(list(OTHERS.values()))
    for _ in range(rng.randint(4, 20)):
        r = rng.random()
        if r < 0.1 and not listing:
            a, b = _secret(rng)
        elif r < 0.2:
            # the name of a secret without one after it
            a = [rng.choice(NAMES) + rng.choice(("", "", ":", ",", "s")), *rng.choice(([], ["is"], ["was"], ["="]))]
            a.append(_word(rng) if rng.random() < 0.8 else rng.choice(("true", "none", "10", "null;", "required")))
            b = [OUTSIDE] * len(a)
        elif listing or r < 0.5:
            a = [rng.choice(("", "", "(", '"')) + (family if listing else rng.choice(list(OTHERS.values())))(rng) + rng.choice(("", "", ",", ".", ")"))]
            b = [OUTSIDE]
        else:
            a, b = [_word(rng)], [OUTSIDE]
        tokens += a
        tags += b
    return tokens, tags


def likelihood(x: np.ndarray, y: np.ndarray, inside: np.ndarray, w: np.ndarray, pair: np.ndarray):
    """Log-likelihood of padded chains (sentences, places, features) with tags ``y``, and its gradients by weights and pairs.

    Forward and backward sums; places where ``inside`` is false take no part.
    """
    n, long = y.shape
    gold = np.eye(3)[y] * inside[:, :, None]
    emit = (x.reshape(-1, x.shape[2]) @ w).reshape(n, long, 3)
    alpha, beta = np.zeros((n, long, 3)), np.zeros((n, long, 3))
    alpha[:, 0] = emit[:, 0] + pair[3]
    for k in range(1, long):
        step = np.logaddexp.reduce(alpha[:, k - 1, :, None] + pair[:3], axis=1) + emit[:, k]
        alpha[:, k] = np.where(inside[:, k, None], step, alpha[:, k - 1])
    for k in range(long - 2, -1, -1):
        step = np.logaddexp.reduce(pair[:3] + (emit[:, k + 1] + beta[:, k + 1])[:, None, :], axis=2)
        beta[:, k] = np.where(inside[:, k + 1, None], step, 0)
    z = np.logaddexp.reduce(alpha[:, -1], axis=1)
    p = np.exp(alpha + beta - z[:, None, None]) * inside[:, :, None]
    both = alpha[:, :-1, :, None] + pair[:3] + (emit[:, 1:] + beta[:, 1:])[:, :, None, :] - z[:, None, None, None]
    p_pair = (np.exp(both) * inside[:, 1:, None, None]).sum(axis=(0, 1))
    gold_pair = np.einsum("sia,sib->ab", gold[:, :-1], gold[:, 1:])
    score = (gold * emit).sum() + (gold_pair * pair[:3]).sum() + (gold[:, 0] @ pair[3]).sum()
    d = x.reshape(-1, x.shape[2]).T @ (gold - p).reshape(-1, 3)
    return float(score - z.sum()), d, np.vstack([gold_pair - p_pair, (gold[:, 0] - p[:, 0]).sum(axis=0)[None]])


def chain_features(tokens: list[str]) -> np.ndarray:
    """(places, features) of one chain, in the order own, before, second before, after, file."""
    own, sides = [own_features(t) for t in tokens], [side_features(t) for t in tokens]
    x = np.zeros((len(tokens), N_OWN + 3 * N_SIDE + N_FILE))
    marks = np.sum([file_marks(t, o) for t, o in zip(tokens, own, strict=True)], axis=0)
    x[:, N_OWN + 3 * N_SIDE :] = file_features(marks[None], np.array([len(tokens)]))
    for k in range(len(tokens)):
        x[k, list(own[k])] = 1
        for place, at in enumerate((k - 1, k - 2, k + 1)):
            if 0 <= at < len(tokens):
                x[k, [N_OWN + place * N_SIDE + f for f in sides[at]]] = 1
    return x


@functools.cache
def fit(sentences: int = 2000, passes: int = 80, rate: float = 0.3, seed: int = 5) -> Field:
    """Adaptive gradient ascent on the regularised log-likelihood."""
    rng = random.Random(seed)
    data = [_generated(rng) for _ in range(sentences)]
    long, sizes = max(len(t) for t, _ in data), (N_OWN, N_SIDE, N_SIDE, N_SIDE, N_FILE)
    x = np.zeros((sentences, long, sum(sizes)), np.float32)
    y, inside = np.full((sentences, long), OUTSIDE), np.zeros((sentences, long), bool)
    for s, (tokens, tags) in enumerate(data):
        x[s, : len(tags)] = chain_features(tokens)
        y[s, : len(tags)], inside[s, : len(tags)] = tags, True
    w, pair = np.zeros((sum(sizes), 3)), np.zeros((4, 3))
    gw, gp = np.full(w.shape, 1e-6), np.full(pair.shape, 1e-6)
    for _ in range(passes):
        _, d, dp = likelihood(x, y, inside, w, pair)
        d, dp = d - 0.5 * w, dp - 0.5 * pair
        gw += d**2
        gp += dp**2
        w += rate * d / np.sqrt(gw)
        pair += rate * dp / np.sqrt(gp)
    cut = np.cumsum((0, *sizes))
    return Field(*(w[a:b] for a, b in zip(cut[:-1], cut[1:], strict=True)), pair)


def found_shares(field: Field, families: dict, n: int = 200, seed: int = 99) -> dict[str, float]:
    """Of ``n`` sentences of words around one token of a family, the share in which the field tags that token."""
    out = {}
    for name, make in families.items():
        rng, hits = random.Random(f"{seed} {name}"), 0
        for _ in range(n):
            before = [_pick(rng, "etaoinshrdlucm", 2, 9) for _ in range(rng.randint(3, 12))]
            made = make(rng)
            text = " ".join([*before, made, *[_pick(rng, "etaoinshrdlucm", 2, 9) for _ in range(rng.randint(3, 12))]])
            lo = len(" ".join(before))
            hits += any(a < lo + 1 + len(made) and lo < b for a, b in field_spans(field, [text])[0])
        out[name] = hits / n
    return out


# scanning ------------------------------------------------------------------------------------------------------


class _Types(dict):
    """Numbers the distinct tokens (bytes) and describes each once; tokens with the same features share a kind."""

    def __init__(self):
        super().__init__()
        self.own, self.side, self.marks = array("l"), array("l"), array("b")
        self.own_kinds, self.side_kinds = {}, {}

    def __missing__(self, word):
        token = word.decode()
        own, side = own_features(token), side_features(token)
        self.own.append(self.own_kinds.setdefault(own, len(self.own_kinds)))
        self.side.append(self.side_kinds.setdefault(side, len(self.side_kinds)))
        self.marks.extend(file_marks(token, own))
        self[word] = code = len(self)
        return code


def field_spans(field: Field, texts: list[str], types: _Types | None = None) -> list[list[tuple[int, int]]]:
    """(start, end) of the spans tagged in each text. ``types`` may be carried from call to call."""
    types = _Types() if types is None else types
    out: list[list[tuple[int, int]]] = []
    lo = 0
    while lo < len(texts):
        codes, sizes, hi = [], [], lo
        while hi < len(texts) and (hi == lo or len(codes) < STEP):
            words = texts[hi].encode().split()  # bytes.split knows ASCII white space only
            codes += map(types.__getitem__, words)
            sizes.append(len(words))
            hi += 1
        emit, ends, starts = chain_scores(field, types, np.array(codes, np.int64), np.array(sizes))
        tags = field.tags(emit, starts)
        hit = np.concatenate(([0], np.cumsum(tags != OUTSIDE)))
        for k, n in enumerate(sizes):
            a, b = int(ends[k]) - n, int(ends[k])
            out.append(_spans(texts[lo + k], tags[a:b]) if hit[b] > hit[a] else [])
        lo = hi
    return out


def chain_scores(field: Field, types: _Types, code: np.ndarray, sizes: np.ndarray):
    """Scores (n, 3) of the tokens of texts laid end to end, the texts' ends, and where non-empty texts start."""
    own, before, second, after = field.tables(types)
    ends = np.cumsum(sizes)
    starts = (ends - sizes)[sizes > 0]
    marks = np.array(types.marks, np.int64).reshape(-1, 3)[code].cumsum(axis=0)
    marks = np.vstack([np.zeros((1, 3), np.int64), marks])
    file = file_features(marks[ends] - marks[ends - sizes], sizes) @ field.file
    emit = own[code] + np.repeat(file, sizes, axis=0)
    place = np.arange(len(code)) - np.repeat(ends - sizes, sizes)
    inner = np.flatnonzero(place > 0)
    emit[inner] += before[code[inner - 1]]
    emit[inner - 1] += after[code[inner]]
    inner = np.flatnonzero(place > 1)
    emit[inner] += second[code[inner - 2]]
    return emit, ends, starts


def _spans(text: str, tags: np.ndarray) -> list[tuple[int, int]]:
    spans, open_ = [], False
    for m, tag in zip(_TOKEN.finditer(text), tags.tolist(), strict=True):
        if tag == OUTSIDE:
            open_ = False
            continue
        core = _LOGIN.search(m[0]) or _CORE.match(m[0])
        start, end = m.start() + core.start(1), m.start() + core.end(1)
        if tag == INSIDE and open_:
            spans[-1] = (spans[-1][0], end)
        elif end > start:
            spans.append((start, end))
            open_ = True
    return spans


def _written(spans) -> str:
    return ",".join(f"{KINDS[kind]}:{a}:{b}" for a, kind, b in spans)


def scan(field: Field, texts: list[str], types: _Types | None = None):
    """For each text: base spans, and all spans, as sorted (start, kind, end)."""
    for text, more in zip(texts, field_spans(field, texts, types), strict=True):
        base = base_spans(text)
        yield base, sorted(base + [(a, 3, b) for a, b in more if all(b <= s or e <= a for s, _, e in base)])


def secret_report(docs: DataFrame) -> DataFrame:
    sent = docs.sparkSession.sparkContext.broadcast(fit())

    def run(batches):
        types = _Types()
        for b in batches:
            types = types if len(types) < MAX_TYPES else _Types()
            rows = [([sum(k == n for _, k, _ in base) for n in range(3)], hashlib.sha256(_written(base).encode()).hexdigest(), _written(every)) for base, every in scan(sent.value, [t or "" for t in b.column(1).to_pylist()], types)]
            counts = [pa.array([r[0][n] for r in rows], pa.int64()) for n in range(3)]
            yield pa.RecordBatch.from_arrays([b.column(0), *counts, pa.array([r[1] for r in rows], pa.string()), pa.array([r[2] for r in rows], pa.string())], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(lean(run), "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
