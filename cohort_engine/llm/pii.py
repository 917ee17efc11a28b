"""Personal data by weak supervision.

Four kinds are found by fixed patterns and checks (e-mail, IP, card, phone) and always stand.
Further spans (credentials, pass phrases, bank, account and social-security numbers, names and addresses) come from a model. Candidates of
five types are read off a text; regex, gazetteer and context labelers each vote for, against or not at all; for each type expectation
maximisation estimates from the votes alone how often each labeler votes which way on true and on false candidates; the resulting
probabilities train a final span classifier on features of the span and its surroundings, and that one
decides. What a labeler is taken to do before any data weighs as much as ``PSEUDO`` candidates, however many there are. Votes and
features take few values, so what the model learns from is counted over
all candidates of all texts and still is a small table, whatever the input.

All patterns run in time linear in the text.

Defined results: null and empty texts have no spans; without candidates the model adds none; repeated rows get equal
spans; a span of the model never overlaps a base span or another of its own; empty tables give empty ones; other columns are not read by
:func:`find`, and pass through :func:`redact`.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_right
from collections import Counter
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import add_columns, map_columns

BASE_KINDS = ("email", "ip", "card", "phone")
MODEL_KINDS = ("secret", "iban", "ssn", "account", "name", "address")

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# a match that starts within a run of digits could also start where the run does
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")
_TOKEN = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789_-")
_TOKEN_RUN = re.compile(r"[A-Za-z0-9_-]*")

Span = tuple[str, int, int]


def _emails(text: str) -> list[Span]:
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at)):
            out.append(("email", start, m.end()))
            free = m.end()
        at = text.find("@", max(at + 1, free))
    return out


def luhn(digits: str) -> bool:
    values = [int(d) for d in reversed(digits)]
    return (sum(values[::2]) + sum(sum(divmod(2 * v, 10)) for v in values[1::2])) % 10 == 0


def base_spans(text: str | None) -> list[Span]:
    """The four fixed kinds, by kind and then start."""
    if not text:
        return []
    out = _emails(text) if "@" in text else []
    if not _DIGIT.search(text):
        return out
    if "." in text:
        out += [("ip", m.start(), m.end()) for m in _IP.finditer(text) if all(len(q := p.lstrip("0")) <= 3 and int(q or 0) <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 16 <= len(digits) <= 19 and luhn(digits):
            out.append(("card", m.start(), m.end()))
    if "+" in text:
        out += [("phone", m.start(), m.end()) for m in _PHONE.finditer(text) if 8 <= sum(c.isdigit() for c in m[0]) <= 15]
    return out


# Words that announce a credential or number, shapes of well-known keys, first names, titles and kinds of streets.
GAZETTEER = ("password", "passwd", "passwort", "contraseña", "pwd", "passphrase", "token", "secret", "api key", "api_key", "apikey", "access key", "private key", "credential", "bearer", "iban", "ssn", "social security", "account number", "passport")
_NUMBER_WORDS = ("iban", "account", "acct", "konto", "kontonummer", "routing", "sort code", "cuenta", "compte", "bank", "ssn", "social security", "passport", "tax id", "swift", "bic")
_SECRET = r"passwords?|passwd|passwort|kennwort|contraseña|mot de passe|pwd|pass[ -]?phrase|passcode|pin(?: code)?|secret|token|api[ _-]?key|access[ _-]?key|credentials?"
_KEY_SHAPE = re.compile(r"(?:AKIA|ASIA)[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{30,}|sk-[A-Za-z0-9-]{20,}|xox[abp]-[A-Za-z0-9-]{10,}|AIza[A-Za-z0-9_-]{30,}")
FIRST_NAMES = frozenset(
    "james john robert michael william david richard joseph thomas charles daniel matthew anthony mark steven paul andrew kenneth george kevin brian edward peter henry mary patricia jennifer linda elizabeth barbara susan"
    " jessica sarah karen nancy lisa margaret sandra emily anna emma laura maria julia alice helen hans klaus jürgen wolfgang dieter günter stefan uwe heinrich monika ursula petra sabine renate helga ingrid heike juan josé"
    " carlos luis miguel pedro antonio manuel francisco javier carmen josefa isabel dolores pilar teresa ana lucía jean pierre michel andré philippe jacques bernard françois nicolas marie nathalie isabelle sylvie catherine"
    " martine françoise valérie sophie claire".split()
)
_TITLE = r"Mr|Mrs|Ms|Miss|Dr|Prof|Herr|Frau|Señor|Señora|Sr|Sra|Mme|Monsieur|Madame"
_STREET = r"Street|St|Avenue|Ave|Road|Rd|Lane|Ln|Drive|Boulevard|Blvd|Court|Square|Terrace|Way"
_WAY = r"straße|strasse|str\.|weg|platz|gasse|allee"
_VIA = r"Calle|Avenida|Plaza|Rue|Avenue|Boulevard|Place"

_IBAN = re.compile(r"[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}")
_GROUPED_IBAN = re.compile(r"[A-Z](?<![A-Za-z0-9][A-Z])[A-Z][0-9]{2}(?: [A-Z0-9]{4}){2,7}(?: [A-Z0-9]{1,3})?(?![A-Za-z0-9])")
_GROUPED_DIGITS = re.compile(r"(?<![A-Za-z0-9+.,-])[0-9]{2,6}(?:[ -][0-9]{2,6}){1,6}(?![A-Za-z0-9.,-]*[0-9])")
_SSN = re.compile(r"[0-9]{3}-[0-9]{2}-[0-9]{4}")
_DATE = re.compile(r"[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{2}-[0-9]{2}-[0-9]{4}")
_HEX = re.compile(r"[0-9a-f]{16,}|[0-9A-F]{16,}")
_ASSIGNED = re.compile(r"[=:]\s?[\"'“]?$")
_PHRASE = re.compile(rf"(?i)(?<![A-Za-z])(?:{_SECRET})(?![A-Za-z])[\"']?(\s{{0,2}}[=:]\s{{0,2}}|\s(?:is|was|ist|lautet|es|est)\s)(?:([\"'“])([^\"'”\n]{{3,200}})[\"'”]|(\S{{3,200}}))")
_PLACEHOLDER = re.compile(r"(?i)[*x.<\[{].*|none|null|required|reset|your.*|the|a|an|not|wrong|incorrect|valid|invalid|expired|missing|protected|empty|changed|needed|optional|true|false|string|text|to|in|only|also|very|too")
_CAP = r"[A-ZÀ-ÖØ-Þ][a-zß-öø-ÿ'’-]{1,30}"
_NAME = re.compile(rf"(?<!\w)(?:(?:(?P<title>{_TITLE})\.?[ ])|(?P<intro>(?:[Mm]y name is|[Nn]ame ?:|[Ii]ch heiße|[Mm]e llamo|[Jj]e m.appelle|[Ss]igned(?: by)?:?|[Cc]ontact ?:|[Pp]atient ?:)[ ]))?(?P<name>(?P<first>{_CAP})(?: [A-Z]\.)?(?: {_CAP}){{0,2}})")
_PLACE = re.compile(rf"(?<![\w.,-])[0-9]{{1,5}}[a-z]? (?:{_CAP} ){{1,3}}(?:{_STREET})(?!\w)\.?|(?<!\w)(?:{_CAP}(?:{_WAY})|{_CAP} (?:Straße|Strasse|Weg|Platz|Allee)|(?:{_VIA}) (?:d[eu]l? |des |la )?{_CAP}(?: {_CAP})?),? [0-9]{{1,4}}[a-z]?(?!\w)")
_WHOLE_KEY = re.compile(rf"(?<![A-Za-z0-9_-])(?:{_KEY_SHAPE.pattern})(?![A-Za-z0-9_-])")
_KEY_HINTS = ("AKIA", "ASIA", "gho_", "ghp_", "ghr_", "ghs_", "ghu_", "sk-", "xoxa-", "xoxb-", "xoxp-", "AIza")
#: A text without any of these has no phrase, place or announced name.
_SECRET_HINTS = ("pass", "kennwort", "contraseña", "mot de", "pwd", "pin", "secret", "token", "key", "credential")
_PLACE_HINTS = (*(f" {w}" for w in _STREET.split("|")), "stra", "str.", "weg ", "weg,", "platz", "gasse", "allee", " Weg", " Platz", " Allee", "Calle", "Avenida", "Plaza", "Rue ", "Avenue", "Boulevard", "Place")
_NAME_HINTS = (*(w + end for w in _TITLE.split("|") for end in (" ", ". ")), "ame is ", "ame: ", "ame : ", "ch heiße ", "e llamo ", "appelle ", "igned ", "igned: ", "ontact: ", "ontact : ", "atient: ", "atient : ")
_PAIRS = re.compile(r"([A-ZÀ-ÖØ-Þ][a-zß-öø-ÿ]+) [A-ZÀ-ÖØ-Þ]")
_POSTCODE = re.compile(r",? (?:[0-9]{4,5}|[A-Z]{1,2}[0-9]{1,2}[A-Z]? [0-9][A-Z]{2}|[A-Z]{2} [0-9]{5})(?![0-9])")
_AT_HOME = re.compile(r"(?i)(?:address|lives? (?:at|in)|living at|ship to|deliver(?:ed)? to|reside[sd]? (?:at|in)|wohnt|wohnhaft|anschrift|adresse|vive en|dirección|habite)[^.]{0,20}$")
_NOT_NAMES = frozenset("monday tuesday wednesday thursday friday saturday sunday january february march april may june july august september october november december the this that there when what where der die das el la los les une".split())
SHORTEST = 10

#: A candidate: its type, and where it is.
Candidate = tuple[str, int, int]


def _iban_ok(token: str) -> bool:
    return bool(_IBAN.fullmatch(token)) and int("".join(str(int(c, 36)) for c in token[4:] + token[:4])) % 97 == 1


class _Taken:
    """Spans that nothing may overlap."""

    def __init__(self, spans: list[tuple[int, int]]) -> None:
        self.starts, self.ends = [], []
        for a, b in sorted(spans):
            if self.ends and a < self.ends[-1]:
                self.ends[-1] = max(self.ends[-1], b)
            else:
                self.starts.append(a)
                self.ends.append(b)

    def free(self, a: int, b: int) -> bool:
        k = bisect_right(self.starts, a)
        return not (k and self.ends[k - 1] > a) and not (k < len(self.starts) and self.starts[k] < b)


def _tokens(text: str) -> list[tuple[int, int]]:
    """Runs of ``SHORTEST`` or more letters, digits, underscores and hyphens with a digit."""
    out, free = [], 0
    m = _DIGIT.search(text)
    while m:
        start = m.start()
        while start > free and text[start - 1] in _TOKEN:
            start -= 1
        free = end = _TOKEN_RUN.match(text, m.start()).end()
        if end - start >= SHORTEST:
            out.append((start, end))
        m = _DIGIT.search(text, end)
    return out


def _phrases(text: str) -> list[tuple[int, int]]:
    """What stands after a word for a secret and an equals sign, colon or "is", whatever it looks like."""
    out = []
    for m in _PHRASE.finditer(text):
        a, b = m.span(3) if m[3] else m.span(4)
        while not m[3] and b > a and text[b - 1] in ".,;:!?)\"'":
            b -= 1
        if b - a >= 3:
            out.append((a, b))
    return out


def candidates(text: str, base: list[Span]) -> list[Candidate]:
    """Candidates of all types that don't overlap base spans or each other, in order; of two that overlap the first type by order stands."""
    digits, low = bool(_DIGIT.search(text)), text.lower()
    found: list[Candidate] = []
    if digits:
        for m in _GROUPED_IBAN.finditer(text):
            # a group that only follows the number is left off
            ends = [m.end(), *(m.start() + k.start() for k in re.finditer(" ", m[0]))]
            good = next((e for e in sorted(ends, reverse=True) if _iban_ok(text[m.start() : e].replace(" ", ""))), m.end())
            found.append(("number", m.start(), good))
        found += [("token", a, b) for a, b in _tokens(text)]
        if any(w in low for w in _NUMBER_WORDS):
            found += [("number", m.start(), m.end()) for m in _GROUPED_DIGITS.finditer(text) if any(w in text[max(0, m.start() - 32) : m.start()].lower() for w in _NUMBER_WORDS)]
        if any(w in text for w in _PLACE_HINTS):
            found += [("address", m.start(), m.end()) for m in _PLACE.finditer(text)]
    if any(w in text for w in _KEY_HINTS):  # keys of a known format need no digit
        found += [("token", *m.span()) for m in _WHOLE_KEY.finditer(text)]
    if any(w in low for w in _SECRET_HINTS):
        found += [("phrase", a, b) for a, b in _phrases(text)]
    named = any(w in text for w in _NAME_HINTS) or any(w.lower() in FIRST_NAMES for w in set(_PAIRS.findall(text)))
    for m in _NAME.finditer(text) if named else ():
        if m["title"] or m["intro"] or (m["first"].lower() in FIRST_NAMES and " " in m["name"]):
            found.append(("name", *m.span("name")))
    if not found:
        return []
    taken = [(a, b) for _, a, b in base]
    out: list[Candidate] = []
    for kind in TYPES:
        blocked = _Taken(taken)
        end = 0
        for t, a, b in sorted((c for c in found if c[0] == kind), key=lambda c: (c[1], -c[2])):
            if a >= end and blocked.free(a, b):
                out.append((t, a, b))
                taken.append((a, b))
                end = b
    return sorted(out, key=lambda c: c[1])


def _bucket(x: float, bounds: tuple[float, ...]) -> int:
    return sum(x >= b for b in bounds)


def observe(text: str, kind: str, start: int, end: int) -> tuple[str, str]:
    """The votes of the type's labelers (``+``, ``-`` or ``0`` each) and the features of a candidate, a digit each."""
    token, before = text[start:end], text[max(0, start - 32) : start]
    low = before.lower()
    n = len(token)
    digits, upper = sum(c.isdigit() for c in token), sum(c.isupper() for c in token)
    assigned = bool(_ASSIGNED.search(before))
    if kind == "token":
        turns = sum(a.isdigit() and b.isalpha() or a.isalpha() and b.isdigit() for a, b in zip(token, token[1:], strict=False))
        variety = len(set(token)) / min(n, 16)
        named = any(g in low for g in GAZETTEER)
        known = bool(_KEY_SHAPE.fullmatch(token) or _SSN.fullmatch(token)) or _iban_ok(token)
        hexadecimal = bool(_HEX.fullmatch(token)) and 0 < digits < n
        dull = digits == n or bool(_DATE.fullmatch(token))
        votes = (
            int(known),  # regex: known keys and numbers
            1 if hexadecimal else -1 if dull else 0,  # regex: hexadecimal strings against plain numbers and dates
            int(named),  # gazetteer
            int(assigned),  # context: assignment
            1 if turns >= 4 else -1 if turns <= 1 else 0,  # context: mixture of letters and digits
            1 if variety >= 0.5 and digits and any(map(str.isalpha, token)) else -1 if variety < 0.3 else 0,  # context: variety of characters
        )
        features = (_bucket(n, (12, 16, 20, 32)), _bucket(digits / n, (0.1, 0.3, 0.6, 1.0)), _bucket(upper / n, (0.05, 0.4)), _bucket(turns, (2, 4, 8)), int(named), int(assigned), int(known))
    elif kind == "number":
        flat = token.replace(" ", "").replace("-", "")
        letters = flat[:1].isalpha()
        sound, named = _iban_ok(flat) or bool(_SSN.fullmatch(token)), any(w in low for w in _NUMBER_WORDS)
        votes = (1 if sound else -1 if letters else 0, int(named), int(assigned), -1 if _DATE.fullmatch(token) or len(flat) < 6 else int(10 <= len(flat) <= 18))
        features = (int(sound), int(letters), int(named), int(assigned), _bucket(len(flat), (6, 9, 13, 18)))
    elif kind == "phrase":
        blank = bool(_PLACEHOLDER.fullmatch(token))
        kinds = (digits > 0) + (upper > 0) + any(c.islower() for c in token) + any(not c.isalnum() and not c.isspace() for c in token)
        quoted, signed = text[start - 1 : start] in ("\"", "'", "“"), any(c in before[-6:] for c in "=:")
        named = bool(re.search(r"(?i)(?:pass|pwd|kennwort|contraseña|pin)[^=:]*[=:]?\W*$|pass\w* (?:is|was|ist|lautet|es|est) \W?$", before))
        votes = (int(named), int(signed), 1 if kinds >= 3 or digits else -1 if token.islower() and not signed else 0, -1 if blank else 0, int(quoted))
        features = (int(signed), kinds, int(blank), int(quoted), int(digits > 0), _bucket(n, (5, 8, 16)))
    elif kind == "name":
        words = token.split()
        m = re.search(rf"(?:(?<!\w)(?:{_TITLE})\.?|(is|:|heiße|llamo|appelle|[Ss]igned|by)) $", before)
        title, intro = bool(m and not m[1]), bool(m and m[1])
        first, dull = words[0].lower() in FIRST_NAMES, any(w.lower() in _NOT_NAMES for w in words)
        votes = (int(title), int(first), int(intro), -1 if dull else 0, 1 if len(words) > 1 else 0)
        features = (int(title), int(first), int(intro), int(dull), min(len(words), 3))
    else:
        post, home = bool(_POSTCODE.match(text, end)), bool(_AT_HOME.search(before))
        words = sum(w[:1].isupper() for w in token.split())
        votes = (int(post), int(home), 1 if words <= 3 else 0)
        features = (int(post), int(home), min(words, 4))
    return "".join("0+-"[v] for v in votes), "".join(map(str, features))


#: For each type what share of candidates is taken to be true before any is seen, how often each labeler's votes are taken to be right, and
#: how many values each feature has. The order is that in which overlaps are settled. The first labeler of the first two types knows
#: formats and checksums, so its vote alone can make a span; otherwise two have to vote for one.
TYPES: dict[str, tuple[float, tuple[float, ...], tuple[int, ...]]] = {
    "number": (0.2, (0.99, 0.75, 0.65, 0.9), (2, 2, 2, 2, 5)),
    "token": (0.1, (0.99, 0.85, 0.8, 0.75, 0.7, 0.65), (5, 5, 3, 4, 2, 2, 2)),
    "phrase": (0.3, (0.75, 0.75, 0.75, 0.95, 0.7), (2, 5, 2, 2, 2, 4)),
    "address": (0.4, (0.9, 0.9, 0.7), (2, 2, 5)),
    "name": (0.4, (0.85, 0.9, 0.8, 0.95, 0.65), (2, 2, 2, 2, 4)),
}
#: How many candidates' worth those beliefs weigh, whatever there is.
PSEUDO = 10.0


def _one_hot(features: list[str], levels: tuple[int, ...]) -> np.ndarray:
    return np.array([[1.0, *(float(int(f[k]) == v) for k, n in enumerate(levels) for v in range(n))] for f in features])


def estimate(votes: np.ndarray, weight: np.ndarray, share: float, beliefs: tuple[float, ...], rounds: int = 500) -> tuple[float, np.ndarray, np.ndarray]:
    """Expectation maximisation over ``votes[pattern, labeler]`` of 1, -1 and 0, each pattern seen ``weight`` times: the share of
    true candidates, how often each labeler's votes are right, and each pattern's probability to be true. A labeler that doesn't
    vote says nothing. ``share`` and ``beliefs`` count as ``PSEUDO`` candidates; nothing else holds the estimates."""
    belief = np.array(beliefs)
    chance, right = share, belief
    cast = weight @ (votes != 0)
    true = np.full(len(votes), -1.0)
    for _ in range(rounds):
        odds = np.log(chance / (1 - chance)) + votes @ np.log(right / (1 - right))
        now = 1 / (1 + np.exp(-np.clip(odds, -500, 500)))
        if np.abs(now - true).max(initial=0) < 1e-10:
            break
        true = now
        agree = weight @ np.where(votes > 0, true[:, None], np.where(votes < 0, 1 - true[:, None], 0))
        right = np.clip((agree + PSEUDO * belief) / (cast + PSEUDO), 1e-6, 1 - 1e-6)
        chance = float(np.clip((weight @ true + PSEUDO * share) / (weight.sum() + PSEUDO), 1e-6, 1 - 1e-6))
    return chance, right, true


def supported(kind: str, votes: str) -> bool:
    """Whether enough labelers vote for a candidate that the classifier may take it."""
    return votes.count("+") >= 2 or (kind in ("number", "token") and votes[0] == "+")


@dataclass(frozen=True)
class SpanModel:
    """For each type the ``share`` of true candidates, how often its labelers are ``right`` and the ``weights`` of its classifier."""

    share: dict[str, float]
    right: dict[str, np.ndarray]
    weights: dict[str, np.ndarray]

    @staticmethod
    def fit(counts: dict[tuple[str, str, str], int]) -> SpanModel:
        """``counts`` of candidates by type, votes and features."""
        share, right, weights = {}, {}, {}
        for kind, (prior, beliefs, levels) in TYPES.items():
            keys = sorted(k for k in counts if k[0] == kind)
            if not keys:
                continue
            weight = np.array([counts[k] for k in keys], float)
            votes = np.array([[{"0": 0, "+": 1, "-": -1}[c] for c in v] for _, v, _ in keys])
            share[kind], right[kind], true = estimate(votes, weight, prior, beliefs)
            true = true * np.array([supported(k, v) for k, v, _ in keys])
            weights[kind] = _classifier(_one_hot([f for *_, f in keys], levels), weight, true)
        return SpanModel(share, right, weights)

    def accepts(self, kind: str, votes: str, features: str) -> bool:
        w = self.weights.get(kind)
        return w is not None and supported(kind, votes) and bool((_one_hot([features], TYPES[kind][2]) @ w)[0] >= 0)


def _classifier(x: np.ndarray, weight: np.ndarray, true: np.ndarray, steps: int = 400) -> np.ndarray:
    """Logistic regression on soft labels, by Newton steps."""
    w, share = np.zeros(x.shape[1]), weight / weight.sum()
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        slope = x.T @ (share * (p - true)) + 1e-4 * w
        bend = (x * (share * p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(len(w))
        step = np.linalg.solve(bend, slope)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


def _kind(kind: str, token: str) -> str:
    if kind == "number":
        return "ssn" if _SSN.fullmatch(token) else "iban" if _iban_ok(token.replace(" ", "")) else "account"
    if kind == "token":
        return "ssn" if _SSN.fullmatch(token) else "iban" if _iban_ok(token) else "secret"
    return "secret" if kind == "phrase" else kind


def spans(text: str | None, model: SpanModel, known: dict[tuple[str, str, str], bool] | None = None) -> tuple[list[Span], list[Span]]:
    """Base spans, and all spans; each by kind and then start. ``known`` keeps decisions, of which there are few."""
    base = base_spans(text)
    if not text:
        return base, base
    known = {} if known is None else known
    more = []
    for kind, a, b in candidates(text, base):
        key = kind, *observe(text, kind, a, b)
        if key not in known:
            known[key] = model.accepts(*key)
        if known[key]:
            more.append((_kind(kind, text[a:b]), a, b))
    order = {k: i for i, k in enumerate((*BASE_KINDS, *MODEL_KINDS))}
    return base, base + sorted(more, key=lambda s: (order[s[0]], s[1]))


def written(found: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in found)


def train(docs: DataFrame, text_col: str = "text") -> SpanModel:
    """One pass over all texts; votes and features are counted in each batch, then by Spark."""

    def run(c: dict[str, list]) -> dict[str, list]:
        seen: Counter = Counter()
        for text in c["text"]:
            if text:
                seen.update((kind, *observe(text, kind, a, b)) for kind, a, b in candidates(text, base_spans(text)))
        return {"type": [k[0] for k in seen], "votes": [k[1] for k in seen], "features": [k[2] for k in seen], "n": list(seen.values())}

    counted = map_columns(docs.select(F.col(text_col).alias("text")), run, "type string, votes string, features string, n bigint")
    rows = counted.groupBy("type", "votes", "features").agg(F.sum("n").alias("n")).collect()  # bounded by what votes and features can be, whatever the input
    return SpanModel.fit({(r["type"], r["votes"], r["features"]): r["n"] for r in rows})


def find(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", model: SpanModel | None = None) -> DataFrame:
    """A row for each document: ``id_col, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_model``."""
    model = model or train(docs, text_col)
    known: dict[tuple[str, str, str], bool] = {}

    def run(c: dict[str, list]) -> dict[str, list]:
        out: dict[str, list] = {n: [] for n in ("n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_model")}
        for text in c["text"]:
            base, every = spans(text, model, known)
            kinds = Counter(k for k, _, _ in base)
            for k in BASE_KINDS:
                out[f"n_{k}"].append(kinds[k])
            out["base_sha256"].append(hashlib.sha256(written(base).encode()).hexdigest())
            out["spans"].append(written(every))
            out["n_model"].append(len(every) - len(base))
        return {"id": c["id"]} | out

    narrow = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    return map_columns(narrow, run, "id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string, n_model bigint").withColumnRenamed("id", id_col)


def masked(text: str | None, found: list[Span]) -> str | None:
    """The text with each span replaced by its kind in angle brackets; of overlapping spans the first, then the longest stands."""
    if not text or not found:
        return text
    out, at = [], 0
    for kind, a, b in sorted(found, key=lambda s: (s[1], -s[2])):
        if a >= at:
            out += [text[at:a], f"<{kind.upper()}>"]
            at = b
        elif b > at:
            at = b
    return "".join(out) + text[at:]


def redact(docs: DataFrame, text_col: str = "text", model: SpanModel | None = None, length_col: str | None = None) -> DataFrame:
    """``docs`` with every span masked; ``length_col`` gets the new length. No shuffle of texts."""
    model = model or train(docs, text_col)
    known: dict[tuple[str, str, str], bool] = {}

    def run(c: dict[str, list]) -> dict[str, list]:
        return {text_col: [masked(t, spans(t, model, known)[1]) for t in c[text_col]]}

    out = add_columns(docs, [text_col], run, f"`{text_col}` string")
    return out.withColumn(length_col, F.length(text_col).cast(docs.schema[length_col].dataType)) if length_col else out
