"""Secret scans: candidates by their shape, false positives removed by a random forest trained from labelled findings."""

from __future__ import annotations

import math
import random
import re
from collections.abc import Iterable
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .boosting import Trees, forest
from .common import by_text, ship

#: Common words and endings of four languages, which every lexicon holds beside what it learns.
WORDS = (
    "the and for that with this from have they will would there their what about which when make like time just know take into year your good some "
    "could them other than then look only come over think also back after work first well even want because these give most number name value user "
    "token secret access public private key password config system service data test example sample value string file path image version release "
    "ation ting able ment tion ness ical ence ance ing the ers ion ent her ter hat tha ere ate his con res ver all ons nce men ith ted ers pro thi wit "
    "les des une est que pour dans avec sur pas ment tion elle aux der die und ein den von mit ist auf fur ung lich keit heit schen verei "
    "los las una con para por del que cion mente ado dora aba este como pero mas"
).split()
VENDOR = re.compile(r"AKIA|ASIA|gh[opusr]_|github_pat_|glpat-|xox[abprs]-|[sr]k_(?:live|test)_|sk-|AIza|eyJ")
#: Keys that name their maker, wherever they stand: inside paths, query strings and longer runs too.
VENDORED = re.compile(
    r"A[KS]IA[A-Z0-9]{16}|gh[opusr]_[A-Za-z0-9]{16,}|github_pat_\w{20,}|glpat-[\w\-]{16,}|xox[abprs]-[\w\-]{10,}|[sr]k_(?:live|test)_\w{10,}"
    r"|(?<![A-Za-z0-9])sk-[\w\-]{20,}|AIza[\w\-]{16,}|(?<![A-Za-z0-9])eyJ[\w\-]{8,}(?:\.[\w\-]+){0,2}"
)
#: The password of an address; any value behind '=', ':' or an opening bracket with a quote, under any name; or a run of key-like characters that holds
#: a digit, a capital inside a word or capitals alone. Which of them are secrets is the forest's to say.
CANDIDATE = re.compile(
    r"://[^\s/:@]*+:([^\s/@]{3,}+)(?=@)"
    r"|(?:=[=>]?|:[:=]?(?!//|[ \t]*+\\?[\"'`]?[\w.\-]{1,64}=[^\s=])|\((?=\s*+\\?[\"'`]))[ \t]*+\\?(?:([\"'`])((?:(?!\2)\S){6,}+)|(?!\w{2,12}://)([^\s\"'`&;,]{6,}+))"
    r"|(?<![A-Za-z0-9+/_\-])((?:(?=[A-Za-z+/_\-]*+[0-9])[A-Za-z0-9+/_\-]{12,}+|[A-Z]{16,}+(?![a-z])|(?=[A-Za-z+/_\-]{16})(?=(?:[A-Z+/_\-]*+[a-z]++(?![A-Z]))*+[A-Z+/_\-]*+[a-z]++[A-Z])[A-Za-z+/_\-]++)(?:={1,2}+(?![^\s\"'`&;,)\]}<]))?)"
)
ABOUT = 40
TELLING = re.compile(r"(?i)(secret|token|passw|pwd|api.?key|access.?key|auth|credential|private|bearer)")
NAMED = re.compile(TELLING.pattern + r"[\w.\-]{0,24}[\"'`\]]{0,2}\s*(=[=>]?|:[:=]?|\()\s*\\?[\"'`]?$")
ADDRESS = re.compile(r"[\w.\-]:$")
INNOCENT = re.compile(r"(?i)(commit|sha\d*|md5|checksum|digest|uuid|guid|build|revision|etag|order|invoice|isbn|serial|version|image|example)")
FEATURES = [
    "length", "digits", "upper", "lower", "signs", "entropy", "class_changes", "letter_to_digit", "transition_score", "vowel_gap", "dictionary",
    "hex_only", "uuid_shape", "date_shape", "vendor", "path_marks", "in_path", "assigned", "quoted", "telling", "innocent", "longest_run", "distinct",
    "named", "in_address", "code_marks",
]


#: A learned word has 4 to 12 letters and is at least one in so many of all such words: the dictionary never holds more words than that.
RARE = 500_000


@dataclass(frozen=True)
class Lexicon:
    """Words, and how much more often than by chance a letter follows another in them (logarithms)."""

    words: frozenset[str]
    transitions: dict[str, float]

    @classmethod
    def of(cls, counts: dict[str, int]) -> Lexicon:
        """From words and how often they occur; the fixed words count once more."""
        pairs: dict[str, int] = {}
        for w, n in [*counts.items(), *((w, 1) for w in WORDS)]:
            for pair in zip(w, w[1:]):
                pairs["".join(pair)] = pairs.get("".join(pair), 0) + n
        total = sum(pairs.values())
        return cls(frozenset([*counts, *WORDS]), {k: math.log(n / total * 676) for k, n in pairs.items()})

    @classmethod
    def learned(cls, docs: DataFrame, rare: int = RARE) -> Lexicon:
        """From the words of all whole texts; counts are folded before they move, and only words above the share come to the driver."""
        words = docs.select(F.explode(F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit(r"(?<![\p{L}\p{N}_])[a-z]{4,12}(?![\p{L}\p{N}_])"), 0)).alias("w"))
        counts = words.groupBy("w").agg(F.count(F.lit(1)).alias("n"))
        kept = counts.crossJoin(F.broadcast(counts.agg(F.sum("n").alias("total")))).filter((F.col("n") * rare >= F.col("total")) & (F.col("n") > 1))
        return cls.of({r.w: r.n for r in kept.select("w", "n").collect()})


PLAIN = Lexicon.of({})
_CLASS = {**dict.fromkeys("0123456789", 1), **dict.fromkeys("ABCDEFGHIJKLMNOPQRSTUVWXYZ", 2), **dict.fromkeys("abcdefghijklmnopqrstuvwxyz", 3)}


def coverage(word: str, dictionary: frozenset[str] = PLAIN.words) -> float:
    """Share of a word's characters that dictionary words cover, longest first from the left."""
    low, at, covered = word.lower(), 0, 0
    while at < len(low):
        for size in range(min(12, len(low) - at), 2, -1):
            if low[at : at + size] in dictionary:
                covered += size
                at += size
                break
        else:
            at += 1
    return covered / max(len(low), 1)


def describe(candidate: str, before: str, after: str, lexicon: Lexicon = PLAIN) -> list[float]:
    """One row of features: the candidate's length, characters and their transitions, its dictionary coverage, path and neighbouring words."""
    n = len(candidate)
    kinds = [_CLASS.get(c, 0) for c in candidate]
    letters = [c for c in candidate.lower() if c.isalpha()]
    counts = [candidate.count(c) for c in set(candidate)]
    pairs = [a + b for a, b in zip(letters, letters[1:])]
    longest = run = 1
    for a, b in zip(kinds, kinds[1:]):
        run = run + 1 if a == b else 1
        longest = max(longest, run)
    gap = max((len(x) for x in re.split(r"[aeiouAEIOU0-9]+", candidate)), default=0)
    return [
        n,
        kinds.count(1) / n,
        kinds.count(2) / n,
        kinds.count(3) / n,
        kinds.count(0) / n,
        -sum(c / n * math.log2(c / n) for c in counts),
        sum(a != b for a, b in zip(kinds, kinds[1:])) / n,
        sum({a, b} in ({1, 2}, {1, 3}) for a, b in zip(kinds, kinds[1:])) / n,
        sum(lexicon.transitions.get(p, -2.0) for p in pairs) / max(len(pairs), 1),
        gap,
        coverage(candidate, lexicon.words),
        float(bool(re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", candidate))),
        float(bool(re.fullmatch(r"(?i)[0-9a-f]{8}(-[0-9a-f]{4}){3}-[0-9a-f]{12}", candidate))),
        float(bool(re.search(r"(19|20)\d\d[-_/]?[01]\d[-_/]?[0-3]\d", candidate))),
        float(bool(VENDOR.match(candidate))),
        candidate.count("/") + candidate.count("-") + candidate.count("_"),
        float(bool(re.search(r"[/\\.@#?&]$", before)) or after[:1] in ("/", ".") and after[1:2].isalnum() or after[:1] == "@"),
        float(bool(re.search(r"(=|:=?|=>)\s*[\"'`]?$", before))),
        float(before[-1:] in ("'", '"', "`") and after[:1] in ("'", '"', "`")),
        float(bool(TELLING.search(before[-24:]))),
        float(bool(INNOCENT.search(before[-24:]))),
        longest,
        len(counts) / n,
        float(bool(NAMED.search(before))),
        float(after[:1] == "@" and bool(ADDRESS.search(before))),
        sum(candidate.count(c) for c in "()[]{}<>.:"),
    ]


@dataclass(frozen=True)
class Finding:
    """A labelled candidate with the text around it."""

    before: str
    candidate: str
    after: str
    secret: bool


def findings_of(rows: DataFrame, most: int = 20_000) -> list[Finding]:
    """Labelled findings from a table (before, candidate, after, secret): at most so many, the first by hash. Rows without a candidate or a label are left out."""
    known = rows.filter("candidate <> '' AND secret IS NOT NULL").select(F.coalesce("before", F.lit("")).alias("before"), "candidate", F.coalesce("after", F.lit("")).alias("after"), F.col("secret").cast("boolean").alias("secret"))
    return [Finding(*r) for r in known.orderBy(F.xxhash64("before", "candidate", "after"), "before", "candidate", "after").limit(most).collect()]


def example_findings(n: int = 6_000, seed: int = 11, lexicon: Lexicon = PLAIN) -> list[Finding]:
    """Labelled findings to begin with: keys, tokens and passwords of usual kinds, and what scanners report by mistake, among words of the lexicon."""
    rng = random.Random(seed)
    known = [*WORDS, *sorted(lexicon.words - PLAIN.words)]
    known_word = lambda: rng.choice(known if rng.random() < 0.5 else WORDS)
    pick = lambda letters, k: "".join(rng.choice(letters) for _ in range(k))
    lower, upper, digits = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    mixed, base32, hexa = lower + upper + digits, upper + "234567", digits + "abcdef"
    word = lambda: "".join(known_word() for _ in range(rng.randint(1, 3)))
    prose = lambda: " ".join(word() for _ in range(3)) + " "
    leet = str.maketrans("aeios", "43105")

    def made_up() -> str:
        """A password as people make them: a word with digits or signs in it or behind it."""
        w = (word() + rng.choice(WORDS) + rng.choice(WORDS))[: rng.randint(5, 12)]
        w = rng.choice([w, w.capitalize(), w.translate(leet), w.capitalize().translate(leet)])
        return w + pick(digits, rng.randint(1, 4)) + rng.choice(["", "x", "!", pick(mixed, 2)])

    out = []
    for k in range(n):
        name = rng.choice(["token", "secret", "api_key", "password", "auth_token", "access_key", "client_secret", "passwd"])
        give = rng.choice([f'{name} = "', f"{name}=", f"{name}: ", f"'{name}': '"])
        close = '"' if give.endswith('"') else "'" if give.endswith("'") else rng.choice([" ", "\n", ""])
        any_name = rng.choice(["", "my", "db_", "aws_", "AWS_", "app.", "user"]) + rng.choice(["token", "secret", "apiKey", "api_key", "password", "accessToken", "access_key", "access_key_id", "secret_access_key", "passwd", "pwd", "privateKey", "auth"])
        any_name = rng.choice([any_name, any_name.upper(), any_name.capitalize(), any_name.replace("_", "-")])
        any_give = any_name + rng.choice(["=", ": ", ":", " = ", '="', "='", ' = "', '": "', "':'", " => '", '("'])
        any_close = any_give[-1] + " " if any_give[-1] in "\"'" else rng.choice([" ", "\n", "&", ", "])
        if k % 2:
            kind = rng.randrange(10)
            if kind == 0:
                f = (prose(), "AKIA" + pick(upper + rng.choice([digits, "234567"]), 16), " " + word())
            elif kind == 1:
                f = (prose() + give, pick(hexa, rng.choice([16, 18, 20, 32, 40, 64])), close + " " + word())
            elif kind == 2:
                f = (prose() + give, pick(mixed + rng.choice(["", "+/", "_-"]), rng.randint(16, 64)), close + " " + word())
            elif kind == 3:
                f = (prose(), rng.choice(["ghp_", "gho_"]) + pick(mixed, 36), " " + word())
            elif kind == 4:
                f = (prose(), rng.choice(["xoxb-", "sk_live_", "glpat-", "AIza"]) + pick(mixed, rng.randint(20, 36)), rng.choice([" ", ".", "\n"]))
            elif kind == 5:
                f = (prose() + rng.choice(["password=", "passwd=", "pwd="]), pick(mixed + "!$%", rng.randint(8, 20)), " " + word())
            elif kind == 6:
                f = (prose() + any_give, made_up(), any_close + word())
            elif kind == 7:
                f = (prose() + any_give, pick(rng.choice([hexa, mixed, mixed + "+/", mixed + "_-"]), rng.randint(16, 64)), any_close + word())
            elif kind == 8:
                f = (prose() + rng.choice(["", "https://", "postgres://", "mysql://", "ftp://", "amqp://"]) + rng.choice(["user", "root", "admin", word()[:10]]) + ":", rng.choice([made_up(), pick(mixed, rng.randint(8, 24))]), "@" + rng.choice(["host", "localhost:5432/", "db.example.org/"]) + word())
            else:
                before = rng.choice([any_give, "https://" + word() + ".org/" + word() + "?" + rng.choice(["code", "q", "key", word()]) + "=", word() + "/", word() + "=", word() + ": "])
                f = (prose() + before, rng.choice(["AKIA" + pick(upper + "234567", 16), "ghp_" + pick(mixed, 36), "glpat-" + pick(mixed, 20), "xoxb-" + pick(digits, 11) + "-" + pick(mixed, 24), "eyJ" + pick(mixed, 20) + ".eyJ" + pick(mixed, 30) + "." + pick(mixed + "_-", 43)]), rng.choice(["&", " ", '"']) + word())
        else:
            kind = rng.randrange(20)
            if kind == 0:
                f = (prose() + rng.choice(["commit ", "sha1 ", "md5: ", "checksum = ", "revision "]), pick(hexa, rng.choice([32, 40, 64])), " " + word())
            elif kind == 1:
                f = (prose() + rng.choice(["", "uuid ", "id="]), "-".join(pick(hexa, i) for i in (8, 4, 4, 4, 12)), " ")
            elif kind == 2:
                f = (prose() + "/", "/".join(word() + pick(digits, rng.randint(0, 3)) for _ in range(3)) + pick(digits, 1), rng.choice([".html", "/", " "]))
            elif kind == 3:
                f = (prose(), "".join(word() for _ in range(3)).upper(), rng.choice(["!! ", " ", ". "]))
            elif kind == 4:
                f = (prose(), pick(digits, rng.randint(12, 19)), " " + word())
            elif kind == 5:
                f = (prose(), f"20{pick(digits, 2)}-{rng.randint(1, 12):02d}-{rng.randint(1, 28):02d}T{pick('0123', 2)}", ":00 ")
            elif kind == 6:
                f = (prose(), "".join(word().capitalize() for _ in range(4)) + pick(digits, rng.randint(0, 2)), rng.choice(["(", " ", "."]))
            elif kind == 7:
                f = (prose() + rng.choice(["password=", "token=", "secret="]), rng.choice(["changeme", "example", "yourpassword", "your_token_here", "placeholder", "redacted", "xxxxxxxx", "********"]), " ")
            elif kind == 8:
                f = (prose(), "-".join(word() for _ in range(3)) + "-" + pick(digits, rng.randint(1, 3)), rng.choice(["@", ".example", " "]))
            elif kind == 9:
                f = (prose() + rng.choice(["image:", "src=", "build "]), word() + "_" + pick(digits, rng.randint(2, 8)) + "_" + word(), rng.choice([".png", " "]))
            elif kind in (10, 11):
                f = (prose() + rng.choice([word() + ": ", word().capitalize() + ": ", word() + "=", word() + '="', '"' + word() + '": "', word() + "::", word() + '("']), rng.choice([word() + "ing", word().capitalize() + "er", rng.choice(WORDS) + "-" + word(), "https", "utf-8-" + word(), word() + "." + word(), "Bearer"]), rng.choice([" ", ". ", '" ', ", "]) + word())
            elif kind == 12:
                f = (prose() + any_give, rng.choice(["changeme", "example", "your_" + word(), "placeholder", "redacted", "xxxxxxxx", "********", "password", "undefined", "[SECRET]", "required"]), any_close + word())
            elif kind == 13:
                f = (prose() + any_give.rstrip("\"'`"), rng.choice([f"os.environ[{name.upper()}]", f"process.env.{name.upper()}", f"config.{name}", f"self.{name}", f"${{{name.upper()}}}", f"<{name}>", f"get_{name}()", f"{{{{{name}}}}}", f"settings.{word()}.{name}", f"getenv({word()})"]), rng.choice([" ", "\n", ")"]))
            elif kind == 14:
                f = (prose() + any_give.rstrip("\"'`="), rng.choice(WORDS) + rng.choice(WORDS) + "ed", rng.choice([" ", ". ", ", "]) + prose())
            elif kind == 15:
                f = (prose() + f"{rng.randint(0, 23):02d}:", f"{rng.randint(0, 59):02d}:{rng.randint(0, 59):02d}" + rng.choice(["Z", "+00:00", "." + pick(digits, 3)]), " " + word())
            elif kind == 16:
                f = (prose() + pick(hexa, 2) + ":", ":".join(pick(hexa, 2) for _ in range(5)), " " + word())
            elif kind == 17:
                f = (prose() + word() + rng.choice([": ", "=", '="', '": "']), rng.choice([pick(digits, rng.randint(6, 16)), f"{pick(digits, 3)}.{pick(digits, 2)}.{pick(digits, 2)}", f"20{pick(digits, 2)}-{pick('01', 1)}1-{pick('012', 1)}3", pick(digits, 3) + "-" + pick(digits, 4) + "-" + pick(digits, 4)]), rng.choice([" ", '"', ", "]) + word())
            elif kind == 18:
                f = (prose() + rng.choice(["href=\"", "src='", "url: ", "path=", "file: "]), rng.choice(["/", "./", "#", "../"]) + "/".join(word() + pick(digits, rng.randint(0, 2)) for _ in range(rng.randint(1, 3))) + rng.choice(["", ".html", ".png"]), rng.choice(['"', "'", " "]) + word())
            else:
                f = (prose() + rng.choice(["mailto:", "mail: ", "to:", "contact="]), word() + rng.choice(["", "."]) + word() + "@" + word() + ".org", " " + word())
        out.append(Finding(*f, bool(k % 2)))
    return out


@dataclass(frozen=True)
class Model:
    """A forest and the lexicon that its features are taken with."""

    trees: Trees
    lexicon: Lexicon


def train(findings: Iterable[Finding], lexicon: Lexicon = PLAIN, **options) -> Model:
    """A forest from labelled findings; any team's own findings serve as well as the examples."""
    rows = list(findings)
    x = np.array([describe(f.candidate, f.before[-ABOUT:], f.after[:ABOUT], lexicon) for f in rows], dtype=np.float64)
    return Model(forest(x, np.array([float(f.secret) for f in rows]), **options), lexicon)


@lru_cache(maxsize=1)
def default_model() -> Model:
    return train(example_findings())


def model_for(docs: DataFrame, findings: DataFrame | None = None) -> Model:
    """The lexicon of the documents; the findings of a table, if there is one, beside the examples."""
    lexicon = Lexicon.learned(docs)
    return train([*example_findings(lexicon=lexicon), *(findings_of(findings) if findings is not None else [])], lexicon)


def candidates(text: str) -> list[tuple[int, int]]:
    """Spans from left to right, none within another. A value that ends like an address ("name:value@host") is taken up to the host."""
    out, at = [], 0
    for a, b in [*(m.span() for m in VENDORED.finditer(text)), (len(text), len(text))]:
        for m in CANDIDATE.finditer(text, at, a):
            start, end = m.span(m.lastindex)
            if m.lastindex == 4 and text[start - 1] == ":" and "@" in text[start:end] and not TELLING.search(text[max(0, start - 24) : start]):
                host = text.rindex("@", start, end)
                end = host if host - start >= 3 else end
            out.append((start, end))
        if b > a:
            out.append((a, b))
        at = b
    return out


def judge(texts: list[str], model: Model) -> list[list[tuple[int, int, float]]]:
    """Per text its candidates as (start, end, score)."""
    spans = [candidates(t) for t in texts]
    rows = [describe(t[a:b], t[max(0, a - ABOUT) : a], t[b : b + ABOUT], model.lexicon) for t, found in zip(texts, spans) for a, b in found]
    scores = iter(model.trees.raw(np.array(rows, dtype=np.float64)) if rows else ())
    return [[(a, b, float(next(scores))) for a, b in found] for found in spans]


def secret_scan(docs: DataFrame, model: Model | None = None, threshold: float = 0.5, findings: DataFrame | None = None) -> DataFrame:
    """Per row: doc_id, n_candidates, n_secrets, max_score (0 without candidates), spans ("start-end" in characters, by comma).

    Null and empty texts have no candidates. Texts are scanned whole, in time linear in their length. Repeated rows give
    repeated results, rows without an id one without it, an empty table an empty one, other columns are ignored. Without a
    model, one is trained with the words of the documents and the labelled ``findings``, if any.
    """
    model = model or model_for(docs, findings)

    def tell(texts: list[str]) -> list[tuple]:
        rows = []
        for found in judge(texts, model):
            real = [(a, b) for a, b, s in found if s >= threshold]
            rows.append((len(found), len(real), max((s for _, _, s in found), default=0.0), ",".join(f"{a}-{b}" for a, b in real)))
        return rows

    return by_text(docs, "doc_id", "text", "n_candidates long, n_secrets long, max_score double, spans string", lambda: tell)


def redact(docs: DataFrame, model: Model | None = None, threshold: float = 0.5, mark: str = "[SECRET]", findings: DataFrame | None = None) -> DataFrame:
    """All rows and columns, with each secret in ``text`` replaced by the mark; texts without secrets, null ones too, stay as they are.

    Repeated rows are changed alike, an empty table stays empty, and no other column is read or renamed, whatever its name.
    """
    ship(docs.sparkSession)
    model = model or model_for(docs, findings)

    @F.pandas_udf("string")
    def cleaned(texts: pd.Series) -> pd.Series:
        known = [t for t in texts if t is not None]
        out = []
        for t, found in zip(known, judge(known, model)):
            parts, at = [], 0
            for a, b, s in found:
                if s >= threshold:
                    parts += [t[at:a], mark]
                    at = b
            out.append("".join(parts) + t[at:] if at else t)
        it = iter(out)
        return pd.Series([None if t is None else next(it) for t in texts], dtype=object)

    return docs.withColumn("text", cleaned("text"))
