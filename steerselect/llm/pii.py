"""Surrogates for personal data and secrets.

Detected entities get keyed replacements of their own type and format: letters stay letters of the same case, digits
digits, a card number keeps its length and its check digit's validity, an address stays a valid address, a person's
name keeps its title, gender and script.  The same entity, however it is written, always gets the same surrogate;
different entities get different ones.  That is checked: surrogates are a function of (key, type, entity, attempt), and
every entity whose surrogate meets another's, or is itself an entity of the corpus, moves to its next attempt until
none meet.  Only those few exceptions travel to the texts.

A person's names are entities of their own: a family name has one surrogate whoever bears it, and a given name is told
from the others of its family name.  So a collision moves one name and no other.  Within a text a title that shows the
gender speaks for every mention of the same full name, and names that follow a title once are replaced wherever they
stand again without one.
"""

from __future__ import annotations

import bisect
import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import begin, slices, text_or_empty, texts, written

#: Exceptions up to this number are broadcast; more are joined to their documents.
BROADCAST_ROWS = 100_000

# Titles by gender, given names by script and gender, syllables by script.
TITLES = {
    "m": ("Mr", "Herr", "Señor", "Sr", "Monsieur", "Don", "Г-н", "Господин"),
    "f": ("Mrs", "Ms", "Miss", "Frau", "Señora", "Señorita", "Sra", "Srta", "Mme", "Mlle", "Madame", "Doña", "Г-жа", "Госпожа"),
    "x": ("Dr", "Prof", "Mx"),
}
GIVEN = {
    ("latin", "m"): ("Adam", "Bruno", "Carl", "David", "Emil", "Felix", "Hugo", "Ivan", "Julian", "Leon", "Martin", "Oscar", "Paul", "Simon", "Victor"),
    ("latin", "f"): ("Alice", "Bella", "Clara", "Diana", "Emma", "Flora", "Helena", "Irene", "Julia", "Laura", "Maria", "Nina", "Olga", "Rosa", "Vera"),
    ("latin", "x"): ("Alex", "Chris", "Dominique", "Kim", "Noa", "Robin", "Sascha", "Toni"),
    ("cyrillic", "m"): ("Антон", "Борис", "Виктор", "Иван", "Максим", "Олег", "Павел", "Роман"),
    ("cyrillic", "f"): ("Анна", "Вера", "Дарья", "Елена", "Ирина", "Мария", "Нина", "Ольга"),
    ("cyrillic", "x"): ("Саша", "Женя", "Валя", "Слава"),
}
SYLLABLES = {
    "latin": ("ba", "ber", "cor", "da", "del", "fan", "gra", "hol", "kas", "la", "lin", "mar", "nor", "pel", "ro", "sal", "ten", "tor", "val", "wen"),
    "cyrillic": ("ба", "бор", "вал", "гор", "дан", "зел", "кар", "лин", "мар", "нов", "пет", "рос", "сав", "тар", "фед"),
}

_names = sorted((t for ts in TITLES.values() for t in ts), key=len, reverse=True)
_title = {t.casefold(): g for g, ts in TITLES.items() for t in ts}
#: The kinds in the order in which they are tried at a place.
PATTERNS = {
    "secret": r"(?<![\w])(?:(?i:token|secret|password|passwd|api[_-]?key|access[_-]?key)\s?[=:]\s?[\"']?(?P<secret>(?=[A-Za-z_\-]*\d)[\w\-]{12,128})|(?P<bare>(?i:AKIA)[0-9A-Za-z]{16}|(?=[0-9a-fA-F]*[a-fA-F])(?=[0-9a-fA-F]*\d)(?:[0-9a-f]{32,64}|[0-9A-F]{32,64})))(?!\w)",
    "email": r"(?P<email>(?<![\w.+\-])[\w+\-]+(?:\.[\w+\-]+)*@[\w\-]+(?:\.[\w\-]+)*\.[A-Za-z]{2,24})(?![\w\-])",
    "iban": r"(?P<iban>(?<!\w)[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?)(?!\w)",
    "phone": r"(?P<phone>(?<![\w+])(?:\+\d{1,3}[ .\-]?)?\(\d{2,4}\)[ .\-]?\d{3,4}[ .\-]\d{3,4}|(?<![\w+])\+\d{1,3}(?:[ .\-]?\d{2,4}){2,5}|(?<![\w.\-])\d{3}[.\-]\d{3}[.\-]\d{4})(?![\w])",
    "ssn": r"(?P<ssn>(?<![\w\-])\d{3}-\d{2}-\d{4})(?![\w\-])",
    "ip": r"(?P<ip>(?<![\w.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d))(?!\.?\w)",
    "card": r"(?P<card>(?<![\w.\-])\d(?:[ \-]?\d){12,18})(?![\w\-])",
    "person": r"(?<!\w)(?P<title>"
    + "|".join(map(re.escape, _names))
    + r")\.?[ ](?P<person>(?:[OD]['’])?[^\W\d_a-zа-я][^\W\d_A-ZА-Я]+(?:[ \-](?:[OD]['’])?[^\W\d_a-zа-я][^\W\d_A-ZА-Я]+){0,2})(?!\w)",
}
FIND = re.compile("|".join(PATTERNS.values()))
#: Every entity holds a digit or an at sign, or follows a title; only the surroundings of these marks are searched.
MARK = re.compile("[@0-9]")
TITLE = re.compile(r"(?<!\w)(?:" + "|".join(map(re.escape, _names)) + r")\.?[ ]")
AROUND = 200


def luhn(digits: str) -> bool:
    d = [int(c) for c in digits[::-1]]
    return (sum(d[::2]) + sum(sum(divmod(2 * x, 10)) for x in d[1::2])) % 10 == 0


def iban_sum(text: str) -> int:
    return int("".join(str(int(c, 36)) for c in text[4:] + text[:4])) % 97


def script_of(name: str) -> str:
    return "cyrillic" if re.search("[Ѐ-ӿ]", name) else "latin"


def entities(text: str) -> list[tuple[int, int, str, str]]:
    """(start, stop, type, canonical form) of the entities of a text, from left to right."""
    found = [x for lo, hi in surroundings(text) for m in FIND.finditer(text, lo, hi) if (x := canonical(text, m)) is not None]
    return with_mentions(text, found) if any(k.startswith("person:") for _, _, k, _ in found) else found


def with_mentions(text: str, found: list[tuple[int, int, str, str]]) -> list[tuple[int, int, str, str]]:
    """The entities with one gender for each full name, and with later mentions of names that bear no title."""
    gender: dict[str, str] = {}
    people: dict[str, str] = {}  # a full or family name as written -> its type
    for start, stop, kind, canon in found:
        if kind.startswith("person:"):
            _, g, script = kind.split(":")
            gender[canon] = g if gender.get(canon, "x") == "x" else gender[canon]
            name = text[start:stop]
            people.setdefault(name, kind)
            people.setdefault(name.rpartition(" ")[2], f"person:x:{script}")
    taken = [(a, z) for a, z, _, _ in found]
    more = []
    for m in re.finditer(r"(?<!\w)(?:" + "|".join(map(re.escape, sorted(people, key=len, reverse=True))) + r")(?!\w)", text):
        at = bisect.bisect_left(taken, (m.end(), 0))
        if at == 0 or taken[at - 1][1] <= m.start():
            more.append((*m.span(), people[m[0]], m[0].casefold()))
    out = []
    for start, stop, kind, canon in sorted(found + more):
        if kind.startswith("person:") and canon in gender:
            kind = f"person:{gender[canon]}:{kind.split(':')[2]}"
        out.append((start, stop, kind, canon))
    return out


def names_of(kind: str, canon: str) -> list[tuple[str, str]]:
    """The (type, canonical form) pairs that have a surrogate each: a person's names, or the entity itself."""
    if not kind.startswith("person:"):
        return [(kind, canon)]
    _, gender, script = kind.split(":")
    words = re.split("[ -]", canon)
    family = [(f"family:{script}", w) for w in words[max(0, min(1, len(words) - 1)) :]]
    return [(f"given:{gender}:{script}:{words[-1]}", words[0])] * (len(words) > 1) + family


def surroundings(text: str) -> list[tuple[int, int]]:
    """Ranges that begin and end at blanks, at least ``AROUND`` characters from the marks in them."""
    out: list[tuple[int, int]] = []
    at = 0
    while m := MARK.search(text, at):
        at = _blank_after(text, m.start() + AROUND)
        out.append((_blank_before(text, m.start() - AROUND), at))
    if any(f"{t} " in text or f"{t}. " in text for t in _names):
        out += [(_blank_before(text, m.start() - 1), _blank_after(text, m.end() + AROUND)) for m in TITLE.finditer(text)]
        out.sort()
    merged: list[tuple[int, int]] = []
    for lo, hi in out:
        if merged and lo <= merged[-1][1]:
            merged[-1] = (merged[-1][0], max(hi, merged[-1][1]))
        else:
            merged.append((lo, hi))
    return merged


def _blank_after(text: str, at: int) -> int:
    m = re.compile(r"\s").search(text, at) if at < len(text) else None
    return m.start() if m else len(text)


def _blank_before(text: str, at: int) -> int:
    while at > 0 and not text[at].isspace():
        at -= 1
    return max(0, at)


def canonical(text: str, m: re.Match) -> tuple[int, int, str, str] | None:
    """(start, stop, type, canonical form) of a match; None if a checksum or a length rules it out."""
    kind = next(k for k, v in m.groupdict().items() if v is not None and k != "title")
    start, stop = m.span(kind)
    found = text[start:stop]
    kind = "secret" if kind == "bare" else kind
    if kind == "person":
        return start, stop, f"person:{_title[m['title'].casefold()]}:{script_of(found)}", found.casefold()
    plain = re.sub(r"[\W_]", "", found)
    if kind == "card" and not luhn(plain) or kind == "iban" and iban_sum(plain) != 1 or kind == "phone" and not 7 <= len(plain) <= 15:
        return None
    return start, stop, kind, found.lower() if kind in ("email", "secret") else found if kind == "ip" else plain


class Keyed:
    """A stream of choices that a key, a type, an entity and an attempt fix."""

    def __init__(self, key: bytes, kind: str, canon: str, attempt: int) -> None:
        self.seed, self.key, self.n, self.held = f"{kind}|{attempt}|{canon}".encode("utf-8", "surrogatepass"), key, 0, b""

    def below(self, n: int) -> int:
        if len(self.held) < 4:
            self.held = hashlib.blake2b(self.seed, key=self.key, salt=self.n.to_bytes(8, "little")).digest()
            self.n += 1
        value, self.held = int.from_bytes(self.held[:4], "little"), self.held[4:]
        return value % n

    def of(self, choices):
        return choices[self.below(len(choices))]


def scrambled(text: str, draw: Keyed, letters: str) -> str:
    return "".join(str(draw.below(10)) if c.isdigit() else draw.of(letters) if c.isalpha() else c for c in text)


def surrogate(key: bytes, kind: str, canon: str, attempt: int = 0) -> str:
    """The surrogate of a canonical form, itself canonical.  Its first attempts keep the length; later ones grow it."""
    draw = Keyed(key, kind, canon, attempt)
    more = "".join(str(draw.below(10)) for _ in range(max(0, attempt - 8)))
    if kind.startswith("family:"):
        script = kind.split(":")[1]
        return "".join(draw.of(SYLLABLES[script]) for _ in range(3 + attempt // 2))
    if kind.startswith("given:"):  # beyond a few attempts the name grows, so any number of bearers finds one
        _, gender, script, _ = kind.split(":", 3)
        return (draw.of(GIVEN[script, gender]) + "".join(draw.of(SYLLABLES[script]) for _ in range(attempt // 2))).casefold()
    if kind == "email":
        local, _, host = canon.partition("@")
        name, _, top = host.rpartition(".")
        inner = Keyed(key, "host", host, 0)  # the same host, the same surrogate host
        return f"{scrambled(local, draw, 'abcdefghijklmnopqrstuvwxyz')}{more}@{scrambled(name, inner, 'bcdfghjklmnprstvwz')}.{top}"
    if kind == "ip":
        return ".".join(str(x) for x in (1 + draw.below(223), draw.below(256), draw.below(256), 1 + draw.below(254)))
    if kind == "card":
        body = canon[0] + "".join(str(draw.below(10)) for _ in canon[2:])
        return next(body + c for c in "0123456789" if luhn(body + c))
    if kind == "iban":
        body = scrambled(canon[4:], draw, "ABCDEFGHIJKLMNOPQRSTUVWXYZ")
        return f"{canon[:2]}{98 - iban_sum(canon[:2] + '00' + body):02d}{body}"
    if kind == "phone":
        keep = max(0, len(canon) - 10)  # the country's digits
        return canon[:keep] + str(2 + draw.below(8)) + "".join(str(draw.below(10)) for _ in canon[keep + 1 :]) + more[: 15 - len(canon)]
    if kind == "secret":
        hexa = re.fullmatch("[0-9a-f]+", canon)
        head = "akia" if canon.startswith("akia") else ""
        return head + scrambled(canon[len(head) :], draw, "abcdef" if hexa else "abcdefghijklmnopqrstuvwxyz") + more
    return scrambled(canon, draw, "abcdefghijklmnopqrstuvwxyz") + more


def rendered(found: str, kind: str, new: str) -> str:
    """A canonical surrogate in the written form of what it replaces."""
    if kind == "ip":
        return new
    if kind.startswith("person:"):
        return new.upper() if found.isupper() else "".join(w.capitalize() for w in re.split("([ -])", new))
    if kind in ("email", "secret"):
        if len(new) == len(found):
            return "".join(n.upper() if f.isupper() or f.isdigit() and found.isupper() else n for f, n in zip(found, new))
        return new.upper() if found.isupper() else new
    rest = iter(new)
    out = "".join(next(rest, c) if c.isalnum() else c for c in found)
    return out + "".join(rest)


def replaced(text: str, key: bytes, attempts: dict[tuple[str, str], int]) -> tuple[str, list[tuple[str, str, str]]]:
    """The text with surrogates, and (type, found, surrogate) in order."""
    out, at, log = [], 0, []
    for start, stop, kind, canon in entities(text):
        found = text[start:stop]
        names = [surrogate(key, k, c, attempts.get((k, c), 0)) for k, c in names_of(kind, canon)]
        if kind.startswith("person:"):
            new = rendered(found, kind, "".join(x for pair in zip(names, [*re.findall("[ -]", canon), ""]) for x in pair))
        else:
            new = rendered(found, kind, names[0])
        out += (text[at:start], new)
        log.append((kind.split(":")[0], found, new))
        at = stop
    return ("".join(out) + text[at:], log) if log else (text, log)


def distinct_entities(docs: DataFrame, text_col: str) -> DataFrame:
    def run(batches):
        begin("pii")
        for b in slices(batches):
            seen = {x for t in b.column("text") for _, _, kind, canon in entities(t.as_py()) for x in names_of(kind, canon)}
            if seen:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*seen)], names=["kind", "canon"])

    return texts(docs, text_or_empty(text_col).alias("text")).mapInArrow(run, "kind string, canon string").distinct()


def exceptions(entity: DataFrame, key: bytes, most_rounds: int = 64) -> DataFrame:
    """(kind, canon, attempt) of the entities whose first surrogate is taken, each with an attempt that is free."""

    def run(batches):
        for b in batches:
            new = [surrogate(key, k, c, a) for k, c, a in zip(b.column("kind").to_pylist(), b.column("canon").to_pylist(), b.column("attempt").to_pylist())]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(new, pa.string())], names=["kind", "canon", "attempt", "new"])

    schema = "kind string, canon string, attempt int, new string"
    settled = written(entity.withColumn("attempt", F.lit(0)).mapInArrow(run, schema), "surrogates")
    for _ in range(most_rounds):
        first = Window.partitionBy("kind", "new").orderBy("attempt", "canon")
        ranked = settled.withColumn("nth", F.row_number().over(first))
        real = entity.select(F.col("kind").alias("k"), F.col("canon").alias("c"), F.lit(True).alias("real"))
        met = ranked.join(real, (F.col("kind") == F.col("k")) & (F.col("new") == F.col("c")), "left")
        marked = written(met.select("kind", "canon", "attempt", "new", ((F.col("nth") > 1) | F.col("real").isNotNull()).alias("again")), "marked")
        if not marked.filter("again").limit(1).count():
            return settled.filter("attempt > 0").select("kind", "canon", "attempt")
        moved = marked.filter("again").select("kind", "canon", (F.col("attempt") + 1).cast("int").alias("attempt")).mapInArrow(run, schema)
        settled = written(marked.filter("not again").drop("again").unionByName(moved), "surrogates")
    raise RuntimeError("surrogates still meet; use a longer format")


def replace_entities(docs: DataFrame, key: bytes = b"a secret that the caller holds", text_col: str = "text", log_col: str | None = None) -> DataFrame:
    """``docs`` with surrogates in ``text_col``; all columns stay, and ``log_col`` lists (kind, found, surrogate).

    Null texts stay null and texts without entities stay as they are, byte for byte; repeated rows get the same text; an
    empty table gives an empty result; a ``log_col`` that exists is an error.
    """
    if log_col in docs.columns:
        raise ValueError(f"the table already has a column {log_col}")
    taken = exceptions(written(distinct_entities(docs, text_col), "entities"), key)
    count = taken.count()
    small = {(r["kind"], r["canon"]): r["attempt"] for r in taken.collect()} if count <= BROADCAST_ROWS else None
    source, extra = docs, "attempts"
    while extra in docs.columns or extra == log_col:
        extra = "_" + extra
    if small is None:
        source = _with_attempts(docs, taken, text_col, extra)
    names = docs.columns
    log_type = pa.list_(pa.struct([("kind", pa.string()), ("found", pa.string()), ("surrogate", pa.string())]))

    def run(batches):
        begin("pii")
        for b in slices(batches, text_col):
            own = b.column(extra).to_pylist() if small is None else None
            texts, logs = [], []
            for i, t in enumerate(b.column(text_col)):
                t = t.as_py()
                attempts = small if small is not None else {(x["kind"], x["canon"]): x["attempt"] for x in own[i] or ()}
                t, log = (t, []) if t is None else replaced(t, key, attempts)
                texts.append(t)
                logs.append([{"kind": k, "found": f, "surrogate": s} for k, f, s in log])
            cols = [pa.array(texts, b.schema.field(text_col).type) if c == text_col else b.column(c) for c in names]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(logs, log_type)] if log_col else cols, names=[*names, log_col] if log_col else names)

    kinds = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema]
    return texts(source).mapInArrow(run, ", ".join(kinds + [f"`{log_col}` array<struct<kind: string, found: string, surrogate: string>>"] * bool(log_col)))


def _with_attempts(docs: DataFrame, taken: DataFrame, text_col: str, extra: str) -> DataFrame:
    """``docs`` and, per row, the exceptions that its text holds, by joins: the way for any number of them."""

    def run(batches):
        for b in slices(batches):
            rows = {(h, *x) for h, t in zip(b.column("h").to_pylist(), b.column("text")) for _, _, kind, canon in entities(t.as_py()) for x in names_of(kind, canon)}
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)], names=["h", "kind", "canon"])

    h = F.sha2(text_or_empty(text_col), 256)
    held = texts(docs, h.alias("h"), text_or_empty(text_col).alias("text")).mapInArrow(run, "h string, kind string, canon string").distinct()
    lists = held.join(taken, ["kind", "canon"]).groupBy("h").agg(F.collect_list(F.struct("kind", "canon", "attempt")).alias(extra))
    lists = lists.withColumnRenamed("h", f"{extra}_h")
    return docs.join(lists, h == lists[f"{extra}_h"], "left").select(*docs.columns, extra)
