"""Personal data replaced by keyed surrogates of the same type.

Each detected value is mapped by a keyed permutation of the values of its own
format (a Feistel network over its characters' alphabets, walked until the result
is valid for the type), so different values stay different, the same value gets
the same surrogate in every document, and length, script, case and punctuation
stay. Given names and surnames come from lists of the same gender and script, and
after the first draws are composed of syllables of the script and an ending of the
gender, more syllables with every few draws, so that names never run out.

Collisions are checked over the whole corpus: a surrogate that two values share,
or that is itself a real value somewhere, is drawn again with the next attempt
number until none is left; only such exceptions are joined to the documents. A format
with no free value left (64 attempts) grows by a character an attempt, so no
clash is ever kept.

The permutation can be undone with its key: callers pass their own secret bytes. A call
without one draws a key that is kept nowhere, so that nothing can be undone.

Defined results: null text stays null; empty and clean texts are unchanged;
repeated values count each time in n_entities; overlapping finds go to the
earliest, then the longest; a text takes time in proportion to its length; all
columns of the input pass through (but for n_entities and entity_kinds).
"""

from __future__ import annotations

import hashlib
import re
import secrets

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, release, table

#: Alphabets in which a character may be replaced.
ALPHABETS = ("0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "àáâãäåæçèéêëìíîïñòóôõöøùúûüýß", "ÀÁÂÃÄÅÆÇÈÉÊËÌÍÎÏÑÒÓÔÕÖØÙÚÛÜÝ", "абвгдежзийклмнопрстуфхцчшщъыьэюя", "АБВГДЕЖЗИЙКЛМНОПРСТУФХЦЧШЩЪЫЬЭЮЯ", "αβγδεζηθικλμνξοπρστυφχψω", "ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ")
HEX = "0123456789abcdef"
PLACE = {c: (a, i) for a in ALPHABETS for i, c in enumerate(a)}
#: Given names by gender and script, surnames by script.
GIVEN = {
    ("m", "latin"): "James Robert Michael William David Richard Joseph Thomas Charles Daniel Matthew Anthony Mark Steven Paul Andrew Kevin Brian George Edward Peter Frank Walter Hans Jürgen Klaus Pierre Jean Luc Carlos Miguel Javier".split(),
    ("f", "latin"): "Mary Patricia Jennifer Linda Elizabeth Barbara Susan Jessica Sarah Karen Nancy Lisa Sandra Ashley Emily Donna Michelle Carol Laura Amy Anna Helga Ursula Ingrid Claire Sophie Camille María Carmen Lucía Elena Isabel".split(),
    ("m", "cyrillic"): "Иван Пётр Сергей Алексей Дмитрий Николай Андрей Михаил Павел Олег".split(),
    ("f", "cyrillic"): "Анна Мария Ольга Елена Наталья Ирина Татьяна Светлана Юлия Вера".split(),
}
SURNAMES = {
    "latin": "Smith Johnson Williams Brown Jones Miller Davis Wilson Anderson Taylor Moore Jackson Martin Thompson White Harris Clark Lewis Walker Hall Young King Wright Scott Green Baker Adams Nelson Hill Campbell Müller Schmidt Schneider Fischer Weber Wagner Becker Hoffmann Dubois Durand Moreau Laurent Garcia Fernández López Martínez Sánchez Romero".split(),
    "cyrillic": "Иванов Смирнов Кузнецов Попов Васильев Петров Соколов Михайлов Новиков Фёдоров Морозов Волков".split(),
}
#: Titles by gender.
TITLES = {"m": r"Mr\.?|Sir|Herr|Herrn|Señor|Sr\.|Don|Monsieur|M\.|господин", "f": r"Mrs\.?|Ms\.?|Miss|Madam|Frau|Señora|Sra\.|Doña|Madame|Mme\.?|госпожа"}
NAME = r"[A-ZÀ-ÖØ-ÞА-ЯЁ][\w'’-]+"
TITLED = {g: re.compile(rf"(?<!\w)(?:{t})[^\S\n]+({NAME}(?:[^\S\n]+{NAME}){{0,2}})") for g, t in TITLES.items()}
ANY_TITLE = re.compile(rf"(?<!\w)(?:{TITLES['m']}|{TITLES['f']})\s")
NAMED = re.compile(rf"(?<!\w){NAME}")
DOMAIN = re.compile(r"[\w-]++(?:\.[\w-]++)++")
TOP = re.compile(r"[^\W\d_]{2,24}(?!\w)")
#: Syllables of composed names by script, and their endings by gender ("s": surnames).
SYLLABLES = {
    "latin": "ba be bo da de do fa fe fi ga ge ka ke ko la le li lo ma me mi mo na ne ni no pa pe ra re ri ro sa se si so ta te ti to va ve vi wa we ya za zo".split(),
    "cyrillic": "ба бе бо ва ве ви га го да де до за зо ка ко ла ле ли ло ма ме ми мо на не ни но па по ра ре ри ро са се си со та те ти то фа фи".split(),
}
ENDINGS = {
    ("m", "latin"): "n rd rt ld s us nd r".split(),
    ("f", "latin"): "lla nna ria tta lia sa na ra".split(),
    ("s", "latin"): "mann son ley ton berg well nez rick".split(),
    ("m", "cyrillic"): "слав мир н р лий сей".split(),
    ("f", "cyrillic"): "на ра лия са нна тья".split(),
    ("s", "cyrillic"): "нов ров ленко ский чук тин".split(),
}
#: Draws from the lists, and draws from the formats before they grow.
LISTED, MOST_DRAWS = 4, 64
#: Exceptions that are sent to the tasks; more are joined by document.
MOST_FIXED = 20_000
#: The numeric formats, most specific first.
NUMERIC = (
    ("secret", re.compile(r"(?<![\w])(?:[0-9a-f]{32,}|[0-9A-F]{32,})(?![\w])")),
    ("key", re.compile(r"(?<!\w)(?:AKIA[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36}|sk-[A-Za-z0-9]{20,})(?!\w)")),
    ("iban", re.compile(r"(?<!\w)[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?!\w)")),
    ("ipv6", re.compile(r"(?<![\w:])(?:[0-9a-fA-F]{1,4}:){7}[0-9a-fA-F]{1,4}(?![\w:])")),
    ("ipv4", re.compile(r"(?<![\w.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?!\w|\.\d)")),
    ("card", re.compile(r"(?<![\w-])\d(?:[ -]?\d){12,18}(?![\w-]|\.\d)")),
    ("ssn", re.compile(r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])")),
    ("phone", re.compile(r"(?<![\w.])(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)[ .-]?)?\d{2,4}(?:[ .-]\d{2,4}){1,4}(?![\w-]|\.\d)")),
    # with a country code: without separators, or in groups of up to eight digits
    ("phone", re.compile(r"(?<![\w.+])\+[1-9](?:[ .-]?\(\d{1,4}\)|[ .-]?\d{1,8}){1,7}(?![\w-]|\.\d)")),
)
ASSIGNED = re.compile(r"(?i)\b(?:token|secret|passw(?:or)?d|api[_-]?key|access[_-]?key)[\"']?\s*[=:]\s*[\"']?([^\s\"'#]{8,})")
DIGIT = re.compile(r"\d")
#: Characters of a long secret that are permuted as one number.
PIECE = 512


def _phone_like(v: str) -> bool:
    n = sum(c.isdigit() for c in v)
    return 7 <= n <= 15 and (v[0] in "+(" or n >= 10 or bool(re.fullmatch(r"\d{3}[ .-]\d{4}", v)))


def luhn(digits: str) -> int:
    """The check digit that follows digits."""
    total = sum(d if i % 2 else (2 * d - 9 if d > 4 else 2 * d) for i, d in enumerate(map(int, reversed(digits))))
    return -total % 10


def emails(text: str):
    """Spans of the addresses: every @ with the longest local part before it and the longest domain after it."""
    at, free = text.find("@"), 0
    while at >= 0:
        start, end = at, None
        while start > free and (text[start - 1].isalnum() or text[start - 1] in "_.+%-"):
            start -= 1
        m = DOMAIN.match(text, at + 1) if start < at else None
        if m:
            labels = m[0].split(".")
            stop = m.end()
            for label in reversed(labels[1:]):
                begin = stop - len(label)
                if top := TOP.match(text, begin, m.end()):
                    end = top.end()
                    break
                stop = begin - 1
        if end is not None:
            yield start, end
            free = end
        at = text.find("@", max(at + 1, free))


def detect(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the entities, without overlaps, in order."""
    spans = []
    if "@" in text:
        spans += [(*m, "email") for m in emails(text)]
    if DIGIT.search(text):
        for kind, rx in NUMERIC:
            spans += [(*m.span(), kind) for m in rx.finditer(text) if kind != "phone" or _phone_like(m[0])]
    if "=" in text or ":" in text:
        spans += [(*m.span(1), "secret") for m in ASSIGNED.finditer(text)]
    if ANY_TITLE.search(text):
        known = {}
        for gender, rx in TITLED.items():
            for m in rx.finditer(text):
                parts = [(p.start() + m.start(1), p.end() + m.start(1)) for p in re.finditer(r"\S+", m[1])]
                for i, (a, b) in enumerate(parts):
                    known.setdefault(text[a:b], "surname" if i == len(parts) - 1 else f"given_{gender}")
        if known:
            for m in NAMED.finditer(text):
                word = m[0]
                while word and word not in known:  # a possessive or a compound of a known name
                    word = word[: max(word.rfind(c) for c in "'’-") if any(c in word for c in "'’-") else 0]
                if word:
                    spans.append((m.start(), m.start() + len(word), known[word]))
    order = {k: i for i, k in enumerate(["email", *(k for k, _ in NUMERIC)])}
    spans.sort(key=lambda s: (s[0], -s[1], order.get(s[2], 99)))
    out, free = [], 0
    for s in spans:
        if s[0] >= free:
            out.append(s)
            free = s[1]
    return out


def _permute(x: int, size: int, key: bytes, tweak: bytes) -> int:
    """A keyed permutation of range(size): Feistel rounds on the next even number of bits, walked back into range."""
    half = max(1, ((size - 1).bit_length() + 1) // 2)
    mask, width = (1 << half) - 1, (half + 7) // 8 + 1
    while True:
        left, right = x >> half, x & mask
        for r in range(8):
            data = right.to_bytes(width, "big")
            f = hashlib.blake2b(tweak + bytes([r]) + data, key=key, digest_size=min(64, width)).digest()
            for i in range(64, width, 64):  # every bit of a wide half is mixed
                f += hashlib.blake2b(tweak + bytes([r]) + i.to_bytes(8, "big") + data, key=key, digest_size=min(64, width - i)).digest()
            left, right = right, left ^ (int.from_bytes(f, "big") & mask)
        x = left << half | right
        if x < size:
            return x


def _letters(value: str, alphabets, key: bytes, tweak: bytes, valid) -> str:
    """Permutes value among the strings with the same alphabet at each place for which valid holds."""
    spots = [i for i, a in enumerate(alphabets) if a]
    size = 1
    for i in spots:
        size *= len(alphabets[i])
    out = value
    if size < 2:
        return value
    while True:
        x = 0
        for i in spots:
            x = x * len(alphabets[i]) + alphabets[i].index(out[i])
        x = _permute(x, size, key, tweak)
        chars = list(out)
        for i in reversed(spots):
            x, r = divmod(x, len(alphabets[i]))
            chars[i] = alphabets[i][r]
        out = "".join(chars)
        if valid(out):
            return out


def _script(v: str) -> str:
    return "cyrillic" if any("Ѐ" <= c <= "ӿ" for c in v) else "latin"


def _name(kind: str, value: str, key: bytes, attempt: int) -> str:
    """A name of the same gender and script: listed at first, then composed of two syllables and more."""
    script, part = _script(value), "s" if kind == "surname" else kind[-1]
    h = int.from_bytes(hashlib.blake2b(f"{kind}|{attempt}|".encode() + value.lower().encode(), key=key, digest_size=32).digest(), "big")
    if attempt < LISTED:
        pool = SURNAMES[script] if part == "s" else GIVEN[part, script]
        name = pool[h % len(pool)]
    else:
        h, e = divmod(h, len(ENDINGS[part, script]))
        out = []
        for _ in range(min(20, 2 + (attempt - LISTED) // 4)):
            h, s = divmod(h, len(SYLLABLES[script]))
            out.append(SYLLABLES[script][s])
        name = "".join([*out, ENDINGS[part, script][e]]).capitalize()
    return name.upper() if value.isupper() and len(value) > 1 else name


def _grown(kind: str, value: str, more: int) -> str:
    """The value in a wider format: further characters like one of its own (before the @ of an address)."""
    place = value.index("@") - 1 if kind == "email" else max((i for i, c in enumerate(value) if c in PLACE), default=len(value) - 1)
    return value[: place + 1] + (value[place] if value[place] in PLACE else "0") * more + value[place + 1 :]


def surrogate(kind: str, value: str, key: bytes, attempt: int = 0) -> str:
    """The replacement of a value; another attempt gives another one."""
    if kind in ("surname", "given_m", "given_f"):
        return _name(kind, value, key, attempt)
    if attempt >= MOST_DRAWS:
        value = _grown(kind, value, attempt - MOST_DRAWS + 1)
        kind = kind if kind in ("email", "secret", "key") else "grown"
    tweak = f"{kind}|{attempt}|{len(value)}|".encode()
    fields: list = [PLACE.get(c, (None, 0))[0] for c in value]
    valid = lambda v: True
    if kind == "email":
        dot = value.rindex(".")
        fields[dot:] = [None] * (len(value) - dot)
    elif kind == "secret" and re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", value):
        a = HEX if value == value.lower() else HEX.upper()
        fields = [a] * len(value)
    elif kind in ("ipv4", "ipv6"):
        if kind == "ipv4":
            parts = list(map(int, value.split(".")))
            x = _permute(int.from_bytes(bytes(parts), "big"), 1 << 32, key, b"ip|%d" % attempt)
            return ".".join(map(str, x.to_bytes(4, "big")))
        fields = [None if c == ":" else (HEX if c in HEX else HEX.upper()) for c in value]
    elif kind == "card":
        digits = re.sub(r"\D", "", value)
        places = [i for i, c in enumerate(value) if c.isdigit()]
        fields[places[0]] = fields[places[-1]] = None  # issuer digit and check digit
        checked = luhn(digits[:-1]) == int(digits[-1])
        out = _letters(value, fields, key, tweak + (b"c" if checked else digits[-1].encode()), valid)
        return out[: places[-1]] + str(luhn(re.sub(r"\D", "", out)[:-1])) + out[places[-1] + 1 :] if checked else out
    elif kind == "phone":
        if value.startswith("+"):
            code = len(re.match(r"\d*", value[1:])[0])
            if code > 3:  # no separator after the country code
                code = 1 if value[1] in "17" else 2
            fields[1 : 1 + code] = [None] * code
        first = next((i for i, a in enumerate(fields) if a), 0)
        if value[first] != "0":
            valid = lambda v: v[first] != "0"
    elif kind == "iban":
        fields[:2] = [None, None]
    elif kind == "key":
        lead = 4 if value[:4] in ("AKIA", "ghp_", "gho_", "ghu_", "ghs_", "ghr_") else 3
        fields[:lead] = [None] * lead
    if kind in ("secret", "key") and len(value) > PIECE:  # in pieces, each under a tweak of those before it
        cuts = range(0, len(value), PIECE)
        return "".join(_letters(value[i : i + PIECE], fields[i : i + PIECE], key, tweak + hashlib.blake2b(value[:i].encode(), digest_size=16).digest(), valid) for i in cuts)
    return _letters(value, fields, key, tweak, valid)


def entities(docs: DataFrame, text: str = "text") -> DataFrame:
    """Distinct (kind, value) of the whole corpus."""

    def run(batches):
        for b in batches:
            seen = set()
            for v in b.column(0):
                t = v.as_py()
                if t:
                    seen.update((kind, t[a:z]) for a, z, kind in detect(t))
            rows = sorted(seen)
            yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in rows], pa.string()), pa.array([v for _, v in rows], pa.string())], names=["kind", "value"])

    return docs.select(text).mapInArrow(run, "kind string, value string").distinct()


def exceptions(found: DataFrame, key: bytes) -> DataFrame:
    """(kind, value, attempt) of the values whose first surrogate collides, with an attempt that does not."""
    space = F.when(F.col("kind").startswith("given"), "given").otherwise(F.col("kind"))

    def draw(batches):
        for b in batches:
            ks, vs, ns = (c.to_pylist() for c in b.columns)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([surrogate(k, v, key, n) for k, v, n in zip(ks, vs, ns, strict=True)], pa.string())], names=["kind", "value", "attempt", "other"])

    real = found.select(space.alias("space"), F.col("value").alias("other"), F.lit(True).alias("real"))
    state = materialize(found.withColumn("attempt", F.lit(0)), "pii-state")
    while True:
        drawn = state.mapInArrow(draw, "kind string, value string, attempt int, other string").withColumn("space", space)
        # of equal surrogates, the value with the fewest attempts left (then the first in order) keeps it
        keeper = drawn.groupBy("space", "other").agg(F.min(F.struct((-F.col("attempt")).alias("a"), "kind", "value")).alias("k"), F.count("*").alias("n"))
        clash = keeper.join(real, ["space", "other"], "left").where("n > 1 or real")
        judged = drawn.join(clash, ["space", "other"], "left")
        again = F.coalesce(F.col("real"), F.lit(False)) | (F.col("n") > 1) & ~((F.col("k.kind") == F.col("kind")) & (F.col("k.value") == F.col("value")))
        moved = F.coalesce(again, F.lit(False))
        nxt = materialize(judged.select("kind", "value", (F.col("attempt") + moved.cast("int")).alias("attempt"), moved.alias("moved")), "pii-state")
        release(state)
        state = nxt.select("kind", "value", "attempt")
        state._scratch = nxt._scratch
        if nxt.where("moved").isEmpty():
            return state


def replace(docs: DataFrame, key: bytes | None = None, text: str = "text") -> DataFrame:
    """The documents with surrogates in their text, and n_entities and entity_kinds; key is the caller's secret."""
    key = secrets.token_bytes(32) if key is None else key
    found = materialize(entities(docs, text), "pii-entities")
    state = exceptions(found, key)
    odd = materialize(state.where("attempt > 0"), "pii-odd")
    release(found, state)
    few = odd.count()
    fixed: dict = {}
    if few <= MOST_FIXED:  # checked bound of what is sent to the tasks
        fixed = {(r.kind, r.value): r.attempt for r in odd.collect()}
        source, extra = docs, []
    else:
        place = docs.withColumn("__row", F.xxhash64(text))

        def spots(batches):
            for b in batches:
                rows = {(h, k, t[a:z]) for h, v in zip(b.column(0).to_pylist(), b.column(1), strict=True) if (t := v.as_py()) for a, z, k in detect(t)}
                cols = list(zip(*rows, strict=True)) if rows else [()] * 3
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.string())], names=["__row", "kind", "value"])

        per = place.select("__row", text).mapInArrow(spots, "__row long, kind string, value string").distinct().join(odd, ["kind", "value"]).groupBy("__row").agg(F.map_from_entries(F.collect_list(F.struct(F.concat_ws("|", "kind", "value"), "attempt"))).alias("__odd"))
        source, extra = place.join(materialize(per, "pii-per-doc"), "__row", "left").drop("__row"), ["__odd"]
    names = [c for c in source.columns if c not in extra and c not in ("n_entities", "entity_kinds")]
    at = names.index(text)

    def run(batches):
        for b in batches:
            texts, counts, kinds = [], [], []
            own = b.column(len(names)).to_pylist() if extra else None
            for i, v in enumerate(b.column(at)):
                t = v.as_py()
                spans = detect(t) if t else []
                if spans:
                    odd_here = dict(own[i] or ()) if own else None
                    parts, last = [], 0
                    for a, z, kind in spans:
                        value = t[a:z]
                        n = (odd_here.get(f"{kind}|{value}", 0) if odd_here is not None else fixed.get((kind, value), 0))
                        parts += [t[last:a], surrogate(kind, value, key, n)]
                        last = z
                    t = "".join([*parts, t[last:]])
                texts.append(t)
                counts.append(len(spans))
                kinds.append(",".join(sorted({k for _, _, k in spans})))
            cols = [b.column(i) for i in range(len(names))]
            cols[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays([*cols, pa.array(counts, pa.int64()), pa.array(kinds, pa.string())], names=[*names, "n_entities", "entity_kinds"])

    schema = source.select(*names, *extra).select(*names).schema.add("n_entities", "long").add("entity_kinds", "string")
    return source.select(*names, *extra).mapInArrow(run, schema)


#: Session setting that holds the secret key (text) of the query and of the pipeline.
KEY_SETTING = "spark.lattica.surrogate.key"


def session_key(spark) -> bytes | None:
    """The session's secret key, hashed to the length that the permutation takes."""
    own = spark.conf.get(KEY_SETTING, None)
    return hashlib.blake2b(own.encode(), digest_size=32).digest() if own else None


def op9_pii_surrogates(spark, sf_dir) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return replace(docs, session_key(spark)).select("doc_id", "text", "n_entities", "entity_kinds", F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"))
