"""Surrogates for personal data.

Detected entities: e-mail addresses in any script, telephone numbers, payment card numbers (by their check digit), IPv4
addresses, US social security numbers, IBANs (by their check digits) and personal names. Each is replaced by a keyed
surrogate of its type and format.

Numbers and letters go through keyed permutations without fixed points: a Feistel network, one step on, and the
network backwards, which moves every string along a single cycle; where a class must be kept (a public address, a valid
area) the cycle is walked on to its next member. So equal values get equal surrogates in all documents, different values
never meet, no value stays as it is, and none of this needs a table. Phones are permuted in their national digits whatever
their punctuation, cards keep brand digit and check digit, addresses stay in their class of network, e-mail hosts end in
the reserved domain ``example``. An address part with letters of other scripts than Latin and Cyrillic becomes a keyed
code of 80 bits.

Names are found by structure: a title before capitalised words, a known given name, a verb of speech or action beside
two or more capitalised words, a phrase of introduction, a salutation, a closing formula, a field label, an e-mail address
beside or spelling the name, and a name joined to a found one. Later bare mentions of the parts of a found name are replaced, too.
A part's surrogate depends on the key and the part alone: known given names move along a keyed cycle of the names of
their gender and script, known surnames along that of theirs; any other part has its vowels and consonants permuted each
among themselves, keeps the letter that tells a given name's gender and the ending of a Cyrillic surname, and never
becomes a known name. So people keep one surrogate over the corpus and never share one; a check in each text makes sure of it.

Defined results: null stays null, text without entities is unchanged; of overlapping matches numbers and addresses go before
names, then the leftmost counts, then the order of KINDS, without candidates that fail their check; repeated rows are treated
alike; other columns are kept by ``anonymise`` and the columns
it adds take the place of ones with the same name. Texts of any length are treated whole.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from vpcoreset.llm.common import trimmed

# Names by script and gender, and surnames (Cyrillic ones in the male form). They lend natural spellings; detection does not end with them.
GIVEN = {
    ("latin", "m"): "James John Robert Michael William David Richard Thomas Charles Daniel Matthew Anthony Steven Paul Andrew Kevin Brian George Edward Peter Hans Klaus Jürgen Pierre Jacques Carlos Miguel Javier Juan Luis José Marco Giovanni Ahmed Mohammed Ali Wei Hiroshi Raj Ivan Lukas Felix",
    ("latin", "f"): "Mary Patricia Jennifer Linda Elizabeth Barbara Susan Jessica Sarah Karen Nancy Margaret Sandra Ashley Emily Michelle Carol Amanda Laura Helen Ursula Heike Brigitte Nathalie Camille Carmen Lucía Pilar Maria Anna Sofia Giulia Fatima Aisha Yuki Priya Olga Emma Julia Sophie Marie Lena",
    ("cyrillic", "m"): "Александр Дмитрий Сергей Андрей Алексей Михаил Николай Владимир Иван Пётр",
    ("cyrillic", "f"): "Анна Мария Елена Ольга Наталья Татьяна Ирина Светлана Екатерина Юлия",
}
SURNAMES = {
    "latin": "Smith Johnson Williams Brown Jones Miller Davis Wilson Anderson Taylor Moore Jackson Martin Thompson White Harris Clark Lewis Robinson Walker Young Allen King Wright Scott Hill Green Adams Baker Nelson Carter Mitchell",
    "cyrillic": "Иванов Смирнов Кузнецов Попов Васильев Петров Соколов Михайлов Новиков Фёдоров Морозов Волков",
}
TITLES = "Mr Mrs Ms Miss Dr Prof Herr Frau Señor Señora Monsieur Madame Sr Sra Mme Sir Lady господин госпожа Господин Госпожа".split()
#: Verbs beside which two capitalised words are a person, and phrases, formulas and labels before a name.
VERBS = (
    "said says asked replied wrote writes told added explained called met visited lives works worked joined signed sent emailed phoned thanked thinks believes left arrived answered "
    "sagte sagt schrieb fragte erklärte antwortete traf rief wohnt arbeitet dit écrit demande répond habite travaille dijo dice escribió respondió vive trabaja "
    "сказал сказала написал написала говорит ответил ответила ушёл ушла ушли живёт работает").split()
BEFORE = "said says asked told met sagte dijo traf".split()
INTRODUCED = ("name is", "Name ist", "am called", "heiße", "m'appelle", "me llamo", "Me llamo", "nombre es", "зовут", "I am", "I'm", "bin", "soy", "suis")
GREETED = "Dear Hello Hi Liebe Lieber Cher Chère Estimado Estimada Querido Querida Уважаемый Уважаемая".split()
CLOSED = ("Regards", "regards", "Sincerely", "sincerely", "faithfully", "truly", "wishes", "Cheers", "Thanks", "Grüßen", "Grüße", "Cordialement", "Saludos", "Atentamente", "уважением")
LABELS = "Name Author From To Contact Patient Customer Client Employee Attn Kunde Nombre Nom Имя name author contact".split()
JOINED = ("and", "und", "et", "y", "и", "&", "with", "mit")
#: Capitalised words that open sentences or name no person.
OPENERS = frozenset([*TITLES, *"Later Soon Finally Meanwhile However Also Now Once Last Next Every Each Some Most Many My Your His Her Our Their Mein Meine Mon Ma Mi Später Dann Puis Ensuite Luego Después Потом Затем Г-н Г-жа The This That These Those When While Then Yesterday Today Tomorrow After Before But And Or As If In On At For From Of It He She They We You Who Sir Madam Customer All Team Friends Reader World Der Die Das Und Aber Als Gestern Heute Le La Les Un Une Et Mais Hier El Los Las Pero Ayer Hoy Y В На Но А И Он Она Вчера Сегодня".split()])
_GIVEN = {k: v.split() for k, v in GIVEN.items()}
_SURNAMES = {k: v.split() for k, v in SURNAMES.items()}
_GENDER = {name: key for key, names in _GIVEN.items() for name in names}
_LISTED = frozenset(x.lower() for x in [*_GENDER, *_SURNAMES["latin"], *_SURNAMES["cyrillic"]])

KINDS = ("email", "iban", "card", "phone", "ssn", "ip", "name")
_HOST = r"[^\W_](?:[\w-]*[^\W_])?"
PATTERN = re.compile(
    rf"(?P<email>(?<![\w.%+-])[\w.%+-]+@{_HOST}(?:\.{_HOST})+)"
    r"|(?P<iban>\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b)"
    r"|(?P<card>(?<![\w.+-])[0-9](?:[ -]?[0-9]){12,18}(?![\w]|[.-][0-9]))"
    r"|(?P<phone>(?<![\w.])(?:\+[0-9]{1,3}[ .-]?(?:\([0-9]{1,4}\)|[0-9]{1,4})(?:[ .-]?[0-9]{2,4}){2,4}|\([0-9]{3}\) ?[0-9]{3}[.-][0-9]{4}|[0-9]{3}[.-][0-9]{3}[.-][0-9]{4}"
    r"|\(?0[1-9][0-9]{1,3}\)?[ /-]{1,3}[0-9]{3,8}(?:[ -][0-9]{2,5}){0,2}|0[1-9](?:[ .][0-9]{2}){4})(?!\w))"
    r"|(?P<ssn>(?<![\w-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-]))"
    r"|(?P<ip>(?<![\w.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?!\w|\.[0-9]))"
)
#: Each kind alone, for candidates of another kind that fail their check.
ALONE = {kind: re.compile(PATTERN.pattern[m.start() :].split("|(?P<")[0]) for kind in KINDS if (m := re.search(rf"\(\?P<{kind}>", PATTERN.pattern))}
#: A text without any of these cannot hold a number or an address; the test is far cheaper than the pattern.
HINT = re.compile(r"@|[0-9][0-9./() +-]{5,}[0-9]|\b[A-Z]{2}[0-9]{2}")

_U, _L = "A-ZÀ-ÖØ-ÞŁŚŠŽŻŹČĆĐŘА-ЯЁІЇЄ", "a-zß-öø-ÿąćęłńśźżčšžđřěůıа-яёіїє"
WORD = rf"(?:[{_U}]['’])?(?:Mc|Mac)?[{_U}][{_L}]+(?:-[{_U}]?[{_L}]+|['’][{_U}][{_L}]+)*"
_LINK = "(?:van|von|de|del|der|den|di|da|dos|la|le|el|bin|ibn|al|ter|zu)"
_MORE = rf"(?: [{_U}]\.)?(?: (?:{_LINK} ){{0,2}}{WORD})"
_END = rf"(?![{_L}{_U}])"
FULL, ONE = rf"{WORD}{_MORE}{{1,3}}{_END}", rf"{WORD}{_MORE}{{0,3}}{_END}"


def _any(words) -> str:
    return "|".join(sorted(map(re.escape, words), key=len, reverse=True))


#: Each has the name as its group 1.
CUES = tuple(map(re.compile, (
    rf"\b(?:{_any(TITLES)})\.? ({ONE})",
    rf"\b({FULL}),? (?:{_any(VERBS)})\b",
    rf"\b(?:{_any(BEFORE)}) ({FULL})",
    rf"\b(?:{_any(INTRODUCED)}) ({FULL})",
    rf"\b(?:{_any(x for x in INTRODUCED if x.endswith(('is', 'ist', 'es', 'heiße', 'appelle', 'llamo', 'зовут')))}) ({ONE})",
    rf"\b(?:{_any(GREETED)}) ({FULL}|{WORD}(?=[,!]))",
    rf"\b(?:{_any(CLOSED)})[,.!]?\s+({FULL}|{WORD}(?=\s*(?:\n|$)))",
    rf"\b(?:{_any(LABELS)}):\s?({FULL})",
    rf"\b({FULL}) [<(](?=[\w.%+-]+@)",
)))
RUN, NAME_WORD = re.compile(rf"\b{FULL}"), re.compile(rf"\b{WORD}{_END}")
NEXT = re.compile(rf",? (?:{_any(JOINED)}) ({FULL})")
PARTS_OF_MAIL = re.compile(rf"(?<![\w.%+-])([{_L}]{{2,}})[._]([{_L}]{{2,}})[0-9]*@", re.I)
#: Single words of which a text must hold one, bare or with a mark after or before it, to hold a name that is not beside an address; labels count with their colon.
CUE_WORDS = (*TITLES, *VERBS, *BEFORE, *"name Name called heiße m'appelle llamo nombre зовут am I'm bin soy suis".split(), *GREETED, *CLOSED)


def _marked(words) -> set[str]:
    return {f"{a}{w}{b}" for w in words for a in ("", "(", '"') for b in ("", ".", ",", ":", ";", "!", "?", '"', ")")}


FOUND = T.ArrayType(T.StructType([T.StructField("kind", T.StringType()), T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())]))
DIGITS, LETTERS, CYRILLIC = "0123456789", "abcdefghijklmnopqrstuvwxyz", "абвгдежзийклмнопрстуфхцчшщъыьэюяё"


class Keyed:
    """Keyed permutations and choices."""

    def __init__(self, key: bytes):
        self.key = hashlib.blake2b(key, digest_size=32).digest()

    def number(self, *parts: object) -> int:
        return int.from_bytes(hashlib.blake2b("\x1f".join(map(str, parts)).encode("utf-8", "surrogatepass"), key=self.key, digest_size=16).digest(), "big")

    def permute(self, text: str, alphabet: str, tweak: str) -> str:
        """A permutation of the strings of this length over the alphabet, without fixed points: one long cycle."""
        base, n = len(alphabet), len(text)
        if n == 0:
            return text
        value = [alphabet.index(c) for c in text]
        if n == 1:
            order = sorted(range(base), key=lambda i: self.number("one", tweak, i))
            return alphabet[order[(order.index(value[0]) + 1) % base]]
        u = n // 2
        read = lambda part: sum(d * base**i for i, d in enumerate(part))
        a, b, sizes = read(value[:u]), read(value[u:]), (base**u, base ** (n - u))
        for turn in (1, -1):
            for r in range(10) if turn == 1 else reversed(range(10)):
                if r % 2:
                    b = (b + turn * self.number("round", tweak, n, r, a)) % sizes[1]
                else:
                    a = (a + turn * self.number("round", tweak, n, r, b)) % sizes[0]
            if turn == 1:  # one step on
                b, a = divmod((a + sizes[0] * b + 1) % (sizes[0] * sizes[1]), sizes[0])
        return "".join(alphabet[a // base**i % base] for i in range(u)) + "".join(alphabet[b // base**i % base] for i in range(n - u))

    def next_of(self, member: str, members: list[str], tweak: str) -> str:
        """The member that follows on a keyed cycle of the list."""
        order = sorted(members, key=lambda x: (self.number("order", tweak, x), x))
        return order[(order.index(member) + 1) % len(order)]

    def walk(self, text: str, alphabet: str, tweak: str, same) -> str:
        """Permutes until the class of the text returns: again one cycle, of that class."""
        kind, now = same(text), self.permute(text, alphabet, tweak)
        while same(now) != kind:
            now = self.permute(now, alphabet, tweak)
        return now


def luhn(digits: str) -> bool:
    odd, even = digits[-1::-2], digits[-2::-2]
    return (sum(map(int, odd)) + sum(sum(divmod(2 * int(d), 10)) for d in even)) % 10 == 0


def iban_valid(text: str) -> bool:
    return int("".join(str(int(c, 36)) for c in text[4:] + text[:4])) % 97 == 1


def _refill(form: str, chars: str, members: str) -> str:
    """The form with its members replaced, in order, case kept."""
    it = iter(chars)
    return "".join((c2.upper() if c.isupper() else c2) if c.lower() in members and (c2 := next(it)) else c for c in form)


def _network(octets: str) -> str:
    a, b = int(octets[:3]), int(octets[3:6])
    if any(int(octets[i : i + 3]) > 255 for i in (0, 3, 6, 9)):
        return "none"
    for kind, inside in (("zero", a == 0), ("private10", a == 10), ("loop", a == 127), ("link", (a, b) == (169, 254)), ("private172", a == 172 and 16 <= b < 32), ("private192", (a, b) == (192, 168)), ("multi", 224 <= a < 240), ("reserved", a >= 240)):
        if inside:
            return kind
    return "public"


#: Letters that are permuted among themselves.
CLASSES = ("bcdfghjklmnpqrstvwxz", "aeiouy", "çñßśšžźżčćđłńř", "àáâãäåæèéêëìíîïòóôõöøùúûüýÿąęěůı", "бвгджзйклмнпрстфхцчшщ", "аеёиоуыэюяіїє", "ъь")
#: Endings of Cyrillic surnames: the part that tells the gender.
ENDING = re.compile("(?:ов|ев|ёв|ин|ын)а?$|[сц]к(?:ий|ая)$|(?:ий|ая|ый|ой)$")


def _ending(word: str) -> tuple[str, str]:
    """Stem and ending of a surname; the ending is empty but for Cyrillic ones."""
    m = ENDING.search(word)
    return (word[: m.start()], m.group()) if m and m.start() > 1 else (word, "")


class Surrogates:
    """Replaces the entities of one text; what replaces what depends on the key alone."""

    def __init__(self, key: str, names: dict[tuple[str, str], str] | None = None):
        self.keyed = Keyed(key.encode())
        self.given = {k: list(dict.fromkeys([*v, *(names or {}).get(k, "").split()])) for k, v in _GIVEN.items()}
        self.gender = {n: k for k, v in self.given.items() for n in v}
        self.listed = _LISTED | {n.lower() for n in self.gender}
        self.cues = _marked([*CUE_WORDS, *self.gender]) | {f"{w}:" for w in LABELS}
        self.memo: dict[tuple[str, str], str | None] = {}

    def _address(self, part: str, form: str, tweak: str) -> str:
        """Letters and digits of a part of an address, each permuted in its alphabet; ``form`` is the spelling that keeps its case."""
        sets = (LETTERS, DIGITS, CYRILLIC)
        if any(c.isalnum() and not any(c in s for s in sets) for c in part):
            return "x" + "".join(LETTERS[b % 16] + LETTERS[b // 16] for b in self.keyed.number("address", tweak, part).to_bytes(16, "big")[:10])
        shape = "".join(next((str(i) for i, s in enumerate(sets) if c in s), c) for c in part)
        for s in sets:
            form = _refill(form, self.keyed.permute("".join(c for c in part if c in s), s, f"{tweak}:{shape}"), s)
        return form

    def email(self, text: str) -> str:
        local, host = text.rsplit("@", 1)
        return f"{self._address(local.lower(), local, 'local')}@{self._address(host.lower(), host.lower(), 'host')}.example"

    def iban(self, text: str) -> str | None:
        plain = text.replace(" ", "")
        if not iban_valid(plain):
            return None
        body = plain[4:]
        form = "".join("9" if c.isdigit() else "A" for c in body)
        digits = self.keyed.permute("".join(c for c in body if c.isdigit()), DIGITS, f"iban:{plain[:2]}:{form}")
        letters = self.keyed.permute("".join(c.lower() for c in body if not c.isdigit()), LETTERS, f"iban:{plain[:2]}:{form}")
        body = _refill(_refill(body, digits, DIGITS), letters, LETTERS)
        check = 98 - int("".join(str(int(c, 36)) for c in body + plain[:2] + "00")) % 97
        return _refill(text, (plain[:2] + f"{check:02d}" + body).lower(), DIGITS + LETTERS)

    def card(self, text: str) -> str | None:
        digits = "".join(c for c in text if c in DIGITS)
        if not luhn(digits):
            return None
        middle = self.keyed.permute(digits[1:-1], DIGITS, f"card:{digits[0]}")
        body = digits[0] + middle
        check = next(c for c in DIGITS if luhn(body + c))
        return _refill(text, body + check, DIGITS)

    def phone(self, text: str) -> str | None:
        digits = "".join(c for c in text if c in DIGITS)
        country = digits[:-10] if len(digits) > 10 else ""
        country = "" if country == "1" else country  # the same line, written with or without the country
        local = digits[len(digits) - 10 :] if len(digits) > 10 else digits
        if len(local) < 7:
            return None
        local = self.keyed.walk(local, DIGITS, f"phone:{country}", lambda x: x[0] == "0")
        return _refill(text, digits[: len(digits) - len(local)] + local, DIGITS)

    def ssn(self, text: str) -> str:
        good = lambda x: x[:3] not in ("000", "666") and x[0] != "9" and x[3:5] != "00" and x[5:] != "0000"
        return _refill(text, self.keyed.walk(text.replace("-", ""), DIGITS, "ssn", good), DIGITS)

    def ip(self, text: str) -> str | None:
        octets = "".join(f"{int(x):03d}" for x in text.split("."))
        if _network(octets) in ("none", "zero", "loop"):
            return None
        code = "".join(f"{int(octets[i : i + 3]):02x}" for i in (0, 3, 6, 9))
        spell = lambda c: "".join(f"{int(c[i : i + 2], 16):03d}" for i in (0, 2, 4, 6))
        if _network(octets) != "public":  # small classes: only the free part is permuted
            keep = 2 if _network(octets) in ("private10", "multi", "reserved") else 4
            free = self.keyed.permute(code[keep:], DIGITS + "abcdef", f"ip:{code[:keep]}")
            code = code[:keep] + free
        else:
            code = self.keyed.walk(code, DIGITS + "abcdef", "ip", lambda c: _network(spell(c)))
        return ".".join(str(int(spell(code)[i : i + 3])) for i in (0, 3, 6, 9))

    def _spelled(self, word: str, tweak: str, fits) -> str:
        """A word with the letters of each class permuted among themselves, the first one that ``fits`` as the word itself does."""
        now = low = word.lower()
        if len(low) != len(word) or not any(c in letters for c in low for letters in CLASSES):
            return "X" + "".join(LETTERS[b % 26] for b in self.keyed.number(tweak, word).to_bytes(16, "big"))
        shape = "".join(next((str(i) for i, s in enumerate(CLASSES) if c in s), c) for c in low)
        while True:
            told = ""
            for i, letters in enumerate(CLASSES):
                own = "".join(c for c, k in zip(now, shape, strict=True) if k == str(i))
                moved = iter(self.keyed.permute(own, letters, f"{tweak}:{shape}:{told}"))
                now = "".join(next(moved) if k == str(i) else c for c, k in zip(now, shape, strict=True))
                told += own + "|"
            if fits(now):
                return "".join(c.upper() if o.isupper() else c for c, o in zip(now, word, strict=True))

    def given_name(self, word: str) -> str:
        if word in self.gender:
            key = self.gender[word]
            return self.keyed.next_of(word, self.given[key], f"given:{key}")
        stem, last = (word[:-1], word[-1]) if len(word) > 3 else (word, "")
        return self._spelled(stem, f"given:{last.lower()}", lambda x: x + last.lower() not in self.listed) + last

    def family_name(self, word: str) -> str:
        for script, names in _SURNAMES.items():
            if word in names:
                return self.keyed.next_of(word, names, f"family:{script}")
            if script == "cyrillic" and word.endswith("а") and word[:-1] in names:
                return self.keyed.next_of(word[:-1], names, f"family:{script}") + "а"
        stem, end = _ending(word)
        return self._spelled(stem, "family", lambda x: _ending(x + end) == (x, end) and not {x + end, (x + end).removesuffix("а")} & self.listed) + end

    def _people(self, text: str, taken: list[tuple[str, int, int]]) -> list[tuple[int, int, str]]:
        """(start, end, role) of words of names, sorted; role is given or family."""
        spans: list[tuple[int, int, bool]] = []
        for no, cue in enumerate(CUES):
            spans += [(m.start(1), m.end(1), no == 0) for m in cue.finditer(text)]
        mails = {(m.group(1).lower(), m.group(2).lower()) for k, a, b in taken if k == "email" and (m := PARTS_OF_MAIL.match(text, a))}
        for run in RUN.finditer(text):
            words = [m.group() for m in NAME_WORD.finditer(run.group())]
            first = next((i for i, w in enumerate(words[:-1]) if w in self.gender), None)
            pair = next((i for i in range(len(words) - 1) if (words[i].lower(), words[i + 1].lower()) in mails), None)
            if first is not None or pair is not None:
                at = [m.start() for m in NAME_WORD.finditer(run.group())]
                spans.append((run.start() + at[min(x for x in (first, pair) if x is not None)], run.end(), False))
        for a, b, _ in list(spans):  # a name joined to a found one, and so on
            while m := NEXT.match(text, b):
                spans.append((m.start(1), m.end(1), False))
                b = m.end(1)
        found: dict[tuple[int, int], str] = {}
        known: dict[str, str] = {}
        runs = [([(a + m.start(), a + m.end(), m.group()) for m in NAME_WORD.finditer(text[a:b])], titled) for a, b, titled in set(spans)]
        for words, titled in sorted(runs, key=lambda x: (len(x[0]) < 2, not x[1], x[0])):
            surname = titled or len(words) > 1
            while words and words[0][2] in OPENERS:
                words = words[1:]
            for i, (x, y, w) in enumerate(words):
                alone = len(words) == 1
                role = "given" if (w in self.gender or not surname if alone else i < len(words) - 1) else "family"
                found.setdefault((x, y), known.get(w, role) if alone else role)
                if len(w) > 1:
                    known[w] = "family" if role == "family" or known.get(w) == "family" else "given"
        if known:
            for m in NAME_WORD.finditer(text):
                if m.group() in known and m.group() not in OPENERS:
                    found.setdefault((m.start(), m.end()), known[m.group()])
        held = sorted((a, b) for _, a, b in taken)
        out, i, last = [], 0, 0
        for (a, b), role in sorted(found.items()):
            while i < len(held) and held[i][1] <= a:
                i += 1
            if a >= last and not (i < len(held) and held[i][0] < b):
                out.append((a, b, role))
                last = b
        return out

    def _remembered(self, kind: str, value: str) -> str | None:
        if (kind, value) not in self.memo:
            if len(self.memo) > 1 << 17:
                self.memo.clear()
            self.memo[kind, value] = getattr(self, kind)(value)
        return self.memo[kind, value]

    @staticmethod
    def _candidates(text: str, m: re.Match) -> Iterator[tuple[str, int]]:
        """(kind, end) of a match, then without its last groups after a space, then of the kinds that follow, at the same start."""
        start = m.start()
        for kind in list(ALONE)[list(ALONE).index(m.lastgroup) :]:
            if found := m if kind == m.lastgroup else ALONE[kind].match(text, start):
                end = found.end()
                yield kind, end
                while kind in ("iban", "card") and (end := text.rfind(" ", start, end)) > start:
                    if ALONE[kind].fullmatch(text, start, end):
                        yield kind, end

    def _values(self, text: str) -> list[tuple[str, int, int, str]]:
        """(kind, start, end, surrogate) of numbers and addresses."""
        out, search = [], 0
        while m := PATTERN.search(text, search):
            for kind, end in self._candidates(text, m):
                if (new := self._remembered(kind, text[m.start() : end])) is not None:
                    out.append((kind, m.start(), end, new))
                    search = end
                    break
            else:  # of no kind after all: go on behind its first run of digits or letters
                search = m.start() + max(1, len(re.match(r"\w*", m.group()).group()))
        return out

    def __call__(self, text: str | None) -> tuple[str | None, list[tuple[str, int, int]]]:
        """The text with surrogates, and (kind, start, end) of the entities in the original."""
        if not text:
            return text, []
        values = self._values(text) if HINT.search(text) else []
        people = []
        if not self.cues.isdisjoint(text.split()) or any(k == "email" for k, *_ in values):
            people = self._people(text, [v[:3] for v in values])
        if not values and not people:
            return text, []
        made = [("name", a, b, self._remembered("given_name" if role == "given" else "family_name", text[a:b])) for a, b, role in people]
        told: dict[str, str] = {}
        for i, ((a, b, role), (*_, new)) in enumerate(zip(people, made, strict=True)):
            while told.setdefault(f"{role} {new}", text[a:b]) != text[a:b]:  # only codes of foreign letters could meet
                new += LETTERS[self.keyed.number("again", new) % 26]
            made[i] = ("name", a, b, new)
        out, at = [], 0
        for _, a, b, new in sorted([*values, *made], key=lambda x: x[1]):
            out += [text[at:a], new]
            at = b
        # Words of one name count as one entity.
        spans: list[tuple[str, int, int]] = []
        for kind, a, b, _ in sorted([*values, *made], key=lambda x: x[1]):
            if kind == "name" and spans and spans[-1][0] == "name" and re.fullmatch(rf" (?:[{_U}]\. )?(?:{_LINK} ){{0,2}}", text[spans[-1][2] : a]):
                spans[-1] = ("name", spans[-1][1], b)
            else:
                spans.append((kind, a, b))
        return "".join([*out, text[at:]]), spans


def anonymise(docs: DataFrame, *, text_col: str = "text", key: str = "surrogates", found_col: str | None = None, names: dict[tuple[str, str], str] | None = None) -> DataFrame:
    """docs, all columns, with surrogates in the text column; ``found_col`` adds the entities of the original, ``names`` more given names, spaced, by (script, gender)."""
    if found_col in docs.columns:
        docs = docs.drop(found_col)
    at = docs.columns.index(text_col)
    schema = T.StructType([*docs.schema.fields, *([T.StructField(found_col, FOUND)] if found_col else [])])
    found_type = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))

    def replace(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        act = Surrogates(key, names)
        for batch in batches:
            done = [act(x) for x in batch.column(at).to_pylist()]
            columns, titles = list(batch.columns), list(batch.schema.names)
            columns[at] = pa.array([t for t, _ in done], pa.string())
            if found_col:
                columns.append(pa.array([[{"kind": k, "start": a, "end": b} for k, a, b in s] for _, s in done], found_type))
                titles.append(found_col)
            yield pa.RecordBatch.from_arrays(columns, titles)

    return docs.mapInArrow(trimmed(replace), schema)
