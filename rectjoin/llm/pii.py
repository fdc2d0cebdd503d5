"""Personal data replaced by surrogates.

Detected entities are e-mail addresses, telephone numbers, IPv4 addresses, card and social-security numbers,
bank account numbers, secrets, and the parts of names of persons. What has a rule of its own must satisfy it: a card
number its issuer's prefix and check digit, an account number its remainder, a social-security number its ranges;
an address after the word version isn't one. A name is found by its surroundings (a title, or a phrase that
introduces a person) or by a known given name, before capitalised words that aren't those of streets, firms or dates.

An entity's surrogate is made with a key, which the caller must give. Where the entity is a string of letters and
digits it is a keyed permutation of all strings of the same shape (a Feistel network with cycle walking): every
letter stays a letter of its case and alphabet, every digit a digit, separators stay. Check digits are made
anew, addresses stay addresses. Each part of a name has a surrogate of its own, so that a full name and a short
mention of it agree: a known given name becomes another of its gender and script, any other part becomes a word of
syllables of its script, by a permutation of all words that may be.

A permutation never gives two entities one surrogate, however many there are. What could still clash (a surrogate
that is a real entity of the corpus or the entity itself) is found on the table of distinct entities; the entity
takes its next attempt. What clashes after ``KEYED`` attempts is ranked and gets a permuted rank, written in the
format and script of its kind, in a space that grows with the table and with every round, so that a round comes
without a clash. That table is joined, never collected: only texts with an entity that needed another attempt
take part in the join, all others are rewritten in one pass.

Defined results: a null text stays null with 0 entities. Entities are found left to right, the earliest and
then the first kind wins. The same entity, in any case or spacing, always has the same surrogate. Rows that
repeat, or have a null id, are rewritten alike. Texts without entities come back unchanged. All columns are kept; the
number of entities is ``n_entities``, or the first of n_entities_2, n_entities_3 ... that the table hasn't.
"""

from __future__ import annotations

import hashlib
import hmac
import re
import unicodedata
from collections.abc import Iterator
from functools import cache, lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import rows_with, rows_without, sliced, written

ROUNDS = 8
#: Attempts by the key alone, before ranks.
KEYED = 4
#: Given names by script and gender.
GIVEN = {
    ("latin", "f"): "Anna Maria Julia Laura Sarah Emma Marie Sophie Claire Lucia Carmen Elena Ingrid Greta Heidi Nora Alice Emily Grace Olivia Camille Amelie Ines Paula".split(),
    ("latin", "m"): "John Peter Thomas Michael David James Robert Karl Hans Jürgen Pierre Louis Antoine Carlos Miguel Javier Pablo Henry Oscar Felix Martin Andre Hugo Marco".split(),
    ("cyrillic", "f"): "Анна Мария Елена Ольга Наталья Ирина Татьяна Светлана Екатерина Юлия Дарья Полина".split(),
    ("cyrillic", "m"): "Иван Пётр Сергей Андрей Дмитрий Николай Алексей Михаил Борис Владимир Павел Олег".split(),
}
#: More given names that are found, by gender; surrogates don't use them. Names that are common words are left out.
KNOWN = {
    "f": "Linda Mary Patricia Jennifer Elizabeth Barbara Susan Jessica Karen Nancy Lisa Betty Margaret Sandra Ashley Kimberly Donna Michelle Carol Amanda Melissa Deborah Stephanie Rebecca Sharon Cynthia Kathleen Amy Angela Shirley Brenda Pamela Nicole Samantha Katherine Catherine Christine Helen Rachel Carolyn Janet Heather Diane Julie Joyce Victoria Kelly Christina Joan Evelyn Lauren Judith Megan Andrea Cheryl Hannah Jacqueline Martha Gloria Teresa Ann Anne Sara Madison Frances Kathryn Janice Jean Abigail Julie Isabella Charlotte Amelia Mia Ella Zoe Chloe Lucy Ursula Petra Sabine Monika Brigitte Susanne Birgit Gabriele Katharina Johanna Lena Leonie Franziska Anja Silke Martina Nathalie Isabelle Valérie Sylvie Céline Chantal Monique Françoise Hélène Léa Manon Élodie Aurélie Ana Isabel Pilar Rosa Teresa Marta Cristina Beatriz Raquel Lucía Sofía Valentina Ximena Giulia Chiara Francesca Alessandra Fatima Aisha Leila Yasmin Noor Zainab Priya Anjali Sunita Lakshmi Deepa Pooja Mei Xiu Yuki Sakura Yoko Keiko Hye Linh Ngoc Svetlana Olga Natalia Natasha Tatiana Irina Ekaterina Yulia Oksana Katarzyna Agnieszka Małgorzata Zofia Ebru Ayşe Emine Ngozi Amina".split(),
    "m": "William Richard Joseph Charles Christopher Daniel Matthew Anthony Donald Steven Andrew Paul Joshua Kenneth Kevin Brian George Timothy Ronald Jason Edward Jeffrey Ryan Jacob Nicholas Gary Eric Jonathan Stephen Larry Justin Scott Brandon Benjamin Samuel Gregory Alexander Patrick Raymond Dennis Jerry Tyler Aaron Jose José Adam Nathan Zachary Douglas Kyle Noah Ethan Jeremy Walter Christian Keith Roger Terry Sean Gerald Harold Dylan Arthur Lawrence Bryan Billy Bruce Gabriel Joe Logan Albert Willie Alan Vincent Eugene Russell Philip Ralph Roy Louis Liam Lucas Mason Stefan Andreas Klaus Jürgen Wolfgang Günter Dieter Uwe Bernd Heinz Helmut Rainer Matthias Tobias Sebastian Florian Lukas Jonas Maximilian Philipp Friedrich Heinrich Ludwig Jean Jacques Michel Philippe Alain François Bernard Nicolas Laurent Olivier Christophe Frédéric Éric Stéphane Guillaume Mathieu Julien Manuel Antonio Francisco Juan Luis Jesús Jorge Fernando Rafael Sergio Alberto Diego Alejandro Andrés Ricardo Roberto Eduardo Giovanni Giuseppe Luca Matteo Lorenzo Mohammed Mohamed Muhammad Ahmed Ali Omar Hassan Hussein Ibrahim Yusuf Khalid Mustafa Mehmet Raj Rahul Amit Sanjay Arjun Vikram Suresh Ramesh Hiroshi Takashi Kenji Satoshi Haruto Minh Sergei Dmitri Vladimir Ivan Alexei Nikolai Mikhail Boris Igor Oleg Piotr Paweł Krzysztof Andrzej Tomasz Lars Sven Olaf Björn Kwame Chinedu Emeka".split(),
    "": "Wei Li Jing Ming Hui Yan Xin Jun Lei Hao Yong Jie Min Jin Alex Chris Robin Kim Jordan Taylor".split(),
    "f cyrillic": "Людмила Галина Валентина Нина Вера Надежда Любовь Оксана Александра Виктория Ксения Алина Маргарита Анастасия Софья Тамара Лариса Наталия".split(),
    "m cyrillic": "Александр Виктор Юрий Анатолий Валерий Евгений Максим Игорь Константин Роман Антон Денис Никита Артём Кирилл Григорий Георгий Фёдор Петр Василий Вячеслав Станислав Тимур Руслан".split(),
}
#: Titles by gender.
TITLES = {"f": "Mrs Ms Miss Frau Madame Mme Mlle Señora Sra Doña", "m": "Mr Mister Herr Monsieur Señor Sr Don", "": "Dr Prof Doctor Professor"}
#: Words that end a name, or show that there is none.
NO_NAME = frozenset("Street Road Avenue Lane Square Bridge Boulevard Drive University College Institute Hospital Church School Museum Library Airport Station Hotel Inc Ltd LLC GmbH AG SA Corp Corporation Company Foundation Island Islands River Lake Mountain Park Prize Award Day Week Monday Tuesday Wednesday Thursday Friday Saturday Sunday January February March April June July August September October November December Straße Platz Allee Rue Calle Plaza Улица".split())
#: Phrases that introduce a person.
INTRODUCES = r"[Mm]y name is|[Dd]ear|[Ss]igned(?: by)?:?|[Nn]ame:|[Aa]uthor:|[Cc]ontact(?: person)?:|[Rr]egards,|[Ss]incerely,|[Pp]atient:?|[Cc]ustomer:"
#: Parts of invented words by script; a word is read back in one way only, as every syllable starts with one consonant and ends in a vowel or one of the last.
SYLLABLES = {"latin": ("bdfghjklmnprstvwz", "aeiou", ("", "l", "n", "r", "s", "t")), "cyrillic": ("бвгджзклмнпрстфх", "аеиоу", ("", "л", "н", "р", "с", "т"))}
ALPHABETS = ("0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "àáâãäåæçèéêëìíîïñòóôõöøùúûüýÿßœ", "ÀÁÂÃÄÅÆÇÈÉÊËÌÍÎÏÑÒÓÔÕÖØÙÚÛÜÝŒ", "абвгдежзийклмнопрстуфхцчшщъыьэюяё", "АБВГДЕЖЗИЙКЛМНОПРСТУФХЦЧШЩЪЫЬЭЮЯЁ")
_AT = {c: (i, a) for a in ALPHABETS for i, c in enumerate(a)}
_NAME = r"(?:[DLO]['’])?[A-ZÀ-ÖØ-ÞА-ЯЁ][^\W\d_]+(?:[-'’][A-ZÀ-ÖØ-ÞА-ЯЁ]?[^\W\d_]+)*"
_INTRO = rf"(?:{INTRODUCES})\s+"
_TITLE = "|".join(sorted((t for v in TITLES.values() for t in v.split()), key=len, reverse=True))


def any_of(words) -> str:
    """An expression for the longest of some words, branching letter by letter."""
    tails: dict[str, set[str]] = {}
    for w in words:
        tails.setdefault(w[:1], set()).add(w[1:])
    ends = tails.pop("", None) is not None
    out = "|".join(re.escape(c) + (any_of(tail) if tail != {""} else "") for c, tail in sorted(tails.items()))
    return f"(?:{out})?" if ends else f"(?:{out})"


@cache
def given_groups() -> dict[str, tuple[str, ...]]:
    """Known given names, folded: the sorted names of the same script and gender. A name of both genders is of none."""
    genders: dict[tuple[str, str], set[str]] = {}
    for key, names in (*GIVEN.items(), *((("cyrillic" if k.endswith("cyrillic") else "latin", k[:1].strip()), v) for k, v in KNOWN.items())):
        for name in names:
            genders.setdefault((key[0], name.casefold()), set()).add(key[1])
    groups: dict[tuple[str, str], list[str]] = {}
    for (script, name), found in sorted(genders.items()):
        groups.setdefault((script, found.pop() if len(found) == 1 else ""), []).append(name)
    return {name: tuple(names) for names in groups.values() for name in names}


_ALL_GIVEN = {n for v in (*GIVEN.values(), *KNOWN.values()) for n in v}
_GIVEN = any_of(_ALL_GIVEN | {n.upper() for n in _ALL_GIVEN if n.upper().lower() == n.lower()})
KINDS = {
    "email": r"[\w.+-]+@[\w-]+(?:\.[\w-]+)+",
    "secret": r"(?<![\w/+])(?=[a-f0-9]*\d)(?=[a-f0-9]*[a-f])[a-f0-9]{32,64}(?!\w)|(?<!\w)(?:AKIA[A-Z0-9]{16}|gh[pousr]_\w{30,60}|sk-[\w-]{20,80})(?!\w)",
    "iban": r"(?<!\w)[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?!\w)",
    "ip": r"(?<![\w.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\w]|\.\d)",
    "ssn": r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])",
    "card": r"(?<![\w.-])\d(?:[ -]?\d){12,18}(?![\w]|[.-]\d)",
    "phone": r"(?<![\w.])(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)[ .-]?)\d{2,4}(?:[ .-]\d{2,4}){1,3}(?!\w)|(?<![\w.])\+\d{1,3}(?:[ .-]?\d{2,4}){2,5}(?!\w)|(?<![\w.-])\d{3}[.-]\d{3}[.-]\d{4}(?![\w-])",
    "name": rf"(?<!\w)(?:(?:{_TITLE})\b\.?(?:[ ]{_NAME}){{1,3}}|{_GIVEN}(?:[ ]{_NAME}){{1,2}}|{_INTRO}{_NAME}(?:[ ]{_NAME}){{1,2}})(?!\w)",
}
ENTITY = re.compile("|".join(f"(?P<{k}>{p})" for k, p in KINDS.items()))
TITLE = re.compile(rf"(?:{_INTRO})?(?:(?:{_TITLE})\b\.?[ ])?")
VERSION = re.compile(r"(?:[Vv]ersion|[Vv]er\.?|[Rr]elease|[Ss]ection|\b[Vv])\s*$")
#: A part of every entity.
_MAY = re.compile(rf"[@\d]|(?<!\w)(?:AKIA|gh[pousr]_|sk-|(?:{_TITLE}|{_GIVEN}|{INTRODUCES})(?!\w))")


def normal(kind: str, text: str) -> str:
    """What makes two mentions the same entity."""
    if kind in ("email", "secret"):
        return text.lower() if kind == "email" else text
    if kind in ("given", "surname"):
        return text.casefold()
    if kind == "phone":
        return ("+" if text.startswith("+") else "") + re.sub(r"\D", "", text)
    return re.sub(r"[ -]", "", text)


def luhn(digits: str) -> bool:
    return sum(sum(divmod(2 * int(d), 10)) if i % 2 else int(d) for i, d in enumerate(reversed(digits))) % 10 == 0


def card_number(digits: str) -> bool:
    """An issuer's prefix and length, and the check digit."""
    n, two, four = len(digits), int(digits[:2]), int(digits[:4])
    issued = (digits[0] == "4" and n in (13, 16, 19)) or ((51 <= two <= 55 or 2221 <= four <= 2720) and n == 16) or (two in (34, 37) and n == 15)
    issued = issued or (two in (36, 38) and n >= 14) or ((two in (35, 62, 65) or four == 6011 or 6440 <= four <= 6499) and n >= 16)
    return issued and luhn(digits)


def account_remainder(iban: str) -> int:
    """1 for a valid account number."""
    return int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97


def right(kind: str, mention: str, before: str) -> bool:
    """The rule of a kind that a pattern doesn't tell. before: some characters of the text before the mention."""
    norm = normal(kind, mention)
    if kind == "card":
        return card_number(norm)
    if kind == "iban":
        return norm.isascii() and account_remainder(norm) == 1
    if kind == "ssn":
        return norm[:3] not in ("000", "666") and norm[0] != "9" and norm[3:5] != "00" and norm[5:] != "0000"
    return kind != "ip" or not VERSION.search(before)


def name_parts(mention: str) -> list[tuple[int, str, str, str]]:
    """(place in the mention, kind, part, gender) of the parts of a name; none where it's no name."""
    title = TITLE.match(mention)[0]
    words, at = [], len(title)
    for w in mention[at:].split(" "):
        if w.capitalize() in NO_NAME or w in NO_NAME:
            break
        words.append((at, w))
        at += len(w) + 1
    if not words or (len(words) == 1 and (not re.search(rf"(?:{_TITLE})\b\.?[ ]$", title))):
        return []
    if len(words) == 1:
        return [(words[0][0], "surname", words[0][1], "")]
    first = words[0][1]
    gender = "" if first.casefold() in given_groups() else next((g for g, ts in TITLES.items() if g and title.rstrip(". ").split(" ")[-1] in ts.split()), "") if title.strip() else ""
    return [(words[0][0], "given", first, gender), *((a, "surname", w, "") for a, w in words[1:])]


def invented(norm: str, key: bytes, tweak: str, extra: int = 0) -> str:
    """A word of syllables for a word, by a permutation of all words: no two share one. extra: at least so many words beyond its own length's."""
    script = "cyrillic" if re.search("[а-яё]", norm) else "latin"
    starts, vowels, ends = SYLLABLES[script]
    letters = word_letters(script)
    if any(c not in letters for c in norm):
        return same_shape(norm, key, tweak)
    rank = 0
    for c in norm:  # words in the order of their lengths
        rank = rank * len(letters) + letters[c] + 1
    base, below, size = len(starts) * len(vowels) * len(ends), 0, len(starts) * len(vowels) * len(ends)
    while rank >= below + size:
        below, size = below + size, size * base
    x, out = permuted(rank - below, size, key, f"{tweak}|{script}|{size}"), []
    while size > 1:
        x, i = divmod(x, base)
        size //= base
        i, e = divmod(i, len(ends))
        i, v = divmod(i, len(vowels))
        out.append(starts[i] + vowels[v] + ends[e])
    return "".join(out)


@cache
def word_letters(script: str) -> dict[str, int]:
    own = ALPHABETS[1] + ALPHABETS[3] if script == "latin" else ALPHABETS[5]
    return {c: i for i, c in enumerate(own + "-'’")}


def permuted(x: int, size: int, key: bytes, tweak: str) -> int:
    """A keyed permutation of 0 ... size - 1."""
    if size < 2:
        return x
    left = 1 << ((size - 1).bit_length() + 1) // 2
    right = -(-size // left)
    while True:
        a, b, m, n = x // right, x % right, left, right
        for r in range(ROUNDS):
            f = int.from_bytes(hmac.new(key, f"{tweak}|{size}|{r}|{b}".encode(), hashlib.sha256).digest()[:16 + m.bit_length() // 8], "big")
            a, b, m, n = b, (a + f) % m, n, m
        # After an even number of rounds the halves are in their places again.
        x = a * right + b
        if x < size:
            return x


@lru_cache(100_000)
def place(c: str) -> tuple[int, str] | None:
    """A character's place and alphabet. Letters and digits outside ``ALPHABETS`` have those of their kind among their 256 neighbours."""
    if c in _AT or not c.isalnum():
        return _AT.get(c)
    of = lambda d: (d.isalnum(), unicodedata.category(d), d.lower() == d)
    near = "".join(d for d in map(chr, range(ord(c) & ~255, (ord(c) | 255) + 1)) if d not in _AT and of(d) == of(c))
    return near.index(c), near


def same_shape(text: str, key: bytes, tweak: str) -> str:
    """A permutation of the strings of one shape; what is no letter or digit stays."""
    value = size = 0
    for c in text:
        if at := place(c):
            value, size = value * len(at[1]) + at[0], (size or 1) * len(at[1])
    if not size:
        return text
    value, out = permuted(value, size, key, tweak), []
    for c in reversed(text):
        if at := place(c):
            value, i = divmod(value, len(at[1]))
            c = at[1][i]
        out.append(c)
    return "".join(reversed(out))


def numeral(x: int, size: int, signs, least: int = 1) -> str:
    """A number below ``size`` in the given signs; as many for every number."""
    width, n = least, len(signs)
    while n**width < size:
        width += 1
    out = []
    for _ in range(width):
        x, i = divmod(x, n)
        out.append(signs[i])
    return "".join(reversed(out))


def ranked_surrogate(kind: str, norm: str, rank: int, size: int, key: bytes, gender: str = "") -> str:
    """The surrogate of a rank below ``size``, in normal form: no two ranks of a kind share one, nor two sizes unless they need as many signs."""
    tweak = f"{kind}|rank"
    if kind in ("ssn", "card", "phone", "iban"):
        head = {"phone": norm[:1] if norm.startswith("+") else "", "iban": norm[:2]}.get(kind, "")
        width = max(len(norm) - len(head) - (kind == "card"), len(str(size - 1)))
        made = f"{head}{permuted(rank, 10**width, key, tweak):0{width}d}"
        if kind == "card":
            right = next(int(d) for d in "0123456789" if luhn(made + d))
            made += str(right if luhn(norm) else (right + 1) % 10)
        return made
    if kind == "secret":  # signs beyond f aren't hexadecimal
        signs = "0123456789abcdef" if re.fullmatch("[0-9a-f]+", norm) else "ghijklmnopqrstuvwxyz"
        width = len(numeral(0, size, signs, len(norm)))
        return numeral(permuted(rank, len(signs) ** width, key, tweak), size, signs, width)
    x = permuted(rank, size, key, tweak)
    if kind == "ip":
        return ".".join(map(str, x.to_bytes(max(4, -(-(size - 1).bit_length() // 8)), "big")))
    if kind == "email":
        domain, top = norm.rsplit("@", 1)[1].rsplit(".", 1)
        signs = next((at[1] for c in norm if c.isalpha() and (at := place(c)) and len(at[1]) > 1), ALPHABETS[1])
        return f"{numeral(x, size, signs)}@{same_shape(domain, key, tweak)}.{top}"
    script = "cyrillic" if re.search("[а-яё]", norm) else "latin"
    starts, vowels, _ = SYLLABLES[script]  # open syllables, one more than any word of the other way has
    return numeral(x, size, [a + b for a in starts for b in vowels], len(norm) + 1)


def surrogate(kind: str, norm: str, attempt: int, key: bytes, gender: str = "") -> str:
    """The surrogate of a normal form, in normal form."""
    tweak = f"{kind}|{attempt}"
    if kind == "email":
        local, domain = norm.rsplit("@", 1)
        name, top = domain.rsplit(".", 1)
        made = same_shape(f"{local}@{name}", key, tweak)
        return f"{made}.{top}"
    if kind == "ip":
        x = permuted(int.from_bytes(bytes(map(int, norm.split("."))), "big"), 1 << 32, key, tweak)
        return ".".join(map(str, x.to_bytes(4, "big")))
    if kind == "card" and luhn(norm):
        body = norm[:4] + same_shape(norm[4:-1], key, f"{tweak}|{norm[:4]}")  # the issuer stays
        return next(body + d for d in "0123456789" if luhn(body + d))
    if kind == "card":
        made = same_shape(norm, key, tweak)
        while luhn(made):
            made = same_shape(made, key, tweak)
        return made
    if kind == "phone" and norm.startswith("+"):
        return "+" + norm[1] + same_shape(norm[2:], key, tweak)
    if kind == "iban":
        body = same_shape(norm[4:], key, f"{tweak}|{norm[:2]}")
        return f"{norm[:2]}{98 - account_remainder(f'{norm[:2]}00{body}'):02d}{body}"
    if kind == "given" and norm in given_groups():
        names = given_groups()[norm]
        n = len(names)
        place_of = {permuted(i, n, key, tweak): i for i in range(n)}
        at = {i: p for p, i in place_of.items()}
        return names[place_of[(at[names.index(norm)] + 1) % n]]  # the next one of a keyed circle, so never itself
    if kind in ("given", "surname"):
        made = invented(norm, key, tweak)
        return made + {"f": "a", "m": "o"}.get(gender, "") if kind == "given" else made
    if kind == "ssn":
        made = same_shape(norm, key, tweak)
        while right(kind, norm, "") and not right(kind, made, ""):  # walked until it is in the ranges
            made = same_shape(made, key, tweak)
        return made
    if kind == "secret" and re.fullmatch("[0-9a-f]+", norm):
        return f"{permuted(int(norm, 16), 16 ** len(norm), key, tweak):0{len(norm)}x}"
    return same_shape(norm, key, tweak)


def dressed(kind: str, mention: str, made: str) -> str:
    """The surrogate in the format of a mention: its title, case, separators."""
    if kind in ("given", "surname"):
        return made.upper() if len(mention) > 1 and mention.isupper() else made[:1].upper() + made[1:]
    if kind == "email":
        return made.upper() if mention.isupper() else made
    if kind in ("ip", "secret"):
        return made
    chars = iter(made.lstrip("+"))
    return "".join([next(chars, "") if c.isalnum() else c for c in mention]) + "".join(chars)


def entities(text: str | None) -> list[tuple[int, int, str, str]]:
    """(start, end, kind, mention) of a text, from left to right; names whole, with what introduces them."""
    if not text or not _MAY.search(text):
        return []
    return [(m.start(), m.end(), m.lastgroup, m[0]) for m in ENTITY.finditer(text) if (name_parts(m[0]) if m.lastgroup == "name" else right(m.lastgroup, m[0], text[max(0, m.start() - 12) : m.start()]))]


def parts(text: str | None) -> list[tuple[int, int, str, str, str]]:
    """(start, end, kind, mention, gender) of what is replaced: entities, and the parts of names."""
    out = []
    for start, end, kind, mention in entities(text):
        out += [(start + at, start + at + len(w), k, w, g) for at, k, w, g in name_parts(mention)] if kind == "name" else [(start, end, kind, mention, "")]
    return out


def rewritten(text: str | None, key: bytes, others: dict[tuple[str, str], str], known: dict) -> tuple[str | None, int]:
    """The text with surrogates, and their number. others: surrogates that took another attempt."""
    found = parts(text)
    if not found:
        return text, 0
    out, last = [], 0
    for start, end, kind, mention, gender in found:
        norm = normal(kind, mention)
        made = others.get((kind, norm))
        if made is None:
            if len(known) > 200_000:
                known.clear()
            if (made := known.get((kind, norm, gender))) is None:
                made = known[kind, norm, gender] = surrogate(kind, norm, 0, key, gender)
        out += (text[last:start], dressed(kind, mention, made))
        last = end
    return "".join((*out, text[last:])), len(found)


def entity_table(docs: DataFrame) -> DataFrame:
    """Distinct (kind, norm, gender); one gender for a name, so that it has one surrogate."""

    def run(batches):
        seen = set()
        for batch in batches:
            new = {(kind, normal(kind, m), g) for b in sliced([batch]) for text in b.column(0).to_pylist() for _, _, kind, m, g in parts(text)} - seen
            seen = new | (seen if len(seen) < 300_000 else set())
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in (list(zip(*sorted(new))) or [()] * 3)], ["kind", "norm", "gender"])

    return docs.select("text").mapInArrow(run, "kind string, norm string, gender string").groupBy("kind", "norm").agg(F.max("gender").alias("gender"), F.min("gender").alias("_other"))


def _made(table: DataFrame, key: bytes, size: int = 0) -> DataFrame:
    """Surrogates of the table's attempts, or of its ranks below ``size``."""
    columns = ["kind", "norm", "gender", "attempt", "mixed"]

    def run(batches):
        for batch in batches:
            kind, norm, gender, last = (batch.column(c).to_pylist() for c in ("kind", "norm", "gender", "rank" if size else "attempt"))
            made = [ranked_surrogate(k, n, x, size, key, g) if size else surrogate(k, n, x, key, g) for k, n, g, x in zip(kind, norm, gender, last)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in columns), pa.array(made, pa.string())], [*columns, "made"])

    return table.select(*columns, *(["rank"] if size else [])).mapInArrow(run, "kind string, norm string, gender string, attempt int, mixed boolean, made string")


def _ranked(table: DataFrame) -> DataFrame:
    """The table with the ranks 0 ... n - 1 of (kind, norm); only the rows of each partition are counted in the driver."""
    placed = written(table.orderBy("kind", "norm").withColumn("_at", F.monotonically_increasing_id()), "placed")
    part = F.shiftright("_at", 33)
    first, before = [(-1, 0)], 0
    for p, n in sorted(tuple(x) for x in placed.groupBy(part.alias("_part")).count().collect()):
        first.append((p, before))
        before += n
    starts = table.sparkSession.createDataFrame(first, "_part long, _first long")
    return placed.withColumn("_part", part).join(F.broadcast(starts), "_part").withColumn("rank", F.col("_first") + F.col("_at").bitwiseAND((1 << 33) - 1)).drop("_part", "_first", "_at")


def surrogates(docs: DataFrame, key: bytes) -> DataFrame:
    """(kind, norm, made, attempt, mixed) for every distinct entity, without a clash."""
    table = entity_table(docs).select("kind", "norm", "gender", F.lit(0).alias("attempt"), (F.col("gender") != F.col("_other")).alias("mixed"))
    table = written(_made(table, key), "surrogates")
    tries = size = 0
    while True:
        # Of those with one surrogate the smallest stays; nobody may get a real entity, but for given names, which many have.
        shared = table.groupBy("kind", "made").agg(F.min("norm").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("kind", "made", "first")
        real = table.where("kind != 'given'").select("kind", F.col("norm").alias("made"), F.lit(True).alias("real"))
        marked = table.join(shared, ["kind", "made"], "left").join(real, ["kind", "made"], "left")
        clash = F.coalesce(F.col("real"), F.lit(False)) | (F.col("first").isNotNull() & (F.col("first") != F.col("norm")))
        marked = written(marked.withColumn("clash", clash), "marked")
        if not marked.where("clash").limit(1).count():
            return marked.select("kind", "norm", "made", "attempt", "mixed")
        tries += 1
        again = marked.where("clash").withColumn("attempt", F.col("attempt") + 1)
        if tries >= KEYED:  # each round has longer surrogates than the last, soon longer than any entity
            size = 1024 * (size or table.count())
        again = _made(_ranked(again) if size else again, key, size)
        table = written(marked.where("NOT clash").select(*again.columns).unionByName(again), "surrogates")


def free_name(wanted: str, taken: list[str]) -> str:
    names = {c.lower() for c in taken}
    return next(n for k in range(1, len(names) + 2) if (n := wanted if k == 1 else f"{wanted}_{k}").lower() not in names)


def replace(docs: DataFrame, key: bytes, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` with surrogates in their text, and their number as the last column."""
    if not key:
        raise ValueError("surrogates need a key")
    quoted = lambda c: F.col(f"`{c.replace('`', '``')}`")
    count, tid, held = (free_name(x, docs.columns) for x in ("n_entities", "__tid", "__map"))
    table = surrogates(docs.select(quoted(text_col).alias("text")), key)
    # Surrogates that the plain pass wouldn't make by itself.
    other = written(table.where("attempt > 0 OR mixed").select("kind", "norm", "made"), "other-attempts")
    result = "struct<text:string,n:bigint>"

    def made(texts, maps, known) -> pa.Array:
        rows = [rewritten(t, key, {(x["kind"], x["norm"]): x["made"] for x in m or ()}, known) for t, m in zip(texts, maps)]
        return pa.StructArray.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int64())], ["text", "n"])

    @F.arrow_udf(result)
    def plainly(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        known: dict = {}
        for texts in arrays:
            yield pa.concat_arrays([made(part.to_pylist(), [None] * len(part), known) for at in range(0, max(1, len(texts)), 1000) for part in [texts.slice(at, 1000)]])

    @F.arrow_udf(result)
    def by_table(arrays: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
        known: dict = {}
        for texts, maps in arrays:
            yield made(texts.to_pylist(), maps.to_pylist(), known)

    def replaced(rows: DataFrame, new) -> DataFrame:
        return rows.select(*((new["text"].alias(c) if c == text_col else quoted(c)) for c in docs.columns), new["n"].alias(count))

    if not other.limit(1).count():
        return replaced(docs, plainly(quoted(text_col)))

    def mentions(batches):
        for batch in sliced(batches):
            rows = [(t, k, n) for t, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()) for k, n in {(k, normal(k, m)) for _, _, k, m, _ in parts(text)}]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in (list(zip(*rows)) or [()] * 3)], [tid, "kind", "norm"])

    digest = F.sha2(F.coalesce(quoted(text_col), F.lit("")), 256).alias(tid)
    inside = docs.select(digest, quoted(text_col)).mapInArrow(mentions, f"{tid} string, kind string, norm string").distinct()
    need = written(inside.join(other, ["kind", "norm"]), "other-mentions")
    maps = need.groupBy(tid).agg(F.collect_list(F.struct("kind", "norm", "made")).alias(held))  # at most a text's entities
    keyed = docs.select(*(quoted(c) for c in docs.columns), digest)
    ids = need.select(tid).distinct()
    direct = replaced(rows_without(keyed, ids, tid), plainly(quoted(text_col)))
    mapped = rows_with(keyed, ids, tid).join(maps, tid)
    return direct.unionByName(replaced(mapped, by_table(quoted(text_col), F.col(held))))
