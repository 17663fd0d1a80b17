"""Corruption operators as array expressions.

A text is cut into units (lines, sentences, words or characters); an operator
says what becomes of unit x at place i. Whether a place is touched is decided by a hash of
document, place, operator and seed, so any engine that has md5 gives the same text.
Operators are written once against a small dialect, for Spark SQL and for DuckDB.
Everything is narrow; lexicons (bounded lists for each language) come as array columns.
"""

from collections.abc import Callable
from dataclasses import dataclass

# Neighbouring keys, look-alike letters, scanner confusions, marks and alphabets used by the operators.
KEYS = "qwertyuiopasdfghjklzxcvbnm"
KEYS_LEFT = "wqwertyuiosasdfghjkxzxcvbn"
KEYS_RIGHT = "aertyuioplsdfghjklmxcvbnmj"
GLYPHS = "aceopxyABEHKMOPTX"
ALIKE = "асеорхуАВЕНКМОРТХ"
SCANNED = "lO1eacS5B8"
SCANNED_AS = "1Ol" + "cocs" + "S8B"
PUNCT = ".,;:!?-"
EMOJI = "😀🔥💰🎁⭐✅"
INVISIBLE = "​‌‍⁠"
RARE = "ꭰꭱꭲꮃꮇꮋꮖꮪ"
SEPARATOR = {"para": "\n", "sent": ". ", "word": " ", "char": ""}


class Spark:
    """Spark SQL text."""

    def units(self, level: str, col: str) -> str:
        if level == "char":
            return f"filter(split({col}, ''), c -> c <> '')"
        return f"split({col}, '{ {'para': chr(10), 'sent': '[.] ', 'word': ' '}[level] }')"

    def each(self, arr: str, f: Callable) -> str:
        return f"transform({arr}, (x, i) -> {f('x', 'i')})"

    def keep(self, arr: str, f: Callable) -> str:
        return f"filter({arr}, (x, i) -> {f('x', 'i')})"

    def at(self, arr: str, i: str) -> str:
        return f"element_at({arr}, cast({i} as int) + 1)"

    def join(self, arr: str, sep: str) -> str:
        return f"array_join({arr}, '{sep}')"

    def size(self, arr: str) -> str:
        return f"size({arr})"

    def number(self, text: str) -> str:
        return f"cast(conv(substring(md5({text}), 1, 13), 16, 10) as bigint)"

    def text(self, x: str) -> str:
        return f"cast({x} as string)"

    def char(self, x: str) -> str:
        return f"chr({x})"


class Duck(Spark):
    """DuckDB text."""

    def units(self, level, col):
        if level == "char":
            return f"list_filter(string_split({col}, ''), lambda c: c <> '')"
        return f"string_split({col}, '{SEPARATOR[level]}')"

    def each(self, arr, f):
        return f"list_transform({arr}, lambda x, i: {f('x', '(i - 1)')})"

    def keep(self, arr, f):
        return f"list_filter({arr}, lambda x, i: {f('x', '(i - 1)')})"

    def at(self, arr, i):
        return f"{arr}[({i})::int + 1]"

    def join(self, arr, sep):
        return f"array_to_string({arr}, '{sep}')"

    def size(self, arr):
        return f"len({arr})"

    def number(self, text):
        return f"('0x' || substr(md5({text}), 1, 13))::bigint"

    def text(self, x):
        return f"({x})::varchar"

    def char(self, x):
        return f"chr(({x})::int)"


@dataclass(frozen=True)
class Place:
    """What an operator may ask about a place of a text."""

    d: Spark
    name: str
    rate: float
    seed: str

    def hash(self, i: str, salt: str = "") -> str:
        return self.d.number(f"{self.d.text('doc_id')} || '-' || {self.d.text(i)} || '-{self.name}{salt}-{self.seed}'")

    def chosen(self, i: str) -> str:
        return f"{self.hash(i)} % 10000 < {round(self.rate * 10000)}"

    def pick(self, arr: str, i: str) -> str:
        """An element of a lexicon, or the empty text of an empty one."""
        return f"coalesce(case when {self.d.size(arr)} > 0 then {self.d.at(arr, f'{self.hash(i, chr(112))} % greatest({self.d.size(arr)}, 1)')} end, '')"

    def letter(self, letters: str, i: str) -> str:
        return f"substring('{letters}', cast({self.hash(i, chr(112))} % {len(letters)} as int) + 1, 1)"

    def when(self, i: str, yes: str, no: str) -> str:
        return f"case when {self.chosen(i)} then {yes} else {no} end"


def _delete(p):
    return p.d.keep("u", lambda x, i: f"not ({p.chosen(i)})")


def _swap(p):
    def f(x, i):
        other = f"case when {i} % 2 = 0 then {i} + 1 else {i} - 1 end"
        pair = f"cast(floor({i} / 2) as int)"
        return f"case when {p.chosen(pair)} and {other} < {p.d.size('u')} then {p.d.at('u', other)} else {x} end"

    return p.d.each("u", f)


def _repeat(sep):
    return lambda p: p.d.each("u", lambda x, i: p.when(i, f"{x} || '{sep}' || {x}", x))


def _replace(value):
    return lambda p: p.d.each("u", lambda x, i: p.when(i, value(p, x, i), x))


def _after(value, sep):
    return lambda p: p.d.each("u", lambda x, i: p.when(i, f"{x} || '{sep}' || {value(p, x, i)}", x))


def _mapped(source, target):
    return lambda p, x, i: f"case when instr('{source}', {x}) > 0 then substring('{target}', instr('{source}', {x}), 1) else {x} end"


def _keyboard(p, x, i):
    at = f"instr('{KEYS}', lower({x}))"
    return f"case when {at} > 0 then case when {p.hash(i, 'k')} % 2 = 0 then substring('{KEYS_LEFT}', {at}, 1) else substring('{KEYS_RIGHT}', {at}, 1) end else {x} end"


def _flip(x):
    return f"case when {x} in ('ß', 'ẞ') then {x} when lower({x}) = {x} then upper({x}) else lower({x}) end"


def _loud(p, x, i):
    up = f"replace(upper(replace({x}, 'ß', '\u0001')), '\u0001', 'ß')"
    return f"case when {p.hash(i, 'c')} % 2 = 0 then {up} else lower({x}) end"


def _edge(front: bool, value, sep):
    """One unit before or after the whole text."""
    def f(p):
        last = f"{p.d.size('u')} - 1"
        hit = "0" if front else last
        joined = (lambda x, v: f"{v} || '{sep}' || {x}") if front else (lambda x, v: f"{x} || '{sep}' || {v}")
        return p.d.each("u", lambda x, i: f"case when {i} = {hit} then {joined(x, value(p, x, '0'))} else {x} end")

    return f


_donor = lambda p, x, i: p.pick("donors", i)
_word = lambda p, x, i: p.pick("all_words", i)
_own_word = lambda p, x, i: p.pick("lang_words", i)
_own_letter = lambda p, x, i: p.pick("letters", i)
_mark = lambda p, x, i: p.letter(PUNCT, i)

#: name: (level, kind, what becomes of the units)
OPERATORS: dict[str, tuple[str, str, Callable]] = {
    "para_delete": ("para", "delete", _delete),
    "para_swap": ("para", "swap", _swap),
    "para_insert": ("para", "insert", _after(_donor, "\n")),
    "para_substitute": ("para", "substitute", _replace(_donor)),
    "sent_delete": ("sent", "delete", _delete),
    "sent_truncate": ("sent", "delete", _replace(lambda p, x, i: f"substring({x}, 1, cast(floor(length({x}) / 2) as int))")),
    "sent_prefix": ("sent", "insert", _edge(True, _donor, ". ")),
    "sent_suffix": ("sent", "insert", _edge(False, _donor, ". ")),
    "sent_insert": ("sent", "insert", _after(_donor, ". ")),
    "sent_repeat": ("sent", "insert", _repeat(". ")),
    "sent_case": ("sent", "substitute", _replace(_loud)),
    "sent_replace": ("sent", "substitute", _replace(_donor)),
    "sent_swap": ("sent", "swap", _swap),
    "word_delete": ("word", "delete", _delete),
    "word_insert": ("word", "insert", _after(_word, " ")),
    "word_insert_lang": ("word", "insert", _after(_own_word, " ")),
    "word_sub_random": ("word", "substitute", _replace(_word)),
    "word_sub_lang": ("word", "substitute", _replace(_own_word)),
    "word_repeat": ("word", "substitute", _repeat(" ")),
    "word_swap": ("word", "swap", _swap),
    "char_delete": ("char", "delete", _delete),
    "char_case": ("char", "substitute", _replace(lambda p, x, i: _flip(x))),
    "char_sub_keyboard": ("char", "substitute", _replace(_keyboard)),
    "char_sub_homoglyph": ("char", "substitute", _replace(_mapped(GLYPHS, ALIKE))),
    "char_sub_ascii": ("char", "substitute", _replace(lambda p, x, i: p.d.char(f"33 + {p.hash(i, 'a')} % 94"))),
    "char_sub_alphabet": ("char", "substitute", _replace(_own_letter)),
    "char_sub_punct": ("char", "substitute", _replace(_mark)),
    "char_repeat": ("char", "insert", _repeat("")),
    "char_insert_alphabet": ("char", "insert", _after(_own_letter, "")),
    "char_insert_punct": ("char", "insert", _after(_mark, "")),
    "char_swap": ("char", "swap", _swap),
    "attack_prepend": ("sent", "attack", _edge(True, _donor, ". ")),
    "attack_append": ("sent", "attack", _edge(False, _donor, ". ")),
    "attack_interleave": ("word", "attack", _after(_own_word, " ")),
    "attack_foreign": ("word", "attack", _after(_word, " ")),
    "attack_typo": ("char", "attack", _replace(_keyboard)),
    "attack_emoji": ("word", "attack", _after(lambda p, x, i: p.letter(EMOJI, i), " ")),
    "attack_homoglyph": ("char", "attack", _replace(_mapped(GLYPHS, ALIKE))),
    "attack_script": ("word", "attack", _after(lambda p, x, i: p.letter(RARE, i), "")),
    "attack_invisible": ("char", "attack", _after(lambda p, x, i: p.letter(INVISIBLE, i), "")),
    "attack_word_pad": ("sent", "attack", _edge(False, lambda p, x, i: " || ' ' || ".join(p.pick("all_words", str(k)) for k in range(8)), ". ")),
    "noise_scan": ("char", "noise", _replace(lambda p, x, i: f"case when {x} = ' ' then '-' || chr(10) else {_mapped(SCANNED, SCANNED_AS)(p, x, i)} end")),
}


def expression(name: str, rate: float, seed: str, d: Spark, rows: str) -> str:
    """SQL that gives (doc_id, text) of rows (doc_id, lang, text, donors, all_words, lang_words, letters) after one operator."""
    level, _, f = OPERATORS[name]
    inner = f"select *, {d.units(level, 'text')} as u from {rows} r where text is not null"
    return f"select doc_id, lang, {d.join(f(Place(d, name, rate, seed)), SEPARATOR[level])} as text from ({inner}) q"
