"""What a method needs to know about a target language: character classes, function words, thresholds, term lists."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

# Character classes as ranges inside a regex class.
HIRAGANA = r"\x{3040}-\x{309F}"
KATAKANA = r"\x{30A0}-\x{30FF}\x{31F0}-\x{31FF}\x{FF66}-\x{FF9F}"
KANJI = r"\x{3400}-\x{4DBF}\x{4E00}-\x{9FFF}\x{F900}-\x{FAFF}々〇"
PUNCTUATION = r"\x{3000}-\x{303F}\x{FF01}-\x{FF0F}\x{FF1A}-\x{FF20}\x{FF3B}-\x{FF40}\x{FF5B}-\x{FF65}"

# Function words by language.
FUNCTION_WORDS = {
    "en": "the of and to in is that it was for on are as with his they at be this from have or by not but what all were when".split(),
    "fr": "le les et un une est que qui dans pour pas sur du au avec il elle des sont par ce nous vous mais plus".split(),
    "de": "der die das und ist nicht ein eine zu mit auf für von dem den im sich auch es wird aus bei nach".split(),
    "es": "el los las que y una por con para no se del al como más pero sus lo su está ser".split(),
}

# Term lists of the stand-in data.
HARMFUL_TERMS = ["trash", "scum", "idiot", "clown", "worthless", "moron", "pathetic", "loser"]
SITE_TERMS = ["stupid", "disgusting"]
BLOCKED_STEMS = ["cheap-pills", "free-bets", "spam-farm", "adult-x", "casino-win", "ads-track"]
ENCYCLOPEDIA_SUFFIX, FORUM_SUFFIX = "th.example.org", ".example.net"
FOOTER_LINES = ["all rights reserved", "licensed under", "copyright", "©", "permalink", "share this"]
TERMINATORS = "。．.!！？?"
ELLIPSES = ["...", "…", "‥", "・・・"]


@dataclass(frozen=True)
class Thresholds:
    """Equality always keeps a text."""

    min_chars: int = 400
    min_hiragana: float = 0.2
    max_katakana: float = 0.5
    min_script: float = 0.5
    mean_sentence: tuple[float, float] = (20.0, 90.0)
    max_sentence: int = 200
    max_ellipsis: float = 0.2
    max_harmful: float = 0.05


@dataclass(frozen=True)
class LanguageProfile:
    code: str
    kana_rules: bool = False
    thresholds: Thresholds = field(default_factory=Thresholds)
    harmful: tuple[str, ...] = tuple(HARMFUL_TERMS)

    def tuned(self, **changes) -> LanguageProfile:
        return replace(self, thresholds=replace(self.thresholds, **changes))


JA = LanguageProfile("ja", kana_rules=True)
LATIN = {code: LanguageProfile(code) for code in FUNCTION_WORDS}

_LOWER, _UPPER = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_ACCENTED = "àáâäçèéêëìíîïñòóôöùúûüßœÀÁÂÄÇÈÉÊËÌÍÎÏÑÒÓÔÖÙÚÛÜ"


def kana_map(letters: str = _LOWER + _UPPER + _ACCENTED, marks: bool = True) -> tuple[str, str]:
    """Equally long source and target strings that stand Latin text in for Japanese: a synthetic proxy.

    a-z become hiragana, A-Z katakana, accented letters kanji; with marks, full stop and comma become ideographic.
    """
    rows = {c: chr(0x3042 + i) for i, c in enumerate(_LOWER)} | {c: chr(0x30A2 + i) for i, c in enumerate(_UPPER)} | {c: chr(0x4E00 + i) for i, c in enumerate(_ACCENTED)}
    picked = [c for c in letters if c in rows]
    return "".join(picked) + ".," * marks, "".join(rows[c] for c in picked) + "。、" * marks
