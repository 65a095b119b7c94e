"""Small own dictionaries: translations and exonyms, address abbreviations, transliteration."""

from __future__ import annotations

import unicodedata

# form -> concept, on folded tokens
ALIASES = {
    "calle": "street", "rue": "street", "strasse": "street", "avenida": "avenue", "bulevar": "boulevard", "camino": "road",
    "norte": "north", "nord": "north", "sur": "south", "sud": "south", "este": "east", "osten": "east", "oeste": "west", "westen": "west",
    "puerto": "port", "hafen": "port", "nacion": "nation", "land": "nation", "interior": "inner", "exterior": "outer",
    "edificio": "building", "muebles": "furniture", "hogar": "household", "maquinaria": "machinery", "automovil": "automobile",
    "osterreich": "austria", "athena": "athens", "deutschland": "germany", "espana": "spain", "italia": "italy",
}

# short form -> long forms, on folded tokens
ABBREVIATIONS = {
    "st": ("street", "saint"), "str": ("street", "strasse"), "ave": ("avenue",), "av": ("avenue",), "blvd": ("boulevard",), "rd": ("road",), "dr": ("drive",), "ln": ("lane",),
    "n": ("north",), "s": ("south",), "e": ("east",), "w": ("west",), "pt": ("port", "point"), "nat": ("nation",), "inn": ("inner",), "out": ("outer",),
    "bldg": ("building",), "furn": ("furniture",), "hh": ("household",), "mach": ("machinery",), "auto": ("automobile",),
}


def accent_table() -> tuple[str, str]:
    """Letters of the Latin blocks with one mark and the plain letters they fold to, from their decomposition."""
    pairs = [(chr(c), d[0]) for c in range(0xC0, 0x250) if len(d := unicodedata.normalize("NFD", chr(c))) > 1 and d[0].isascii()]
    return "".join(a for a, _ in pairs), "".join(b for _, b in pairs)


def romanization_table() -> dict[str, str]:
    """Greek and Cyrillic small letters to Latin, from the letters' Unicode names where those are one sound."""
    special = {"θ": "th", "χ": "ch", "ψ": "ps", "ω": "o", "η": "e", "υ": "y", "φ": "f", "ξ": "x", "ж": "zh", "ц": "ts", "ч": "ch", "ш": "sh", "щ": "shch", "ъ": "", "ы": "y", "ь": "", "э": "e", "ю": "yu", "я": "ya", "й": "y", "х": "kh", "е": "e"}
    out = dict(special)
    for c in [*range(0x3B1, 0x3CA), *range(0x430, 0x450)]:
        name = unicodedata.name(chr(c), "").split(" LETTER ")[-1].split(" ")[-1].lower()
        if chr(c) not in out and name:
            sound = name if chr(c) >= "а" else name[0]
            out[chr(c)] = sound[1] if len(sound) == 2 and sound[0] == "e" and chr(c) >= "а" else sound[0]
    return out
