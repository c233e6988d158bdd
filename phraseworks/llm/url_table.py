"""A small table of labelled URLs to train the URL filter from: (url, 1 to block or 0). Hosts and paths are put together by rule from
words that tell and words that do not, so that the label may be in either part, and in any place of it."""

from __future__ import annotations

import zlib

#: Words that stand for what is blocked, and words of ordinary sites.
BLOCKED = "casino poker jackpot slots betting lottery pills pharmacy viagra cialis steroids replica escort adult xxx porn nude cams hookup torrent warez crack keygen serials hacks malware phishing trojan spam scam payday loanshark freemoney winmoney bonus clickbait linkfarm doorway backlinks botnet".split()
ALLOWED = "library museum university school college science journal archive history garden recipes cooking travel weather news council hospital health books music gallery sports chess birds forest rivers maps docs wiki code data research review papers forum blog community theatre parish orchard".split()
#: Words that say nothing, and hosts of syllables, so that a host without any evidence is an ordinary one.
FILLERS = "my best top online world hub zone shop now pro site club center direct daily first open live store network".split()
SYLLABLES = "the and ing ion ent her tha nth int ere tio ter est ers ati hat ate all eth hes ver his oft ith fth sth oth res ont ou nd ea le no mi la su vo ka be".split()
FRONTS, TOPS = ("", "www.", "blog.", "m.", "shop."), ("example.com", "example.org", "example.net", "example.edu", "com", "info")
#: Plain paths, in which {n} is a number.
PATHS = ("/", "/en/{n}", "/fr/{n}/", "/de/{n}.html", "/es/index.html", "/2024/05/{n}", "/item/{n}.php", "/p/{n}")


def _pick(items, *place):
    """One of the items, by a hash of the place, so that no two choices go together."""
    return items[zlib.crc32(repr(place).encode()) % len(items)]


def _host(words: list[str], *place) -> str:
    return f"{_pick(FRONTS, 'front', *place)}{_pick(('-', '', '.'), 'join', *place).join(words)}.{_pick(TOPS, 'top', *place)}"


def _quiet_word(*place) -> str:
    return "".join(_pick(SYLLABLES, k, *place) for k in range(2 + zlib.crc32(repr(place).encode()) % 3))


def _url(words: list[str], told: str, *place) -> str:
    """A URL with the words in its host (told = 'host') or its path, and quiet words in the other."""
    n, filler, quiet = zlib.crc32(repr(place).encode()) % 9999, _pick(FILLERS, "filler", *place), _quiet_word("quiet", *place)
    named = _pick(([words[0], filler], [filler, words[0]], words, words[:1]), "host", *place)
    host = _host(named if told == "host" else [quiet], *place)
    in_path = _pick((f"/{words[0]}/{n}", f"/{filler}/{'-'.join(words)}.html", f"/{'_'.join(words)}", f"/en/{words[0]}{filler}/{n}"), "path", *place)
    return f"{_pick(('http', 'https'), *place)}://{host}{in_path if told == 'path' else _pick(PATHS, 'plain', *place).format(n=n)}"


def labelled(per_word: int = 30, quiet: int = 2400) -> list[tuple[str, int]]:
    """per_word URLs of each telling word, half of them in the host and half in the path, and as many as ``quiet`` without any."""
    out = []
    for label, telling in ((1, BLOCKED), (0, ALLOWED)):
        out += [(_url([w, _pick(telling, "other", w, j)], ("host", "path")[j % 2], w, j), label) for w in telling for j in range(per_word)]
    return out + [(_url([_quiet_word("a", i), _quiet_word("b", i)], ("host", "path")[i % 2], i), 0) for i in range(quiet)]
