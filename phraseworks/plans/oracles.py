"""DuckDB SQL of the registered queries, written from the definitions. Common table expressions are shared by name."""

from __future__ import annotations

import re

from ..functions.stem import STEP2, STEP3, STEP4
from ..functions.text import STOP_WORDS

K, DOC_PRIOR, WORD_PRIOR, SWEEPS = 4, 0.5, 0.01, 3
SUPPORT, THRESHOLD, LONGEST = 10, 3, 6
_BOUNDARY = r"[^\p{L}\p{N}\s]+|\n"
_STOP = "CASE lang " + " ".join(f"WHEN '{c}' THEN [{', '.join(repr(w) for w in ws)}]" for c, ws in STOP_WORDS.items()) + " ELSE []::VARCHAR[] END"


def unit(*keys: str, sweep: int = 0) -> str:
    """The uniform number of a sweep for the key columns."""
    joined = " || '|' || ".join(keys)
    return f"(('0x' || substr(md5('7|{sweep}|' || {joined}), 1, 8))::BIGINT / 4294967296.0)"


#: name: (names it reads, its SQL)
CTES: dict[str, tuple[tuple[str, ...], str]] = {
    "raw": ((), f"""SELECT doc_id, lang, source, (i - 1)::INT AS chunk_no, list_filter(string_split_regex(parts[i], '\\s+'), lambda w: w <> '') AS toks
        FROM (SELECT doc_id, lang, source, string_split_regex(lower(text), '{_BOUNDARY}') AS parts FROM documents) p, unnest(range(1, len(parts) + 1)) AS t(i)
        WHERE len(list_filter(string_split_regex(parts[i], '\\s+'), lambda w: w <> '')) > 0"""),
    "placed": (("raw",), f"SELECT doc_id, lang, source, chunk_no, toks AS all_toks, list_filter(range(0, len(toks)), lambda i: NOT list_contains({_STOP}, toks[i + 1])) AS ats FROM raw"),
    "ch": (("placed",), "SELECT doc_id, lang, source, chunk_no, all_toks, ats, list_transform(ats, lambda i: all_toks[i + 1]) AS toks FROM placed WHERE len(ats) > 0"),
    "l": (("ch",), "SELECT sum(len(toks))::DOUBLE AS l FROM ch"),
    "grams": (("ch",), f"SELECT doc_id, lang, source, n::INT AS n, array_to_string(toks[i:i + n - 1], ' ') AS phrase FROM ch, unnest(range(1, {LONGEST + 1})) AS a(n), unnest(range(1, len(toks) - n + 2)) AS b(i)"),
    "cnt": (("grams",), f"SELECT n, phrase, count(*) AS cnt FROM grams GROUP BY n, phrase HAVING count(*) >= {SUPPORT}"),
    "u": (("ch",), "SELECT row_number() OVER () AS uid, toks, count(*) AS mult FROM ch GROUP BY toks"),
    # one row a chunk, replaced at each merge
    "seg": (("u", "cnt", "l"), f"""SELECT uid, toks, []::STRUCT(a VARCHAR, b VARCHAR, s DOUBLE)[] FROM u
        UNION
        SELECT seg.uid, list_concat(list_concat(seg.units[1:best.pos - 1], [best.a_p || ' ' || best.b_p]), seg.units[best.pos + 2:]), list_append(seg.merges, {{'a': best.a_p, 'b': best.b_p, 's': best.s}})
        FROM seg JOIN (SELECT uid, arg_min(struct_pack(pos := pos, a_p := a_p, b_p := b_p, s := s), struct_pack(ns := -s, pos := pos)) AS best FROM (
            SELECT uid, pos, a_p, b_p, round((c.cnt - a.cnt::DOUBLE * b.cnt / l.l) / sqrt(c.cnt), 9) AS s
            FROM (SELECT uid, pos, units[pos] AS a_p, units[pos + 1] AS b_p, units[pos] || ' ' || units[pos + 1] AS c_p FROM (SELECT uid, units, unnest(range(1, len(units))) AS pos FROM seg)) q
            JOIN cnt c ON c.phrase = q.c_p JOIN cnt a ON a.phrase = q.a_p JOIN cnt b ON b.phrase = q.b_p CROSS JOIN l)
            WHERE s >= {THRESHOLD} GROUP BY uid) bb ON bb.uid = seg.uid"""),
    "part": (("ch", "u", "seg"), """SELECT doc_id, chunk_no, j, all_toks, ats, phrase, len(string_split(phrase, ' '))::INT AS n_words, (coalesce(sum(len(string_split(phrase, ' '))) OVER (PARTITION BY doc_id, chunk_no ORDER BY j ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::INT AS start,
            (row_number() OVER (PARTITION BY doc_id ORDER BY chunk_no, j) - 1)::INT AS g
        FROM (SELECT ch.doc_id, ch.chunk_no, ch.all_toks, ch.ats, j, seg.units[j] AS phrase FROM ch JOIN u ON u.toks = ch.toks JOIN seg USING (uid), unnest(range(1, len(seg.units) + 1)) AS t(j))"""),
    "z0": (("part",), f"SELECT doc_id, g, phrase, n_words, string_split(phrase, ' ') AS words, floor({unit('doc_id', 'g')} * {K})::INT AS z FROM part"),
    "tok": (("z0",), "SELECT doc_id, g, z, words, n_words, j, words[j] AS word FROM z0, unnest(range(1, n_words + 1)) AS t(j)"),
    "wk": (("tok",), "SELECT word, z AS k, count(*) AS c FROM tok GROUP BY word, z"),
    "dk": (("tok",), "SELECT doc_id, z AS k, count(*) AS c FROM tok GROUP BY doc_id, z"),
    "tk": (("tok",), "SELECT z AS k, count(*) AS c FROM tok GROUP BY z"),
    "v": (("tok",), "SELECT count(DISTINCT word) AS v FROM tok"),
    "ks": ((), f"SELECT unnest(range(0, {K}))::INT AS k"),
    "logs": (("tok", "wk", "dk", "tk", "v", "ks"), f"""SELECT t.doc_id, t.g, ks.k, sum(
            ln({DOC_PRIOR} + coalesce(dk.c, 0) - CASE WHEN t.z = ks.k THEN t.n_words ELSE 0 END + t.j - 1)
            + ln({WORD_PRIOR} + coalesce(wk.c, 0) - CASE WHEN t.z = ks.k THEN len(list_filter(t.words, lambda w: w = t.word)) ELSE 0 END + len(list_filter(t.words[1:t.j - 1], lambda w: w = t.word)))
            - ln({WORD_PRIOR} * v.v + tk.c - CASE WHEN t.z = ks.k THEN t.n_words ELSE 0 END + t.j - 1)) AS lw
        FROM tok t CROSS JOIN ks CROSS JOIN v JOIN tk ON tk.k = ks.k LEFT JOIN wk ON wk.word = t.word AND wk.k = ks.k LEFT JOIN dk ON dk.doc_id = t.doc_id AND dk.k = ks.k
        GROUP BY t.doc_id, t.g, ks.k"""),
    "probs": (("logs",), "SELECT doc_id, g, k, exp(lw - max(lw) OVER w) / sum(exp(lw - m)) OVER w AS p FROM (SELECT *, max(lw) OVER (PARTITION BY doc_id, g) AS m FROM logs) WINDOW w AS (PARTITION BY doc_id, g)"),
    "tf": (("z0",), "SELECT phrase, n_words, z AS k, count(*) AS tf FROM z0 GROUP BY phrase, n_words, z"),
    "wtf": (("tok",), "SELECT word, z AS k, count(*) AS tf FROM tok GROUP BY word, z"),
    "topw": (("wtf",), "SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY tf DESC, word) AS rank FROM wtf) WHERE rank <= 10"),
    "topp": (("tf",), "SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY tf DESC, phrase) AS rank FROM tf WHERE n_words > 1) WHERE rank <= 10"),
    "bagged": (("part",), "SELECT phrase, n_words, count(*) AS cnt FROM part GROUP BY phrase, n_words"),
    "lw": (("ch",), f"SELECT doc_id, chunk_no, pos, word, floor({unit('doc_id', 'g')} * {K})::INT AS z FROM (SELECT doc_id, chunk_no, (i - 1)::INT AS pos, toks[i] AS word, row_number() OVER (PARTITION BY doc_id ORDER BY chunk_no, i) - 1 AS g FROM ch, unnest(range(1, len(toks) + 1)) AS t(i))"),
    "dw": (("ch",), "SELECT DISTINCT doc_id, unnest(toks) AS word FROM ch"),
}


def _steps(table: dict[str, str] | list[str], least: int, w: str = "w", extra: str = "") -> str:
    """CASE that puts a suffix's replacement in place of the longest fitting suffix, if what is before it has over ``least`` measures."""
    pairs = table if isinstance(table, dict) else dict.fromkeys(table, "")
    arms = []
    for end in sorted(pairs, key=len, reverse=True):
        head = f"left({w}, len({w}) - {len(end)})"
        ok = f"{_measures(f'left(s, len({w}) - {len(end)})')} > {least}" + (f" AND regexp_matches({head}, '[st]$')" if end == extra else "")
        arms.append(f"WHEN suffix({w}, '{end}') THEN CASE WHEN {ok} THEN {head} || '{pairs[end]}' ELSE {w} END")
    return "CASE " + " ".join(arms) + f" ELSE {w} END"


def _measures(shape: str) -> str:
    return f"len(regexp_extract_all({shape}, 'V+C+'))"


def _shaped(source: str) -> str:
    """word, w and s, the letters of w as vowels and consonants; y is a vowel behind a consonant."""
    s = "regexp_replace(regexp_replace(regexp_replace(w, '[aeiou]', 'V', 'g'), '[^Vy]', 'C', 'g'), '^y', 'C')"
    for _ in range(3):
        s = f"replace(replace({s}, 'Cy', 'CV'), 'Vy', 'VC')"
    return f"(SELECT word, w, {s} AS s FROM ({source}))"


def _stem_sql(words: str) -> str:
    """word, stem of the distinct words that ``words`` selects, by the five steps of the published rules."""
    cvc = lambda w, s: f"(regexp_matches({s}, 'CVC$') AND NOT regexp_matches({w}, '[wxy]$'))"
    now = f"SELECT word, CASE WHEN suffix(w, 'sses') OR suffix(w, 'ies') THEN left(w, len(w) - 2) WHEN suffix(w, 'ss') THEN w WHEN suffix(w, 's') THEN left(w, len(w) - 1) ELSE w END AS w FROM (SELECT word, word AS w FROM ({words}) WHERE regexp_full_match(word, '[a-z]{{3,}}'))"
    cut = f"SELECT word, CASE WHEN suffix(w, 'eed') THEN CASE WHEN {_measures('left(s, len(w) - 3)')} > 0 THEN left(w, len(w) - 1) ELSE w END WHEN suffix(w, 'ed') AND contains(left(s, len(w) - 2), 'V') THEN '+' || left(w, len(w) - 2) WHEN suffix(w, 'ing') AND contains(left(s, len(w) - 3), 'V') THEN '+' || left(w, len(w) - 3) ELSE w END AS w FROM {_shaped(now)}"
    # a word that lost its ending is marked by a plus until it is mended
    mend = _shaped(f"SELECT word, ltrim(w, '+') AS w, w[1] = '+' AS was_cut FROM ({cut})").replace("SELECT word, w, ", "SELECT word, w, was_cut, ", 1)
    now = f"SELECT word, CASE WHEN NOT was_cut THEN w WHEN regexp_matches(w, '(at|bl|iz)$') THEN w || 'e' WHEN len(w) > 1 AND w[-1] = w[-2] AND s[-1] = 'C' AND w[-1] NOT IN ('l', 's', 'z') THEN left(w, len(w) - 1) WHEN {_measures('s')} = 1 AND {cvc('w', 's')} THEN w || 'e' ELSE w END AS w FROM {mend}"
    now = f"SELECT word, CASE WHEN suffix(w, 'y') AND contains(left(s, len(w) - 1), 'V') THEN left(w, len(w) - 1) || 'i' ELSE w END AS w FROM {_shaped(now)}"
    for table, least, extra in ((STEP2, 0, ""), (STEP3, 0, ""), (STEP4, 1, "ion")):
        now = f"SELECT word, {_steps(table, least, extra=extra)} AS w FROM {_shaped(now)}"
    before = "left(s, len(w) - 1)"
    now = f"SELECT word, CASE WHEN suffix(w, 'e') AND ({_measures(before)} > 1 OR ({_measures(before)} = 1 AND NOT {cvc('left(w, len(w) - 1)', before)})) THEN left(w, len(w) - 1) ELSE w END AS w FROM {_shaped(now)}"
    now = f"SELECT word, CASE WHEN suffix(w, 'll') AND {_measures(before)} > 1 THEN left(w, len(w) - 1) ELSE w END AS w FROM {_shaped(now)}"
    return f"SELECT word, w AS stem FROM ({now}) UNION ALL SELECT word, word FROM ({words}) WHERE NOT regexp_full_match(word, '[a-z]{{3,}}')"


#: With stems: chunks whose words are their stems.
STEMMED = {
    "unstemmed": CTES["ch"],
    "cnt_unstemmed": (("unstemmed",), CTES["cnt"][1].replace("FROM grams", f"FROM ({CTES['grams'][1].replace('FROM ch', 'FROM unstemmed')})")),
    "stemmed": (("unstemmed",), _stem_sql("SELECT DISTINCT unnest(toks) AS word FROM unstemmed")),
    "ch": (("unstemmed", "stemmed"), "SELECT doc_id, any_value(lang) AS lang, any_value(source) AS source, chunk_no, any_value(all_toks) AS all_toks, any_value(ats) AS ats, list(stem ORDER BY i) AS toks FROM (SELECT c.*, t.i, s.stem FROM unstemmed c, unnest(range(1, len(toks) + 1)) AS t(i) JOIN stemmed s ON s.word = c.toks[t.i]) GROUP BY doc_id, chunk_no"),
}


def _chain(sweeps: int) -> dict[str, tuple[tuple[str, ...], str]]:
    """The initial topics under another name, and z0 after some snapshot sweeps: each from the counts of the one before."""
    out, names = {"z_0": CTES["z0"]}, ("tok", "wk", "dk", "tk", "v", "logs", "probs")
    for i in range(sweeps):
        renamed = {n: f"{n}_{i}" for n in names} | {"z0": f"z_{i}"}
        as_new = lambda text, renamed=renamed: re.sub(r"\b(FROM|JOIN|CROSS JOIN|,) (tok|wk|dk|tk|v|logs|probs|z0)\b(?! AS| \()", lambda m: f"{m[1]} {renamed[m[2]]} {m[2]}", text)
        for n in names:
            needs, text = CTES[n]
            # a table that has an alias of its own keeps it
            out[renamed[n]] = (tuple(renamed.get(x, x) for x in needs), re.sub(r"\b(tok|wk|dk|tk|v|logs|probs|z0) \1 t\b", r"\1 t", as_new(text)).replace(f"{renamed['tok']} tok t ", f"{renamed['tok']} t "))
        out[f"z_{i + 1}"] = ((f"z_{i}", renamed["probs"]), f"""SELECT o.doc_id, o.g, o.phrase, o.n_words, o.words, d.z FROM z_{i} o JOIN (
            SELECT doc_id, g, least(count(*) FILTER (WHERE cum <= u), {K - 1})::INT AS z FROM (
                SELECT doc_id, g, sum(p) OVER (PARTITION BY doc_id, g ORDER BY k ROWS UNBOUNDED PRECEDING) AS cum, {unit('doc_id', 'g', sweep=i + 1)} AS u FROM {renamed['probs']}) GROUP BY doc_id, g) d ON d.doc_id = o.doc_id AND d.g = o.g""")
    out["z0"] = ((f"z_{sweeps}",), f"SELECT * FROM z_{sweeps}")
    return out


def _word_chain(sweeps: int) -> dict[str, tuple[tuple[str, ...], str]]:
    """The same for the word model: lw after some snapshot sweeps."""
    out = {"lw_0": (("ch",), CTES["lw"][1].replace("chunk_no, pos, word, floor", "chunk_no, pos, word, g, floor"))}
    for i in range(sweeps):
        t = f"lw_{i}"
        out[f"lw_{i + 1}"] = ((t, "ks"), f"""SELECT o.doc_id, o.chunk_no, o.pos, o.word, o.g, d.z FROM {t} o JOIN (
            SELECT doc_id, g, least(count(*) FILTER (WHERE cum <= u), {K - 1})::INT AS z FROM (
                SELECT doc_id, g, k, sum(p) OVER (PARTITION BY doc_id, g ORDER BY k ROWS UNBOUNDED PRECEDING) / sum(p) OVER (PARTITION BY doc_id, g) AS cum, {unit('doc_id', 'g', sweep=i + 1)} AS u FROM (
                    SELECT t.doc_id, t.g, ks.k, ({DOC_PRIOR} + coalesce(a.c, 0) - (t.z = ks.k)::INT) * ({WORD_PRIOR} + coalesce(b.c, 0) - (t.z = ks.k)::INT) / ({WORD_PRIOR} * vv.v + c.c - (t.z = ks.k)::INT) AS p
                    FROM {t} t CROSS JOIN ks CROSS JOIN (SELECT count(DISTINCT word) AS v FROM {t}) vv JOIN (SELECT z, count(*) AS c FROM {t} GROUP BY z) c ON c.z = ks.k
                    LEFT JOIN (SELECT doc_id, z, count(*) AS c FROM {t} GROUP BY ALL) a ON a.doc_id = t.doc_id AND a.z = ks.k
                    LEFT JOIN (SELECT word, z, count(*) AS c FROM {t} GROUP BY ALL) b ON b.word = t.word AND b.z = ks.k)) GROUP BY doc_id, g) d ON d.doc_id = o.doc_id AND d.g = o.g""")
    out["lw"] = ((f"lw_{sweeps}",), f"SELECT doc_id, chunk_no, pos, word, z FROM lw_{sweeps}")
    return out


#: With fitted topics: the state after SWEEPS snapshot sweeps in place of the initial one, of both models.
FITTED = _chain(SWEEPS) | _word_chain(SWEEPS)


def sql(body: str, *names: str, fitted: bool = False, stems: bool = False, documents: str | None = None) -> str:
    """body after the named expressions and what they read, each once; from another relation than documents if one is given."""
    ctes = CTES | (STEMMED if stems else {}) | (FITTED if fitted else {})
    order: list[str] = []

    def add(name: str) -> None:
        if name not in order:
            for d in ctes[name][0]:
                if d != name:
                    add(d)
            order.append(name)

    for n in names:
        add(n)
    head = ",\n".join(f"seg(uid, units, merges) USING KEY (uid) AS ({ctes[n][1]})" if n == "seg" else f"{n} AS MATERIALIZED ({ctes[n][1]})" for n in order)
    whole = f"WITH RECURSIVE {head}\n{body}" if order else body
    return re.sub(r"\bFROM documents\b", lambda _: f"FROM ({documents}) documents", whole) if documents else whole
