"""DuckDB twins of the queries: the same definitions in SQL, for checking."""

from __future__ import annotations

from corpusforge.functions import html, pii
from corpusforge.functions import warnings as W
from corpusforge.functions.labels import LANGUAGES, NO_WORD_BOUNDARY
from corpusforge.operators import noise, relational
from corpusforge.operators.content import SEEDS
from corpusforge.queries import ABROAD, FAMILIES, NOISE_ID, REJECT_TEST, REJECT_TRAIN, REJECT_WORDS, RELABELLED, RULES, SWAPS, TOO_SHORT
from corpusforge.streaming import stream

BUCKETS = 2_000_000
ALPHA = 0.5


def text(value: str | None) -> str:
    return "null" if value is None else "'" + value.replace("'", "''") + "'"


def values(rows, *columns: str) -> str:
    """A constant table."""
    cell = lambda v: text(v) if isinstance(v, str) or v is None else str(v).lower()
    return f"(select * from (values {', '.join('(' + ', '.join(cell(v) for v in r) + ')' for r in rows)}) t({', '.join(columns)}))"


LABEL = "case lang when 'en' then 'eng_Latn' when 'fr' then 'fra_Latn' when 'de' then 'deu_Latn' when 'es' then 'spa_Latn' end"


def h32(e: str) -> str:
    return f"cast(('0x' || substr(md5({e}), 1, 8)) as bigint)"


DRAW = lambda *parts: h32(f"concat_ws(':', {', '.join(parts)})")
GRAMS = "flatten([[substr(p, i, n) for i in range(1, length(p) - n + 2)] for n in range(2, 6)])"
LINES = f"lines as (select doc_id, source, pos, trim(l) as line, label, part from (select doc_id, source, {LABEL} as label, {h32('text')} % 10 as part, unnest(string_split(text, chr(10))) as l, generate_subscripts(string_split(text, chr(10)), 1) - 1 as pos from documents) where trim(l) <> '')"


def vocabulary(where: str = "true", name: str = "voc") -> str:
    """n-grams with their occurrences."""
    return f"{name}_w as (select word, count(*) as n from (select unnest(regexp_extract_all(lower(line), '\\p{{L}}+')) as word from lines where {where}) group by 1), {name} as (select g, cast(sum(n) as bigint) as n from (select n, unnest({GRAMS}) as g from (select n, ' ' || word || ' ' as p from {name}_w)) group by 1)"


# -------------------------------------------------------------------------------------------- the counting model in SQL


def numbered(n: int) -> str:
    """Rows that lines are drawn for: numbers, drawn by themselves."""
    return f"(select r as row, cast(r as varchar) as r from range({n}) t(r))"


#: Documents that lines are drawn for, by their texts.
FOR_DOCUMENTS = "(select doc_id, md5(text) as r from documents)"


def drawn_rows(alphabets: dict[str, str], of: str, seed: str, words: tuple[int, int], length: tuple[int, int]) -> str:
    """(name, line, and the columns of the rows) of random words for each alphabet."""
    size = lambda low, high, *parts: f"cast({DRAW(text(seed), 'name', 'r', *parts)} % {high - low + 1} + {low} as integer)"
    word = f"array_to_string([letters[cast({DRAW(text(seed), 'name', 'r', 'w', 'i')} % len(letters) + 1 as integer)] for i in range(1, {size(*length, 'w', text('n'))} + 1)], '')"
    table = "(select name, string_split(l, '') as letters from " + values(list(alphabets.items()), "name", "l") + ")"
    return f"select *, array_to_string([{word} for w in range(1, {size(*words)} + 1)], ' ') as line from {table}, {of}"


def und_rows(scripts: list[str], of: str, seed: str, words: tuple[int, int], key: str = "row") -> str:
    return f"select 'und_' || name as label, {key}, line from ({drawn_rows({s: noise.alphabet(s) for s in scripts}, of, seed, words, (2, 10))})"


def pdf_rows(of: str, seed: str, key: str = "row") -> str:
    return f"select {key}, line from ({drawn_rows({'pdf': noise.STROKES}, of, seed, (10, 29), (1, 2))})"


def binary_rows(of: str, seed: str, key: str = "row") -> str:
    h = " || ".join(f"md5(concat_ws(':', '{seed}', 'bin', r, '{k}'))" for k in range(4))
    codes = "[cast('0x' || substr(h, 2 * i + 1, 2) as integer) for i in range(64)]"
    return f"select {key}, array_to_string([chr(c) for c in {codes} if c > 32 and not c between 127 and 160], '') as line from (select {key}, {h} as h from {of})"


def latin_bytes(e: str) -> str:
    """UTF-8 bytes of a text, each as a Latin-1 character."""
    return f"array_to_string([chr(cast('0x' || substr(hex(encode({e})), 2 * i + 1, 2) as integer)) for i in range(length(hex(encode({e}))) // 2)], '')"


SPACED = "array_to_string(string_split(regexp_replace({e}, '\\s+', '', 'g'), ''), ' ')"


def with_replacements(e: str, key: str, rate: float, seed: str) -> str:
    return f"array_to_string([case when {DRAW(text(seed), text('fffd'), key, 'i - 1')} % 1000 < {int(rate * 1000)} then chr(65533) else string_split({e}, '')[i] end for i in range(1, length({e}) + 1)], '')"


def rejects(n: int, seed: str, scripts: list[str] | None = None, words: tuple[int, int] | None = None) -> str:
    """(kind, label, row, line) over the CTE ``lines``."""
    part = "part < 8" if seed == "train" else "part = 9"
    chosen = lambda kind: f"(select doc_id, pos, line, row_number() over (order by md5(concat_ws(':', '{seed}', '{kind}', doc_id, pos)), doc_id, pos) - 1 as row from lines where {part} qualify row < {n})"
    und = und_rows(noise.unseen_scripts() if scripts is None else scripts, numbered(n), seed, words or REJECT_WORDS[seed])
    vowels, signs = (drawn_rows({k: a}, numbered(n), seed, (5, 15), (2, 8)) for k, a in (("mojibake_latin", noise.VOWELS), ("mojibake_arabic", noise.ARABIC_SIGNS)))
    key = "cast(doc_id as varchar) || ':' || cast(pos as varchar)"
    kinds = {
        "pdf": pdf_rows(numbered(n), seed), "binary": binary_rows(numbered(n), seed), "spaced": f"select row, {SPACED.format(e='line')} as line from {chosen('spaced')}",
        "replacement": f"select row, {with_replacements('line', key, 0.5, seed)} as line from {chosen('replacement')}",
        "mojibake_latin": f"select row, {latin_bytes('line')} as line from ({vowels})", "mojibake_arabic": f"select row, line from ({signs})",
    }
    return f"select label as kind, label, row, line from ({und})" + "".join(f" union all select '{k}', '{noise.KINDS[k]}', row, line from ({q})" for k, q in kinds.items())


def model(units: str, train: str = "select label, line from lines where part < 8", buckets: int = BUCKETS, pattern: str = r"\p{L}+", only: str = "true", tau: float = 1.0, tag: str = "") -> str:
    """CTEs from training rows (label, line) and units (id, t) to ``scored`` (id, label, score, grams), ``prob`` and ``best``."""
    names = {k: k + tag for k in ("train", "units", "tw", "uw", "grams", "counts", "tot", "gains", "sizes", "scored", "probs", "best")}
    q = """{train} as (__train), {units} as (__units),
{tw} as (select label, word, count(*) as n from (select label, unnest(regexp_extract_all(lower(line), '__pattern')) as word from {train}) group by all),
{uw} as (select id, word, count(*) as n from (select id, unnest(regexp_extract_all(lower(t), '__pattern')) as word from {units}) group by all),
{grams} as (select word, __hash % __buckets as b, count(*) as tf from (select word, unnest(__grams) as g from (select word, ' ' || word || ' ' as p from (select word from {tw} union select word from {uw}))) group by all),
{counts} as (select b, label, sum(n * tf) as c from {tw} join {grams} using (word) group by all),
{tot} as (select label, sum(c) as total, ln(__alpha / (sum(c) + __alpha * __buckets)) as w0 from {counts} group by all),
{gains} as (select word, label, sum(tf * ln(1 + c / __alpha)) as gain from {grams} join {counts} using (b) where word in (select word from {uw}) group by all),
{sizes} as (select id, sum(n * size) as grams from {uw} join (select word, sum(tf) as size from {grams} group by 1) using (word) group by all),
{scored} as (select s.id, t.label, s.grams, coalesce(g.gain, 0) + s.grams * t.w0 as score from {sizes} s cross join {tot} t left join (select id, label, sum(n * gain) as gain from {uw} join {gains} using (word) group by all) g on g.id = s.id and g.label = t.label where __only),
{probs} as (select *, e / sum(e) over (partition by id) as prob from (select *, exp((score - max(score) over (partition by id)) / (__tau * sqrt(grams))) as e from {scored})),
{best} as (select id, label as pred, prob from (select *, row_number() over (partition by id order by round(prob, 9) desc, label) as k from {probs}) where k = 1)""".format(**names)
    for key, value in (("__train", train), ("__units", units), ("__pattern", pattern), ("__hash", h32("g")), ("__buckets", str(buckets)), ("__grams", GRAMS), ("__alpha", str(ALPHA)), ("__only", only), ("__tau", str(tau))):
        q = q.replace(key, value)
    return q


TEST = f"test as (select doc_id, text, {LABEL} as gold from documents where {h32('text')} % 10 = 9)"
UNITS = "select doc_id as id, text as t from test"
PRED = f"pred as (select doc_id, gold, pred, prob from test left join best on doc_id = id)"
DOCS = f"with {LINES}, {TEST}, {model(UNITS)}, {PRED} "
THREE = "select label, line from lines where part < 8 and label in ('eng_Latn', 'fra_Latn', 'deu_Latn')"
NARROW = f"with {LINES}, {TEST}, {model(UNITS, THREE)}, {PRED} "
WEAK_UNITS = "select cast(doc_id as varchar) || ':' || cast(pos as varchar) as id, line as t from lines where part = 9"
WEAK = f"with {LINES}, {model(WEAK_UNITS, buckets=64)}, pred as (select doc_id, pos, label as gold, pred, prob from lines left join best on cast(doc_id as varchar) || ':' || cast(pos as varchar) = id where part = 9) "
CELLS = "cells as (select gold, coalesce(pred, 'none') as pred, count(*) as n from pred group by all)"


def prf(name: str = "prf", cells: str = "cells") -> str:
    r = lambda a, b: f"round(case when {b} > 0 then ({a}) / ({b}) else 0.0 end, 6)"
    return f"""{name}_c as (select g.gold as label, tp, coalesce(of_pred, 0) - tp as fp, of_gold - tp as fn, sum(of_gold) over () - of_gold - coalesce(of_pred, 0) + tp as tn
from (select gold, cast(sum(n) as bigint) as of_gold, cast(sum(case when gold = pred then n else 0 end) as bigint) as tp from {cells} group by 1) g left join (select pred, cast(sum(n) as bigint) as of_pred from {cells} group by 1) p on g.gold = p.pred),
{name} as (select label, tp, fp, fn, cast(tn as bigint) as tn, {r('tp', 'tp + fp')} as precision, {r('tp', 'tp + fn')} as recall, {r('2 * tp', '2 * tp + fp + fn')} as f1, {r('fp', 'fp + tn')} as fpr from {name}_c)"""


F1 = "select label, tp, fp, fn, precision, recall, f1 from prf"
_FAMILIES = lambda name: values(FAMILIES, "l", "m") + f" {name}"
WEAKEST = WEAK.replace("% 64 as b", "% 4 as b").replace("* 64)", "* 4)")
_LOW = f"{WEAKEST}, {CELLS}, {prf()}, low as (select label, f1 from prf where f1 < 0.7)"
_RELABELLED = "case " + " ".join(f"when doc_id % 5 = {k} then {text(v)}" for k, v in RELABELLED.items()) + f" else {LABEL} end"
SQL: dict[str, str] = {
    "ngram_counts": f"with {LINES}, {vocabulary()} select cast(length(g) as integer) as size, count(*) as n_distinct, cast(sum(n) as bigint) as n from voc group by all",
    "collision_rate": f"with {LINES}, {vocabulary()} "
    + " union all ".join(f"select cast({b} as bigint) as buckets, cast(sum(k) as bigint) as n_distinct, count(*) as occupied, cast(sum(case when k > 1 then k else 0 end) as bigint) as colliding, round(sum(case when k > 1 then k else 0 end) / sum(k), 6) as rate from (select {h32('g')} % {b} as b, count(*) as k from voc group by 1)" for b in (1 << 12, 1 << 16, 1 << 20, BUCKETS)),
    "oov_share": f"with {LINES}, {vocabulary('part < 8', 'tr')}, {vocabulary('part = 9', 'te')}, u as (select distinct {h32('g')} % {BUCKETS} as b from tr), x as (select te.g, tr.g is null as unseen, u.b is not null as used from te left join tr on te.g = tr.g left join u on {h32('te.g')} % {BUCKETS} = u.b) select count(*) as n_test, count(*) filter (unseen) as unseen, count(*) filter (unseen and used) as colliding, round(count(*) filter (unseen) / count(*), 6) as unseen_share from x",
    "exact_vocab": f"with {LINES}, {vocabulary()} select g, n from voc where n >= 50",
    "lid_train_counts": f"with {LINES}, {TEST}, {model(UNITS)} select label, count(*) as n_buckets, cast(sum(c) as bigint) as total, cast(max(c) as bigint) as largest from counts group by all",
    "lid_predict_docs": DOCS + "select doc_id, pred, round(prob, 4) as prob from pred",
    "lid_predict_lines": f"with {LINES}, {model(WEAK_UNITS)} select cast(split_part(id, ':', 1) as bigint) as doc_id, cast(split_part(id, ':', 2) as integer) as pos, pred, round(prob, 4) as prob from best",
    "lid_predict_fused": DOCS + ", n as (select doc_id, len(list_filter(string_split(text, chr(10)), lambda x: trim(x) <> '')) as n_lines from test) select doc_id, pred, round(prob, 4) as prob, cast(n_lines as integer) as n_lines from pred join n using (doc_id)",
    "lid_reject_threshold": DOCS + "select not coalesce(prob >= 0.9, false) as miss, count(*) as n from pred group by all",
    "lid_script_restricted": DOCS + "select id as doc_id, pred from best",
    "lid_subset_softmax": f"with {LINES}, {TEST}, {model(UNITS, only=chr(32) + 't.label in (' + text('eng_Latn') + ', ' + text('fra_Latn') + ')')} select id as doc_id, label, round(prob, 4) as prob from probs",
    "lid_bench_restricted": f"with {LINES}, {TEST}, {model(UNITS, only=chr(32) + 't.label in (' + text('deu_Latn') + ', ' + text('eng_Latn') + ', ' + text('spa_Latn') + ')')}, {PRED} select doc_id, pred from pred",
    "lid_confusion": DOCS + f", {CELLS} select * from cells",
    "lid_confused_pairs": WEAK + f", {CELLS} select least(gold, pred) as a, greatest(gold, pred) as b, cast(sum(case when gold < pred then n else 0 end) as bigint) as n_ab, cast(sum(case when gold > pred then n else 0 end) as bigint) as n_ba, cast(sum(n) as bigint) as n, fa.m = fb.m as one_macro from cells join {_FAMILIES('fa')} on fa.l = least(gold, pred) join {_FAMILIES('fb')} on fb.l = greatest(gold, pred) where gold <> pred and pred <> 'none' group by all",
    "lid_f1": DOCS + f", {CELLS}, {prf()} {F1}",
    "lid_f1_macro": DOCS + f", {CELLS}, {prf()} select 'f1_macro' as metric, round(avg(f1), 6) as value, count(*) as n_labels from prf union all select 'f1_micro', round(2 * sum(case when gold = pred then 1 else 0 end) / (count(*) + count(pred)), 6), count(distinct gold) from pred",
    "lid_fpr": DOCS + f", {CELLS}, {prf()} select label, fp, tn, fpr from prf",
    "lid_worst_labels": WEAK + f", {CELLS}, {prf()} select label, f1 from prf order by f1, label limit 3",
    "lid_baseline_compact": f"with {LINES}, {TEST}, {model(UNITS, buckets=4096)}, {PRED}, {CELLS}, {prf()} {F1}",
    "lid_baseline_narrow": NARROW + "select gold, coalesce(case when prob >= 0.8 then pred end, 'none') as pred, count(*) as n from pred group by all",
    "lid_calibration": DOCS + ", b as (select *, cast(least(floor(round(prob, 9) * 10), 9) as integer) as bin from pred where pred is not null) select bin, count(*) as n, round(avg(prob), 4) as conf, round(avg(cast(gold = pred as integer)), 6) as acc from b group by all",
    "lid_indomain_sample": f"with {LINES} select label, doc_id, cast(pos as integer) as pos, cast(rank as integer) as rank from (select *, row_number() over (partition by label order by md5(concat_ws(':', 'in-domain', doc_id, pos)), doc_id, pos) as rank from lines where part = 9) where rank <= 50",
    "lid_label_overlap": f"with {LINES}, k as (select distinct label from lines where part < 8), b as (select distinct label from {values(LANGUAGES, 'label', 'area', 'constructed', 'macro')}) select count(*) as n_bench, count(k.label) as n_covered from b left join k using (label)",
    "lid_cousins": NARROW + "select gold, pred, count(*) as n, round(avg(prob), 4) as mean_prob from pred where gold = 'spa_Latn' and pred is not null group by all",
    "label_parse": f"with l as (select distinct {LABEL} as label from documents union all select unnest(['und_Mong', 'zxx-Latn', 'jpn-Jpan'])), p as (select label, regexp_extract(label, '^([a-z]{{3}})[-_]', 1) as iso, regexp_extract(label, '^[a-z]{{3}}[-_](.+)$', 1) as script from l) select *, case when iso in ('und', 'zxx') then iso else 'lang' end as kind, iso not in ({', '.join(map(text, NO_WORD_BOUNDARY))}) as word_based from p",
    "curation_rules": f"with {LINES} select case op when 'delete' then null when 'keep' then label else coalesce(to_label, label) end as label, count(*) as n from lines left join {values(RULES, 'op', 'from_label', 'to_label')} r on label = from_label where op is distinct from 'delete' group by all",
    "curation_low_f1": f"{_LOW} select label, f1 from low",
    "curation_drop_labels": f"{_LOW} select label, count(*) as n from lines where label not in (select label from low) group by all",
    "curation_exclusive": f"with l as (select distinct {_RELABELLED} as label from documents) select m.label as macro, l.label from l join {values(LANGUAGES, 'label', 'area', 'constructed', 'macro')} k on l.label = k.label join l m on split_part(m.label, '_', 1) = k.macro",
    "label_mixture": WEAK + ", c as (select gold, pred, count(*) as n from pred where pred is not null group by all), s as (select *, round(n / sum(n) over (partition by gold), 6) as share from c) select * from s where gold <> pred and share >= 0.01",
    "split_mass": f"with {LINES}, {TEST}, {model(UNITS, buckets=64, tau=4.0)}, w as (select id, max(prob) as top, arg_max(label, prob) as won from probs group by 1), p as (select id, a, b, sum(prob) as both_ from probs join (select 'eng_Latn' as a, 'deu_Latn' as b union all select 'fra_Latn', 'spa_Latn') on label in (a, b) group by all) select a, b, count(*) as n, round(avg(top), 4) as top, round(avg(both_), 4) as both from p join w using (id) where won in (a, b) group by all",
    "train_split": f"with {LINES} select label, case when part < 8 then 'train' when part < 9 then 'valid' else 'test' end as split, count(*) as n from lines group by all",
    "train_dedup": f"with {LINES}, f as (select min({{'d': doc_id, 'p': pos}}) as first, count(*) as copies from lines group by md5(trim(regexp_replace(lower(line), '\\s+', ' ', 'g')))) select first.d as doc_id, cast(first.p as integer) as pos, copies from f",
    "train_cap": f"with {LINES} select label, doc_id, cast(pos as integer) as pos, cast(rank as integer) as rank from (select *, row_number() over (partition by label order by md5(concat_ws(':', doc_id, pos)), doc_id, pos) as rank from lines) where rank <= 100",
    "train_temperature": f"with {LINES}, z as (select label, count(*) as n from lines group by 1), r as (select label, least(1.0, 1000 * pow(n, 0.5) / sum(pow(n, 0.5)) over () / n) as rate from z) select label, doc_id, cast(pos as integer) as pos from lines join r using (label) where cast('0x' || substr(md5(concat_ws(':', 'temperature', doc_id, pos)), 1, 8) as bigint) / 4294967296.0 < rate",
    "union_sources": "select 'documents' as provenance, count(*) as n, count(source) as with_source from documents union all select 'conversations', count(*), 0 from conversations",
    "und_samples": und_rows(["Mong", "Newa", "Gran"], FOR_DOCUMENTS, "train", (5, 15), "doc_id"),
    "noise_pdf": pdf_rows(FOR_DOCUMENTS, "train", "doc_id"),
    "noise_spaced": f"select doc_id, {SPACED.format(e='text')} as line from documents",
    "noise_replacement": f"select doc_id, {with_replacements('text', 'doc_id', 0.3, 'train')} as line from documents",
    "noise_mojibake_arabic": f"select doc_id, translate(text, {text(noise.ARABIC_MOJIBAKE[0])}, {text(noise.ARABIC_MOJIBAKE[1])}) as line from documents where lang <> 'en'",
}

# --------------------------------------------------------------------------------------------- releases with reject rows

_R3 = f"select label, line from lines where part < 8 union all select label, line from ({rejects(REJECT_TRAIN, 'train')})"
_KINDS = values([(k, i) for i, k in enumerate([f"und_{s}" for s in noise.unseen_scripts()] + list(noise.KINDS))], "k", "place")
NOISE = f"noise_docs as (select {NOISE_ID} + place * 1000000 + row as doc_id, line as text, label as gold from ({rejects(REJECT_TEST, 'test')}) join {_KINDS} on k = kind)"
_MIXED = f"{NOISE}, mixed as (select doc_id as id, text as t, gold, false as is_noise from test union all select doc_id, text, gold, true from noise_docs)"
_SCRIPTED = "case when len(regexp_extract_all(t, '\\p{L}')) = 0 or len(regexp_extract_all(t, '\\p{Latin}')) > 0 then b1.pred end"
_BOTH = (
    f"with {LINES}, {TEST}, {_MIXED}, {model('select id, t from mixed', tag='1')}, {model('select id, t from mixed', _R3, pattern=chr(92) + 'S+', tag='3')}, "
    f"said as (select m.*, b1.pred as r1, b1.prob as prob1, {_SCRIPTED} as r2, b3.pred as r3 from mixed m left join best1 b1 using (id) left join best3 b3 using (id))"
)
_RELEASES = ("r1", "r2", "r3")
SQL["lid_release_delta"] = (
    _BOTH
    + "".join(f", cells_{r} as (select gold, coalesce({r}, 'none') as pred, count(*) as n from said group by all), {prf(f'prf_{r}', f'cells_{r}')}" for r in _RELEASES)
    + " select label, a.f1 as r1, b.f1 as r2, c.f1 as r3, round(b.f1 - a.f1, 6) as r2_gain, round(c.f1 - a.f1, 6) as r3_gain from prf_r1 a full join prf_r2 b using (label) full join prf_r3 c using (label)"
)
SQL["lid_release_noise"] = (
    _BOTH
    + " "
    + " union all ".join(f"select substr(gold, 1, 3) as kind, case when {r} is null then 'nothing' when regexp_matches({r}, '^(und|zxx)_') then 'reject' else 'language' end as said, count(*) as n, '{r}' as release from said where is_noise group by all" for r in _RELEASES)
)
_OUT = {"threshold": "coalesce(prob1 < 0.5, true)", "script": "r2 is null", "labels": "coalesce(regexp_matches(r3, '^(und|zxx)_'), true)"}
SQL["lid_rejection_vs_threshold"] = (
    _BOTH
    + " "
    + " union all ".join(f"select '{m}' as method, is_noise, count(*) as n, count(*) filter ({out}) as rejected, round(count(*) filter ({out}) / count(*), 6) as rate from said group by all" for m, out in _OUT.items())
)
SQL["noise_kinds"] = f"with {LINES} {rejects(20, 'train', ['Mong', 'Newa', 'Gran', 'Talu', 'Sylo'])}"
SQL["noise_binary"] = binary_rows(FOR_DOCUMENTS, "train", "doc_id")

# ------------------------------------------------------------------------------------------------------------- scripts

_SWAP = "case " + " ".join(f"when doc_id % 7 = {k} then translate(lower(text), {text(a)}, {text(b)})" for k, (a, b) in enumerate(SWAPS.values())) + " else text end"
SWAPPED = f"swapped as (select doc_id, {_SWAP} as text, {LABEL} as label from documents)"
_N = lambda s, t="text": f"len(regexp_extract_all({t}, '\\p{{{s}}}'))"
_LATIN = lambda t="text": f"len(regexp_extract_all({t}, '\\p{{Latin}}'))"
SQL["script_shares"] = f"with {SWAPPED}, c as (select doc_id, cast({_LATIN()} as bigint) as latn, cast({_N('Cyrillic')} as bigint) as cyrl, cast(len(list_filter(regexp_extract_all(text, '\\p{{Arabic}}'), lambda x: regexp_matches(x, '\\p{{L}}'))) as bigint) as arab, cast({_N('Han')} as bigint) as hani from swapped) select *, (select k from (values ('Latn', latn), ('Cyrl', cyrl), ('Arab', arab), ('Hani', hani)) v(k, n) where n > 0 order by n desc, k limit 1) as main from c"
_GOODSHARE = "case when len(regexp_extract_all(line, '\\p{L}')) > 0 then len(regexp_extract_all(line, '\\p{Latin}')) / len(regexp_extract_all(line, '\\p{L}')) else 0.0 end"
SQL["script_filter"] = f"with {SWAPPED}, l as (select label, trim(l) as line from (select label, unnest(string_split(text, chr(10))) as l from swapped) where trim(l) <> '') select label, count(*) as n from l where {_GOODSHARE} >= 0.5 group by all"
SQL["admissible_labels"] = f"with l as (select distinct {LABEL} as label from documents union select unnest(['rus_Cyrl', 'und_Mong'])) select split_part(label, '_', 2) as script, string_agg(label, ',' order by label) as labels from l group by all"

# ------------------------------------------------------------------------------------------------------------- warnings

LS = "[trim(x) for x in string_split(text, chr(10)) if trim(x) <> '']"
DOC_LINES = f"d as (select doc_id, text, {LS} as ls from documents)"


def _tokens(e: str) -> str:
    return f"list_filter(regexp_split_to_array({e}, '\\s+'), lambda w: w <> '')"


def _share(a: str, b: str) -> str:
    return f"(case when {b} > 0 then {a} / {b} else 0.0 end)"


_SHORT = lambda ls: f"len(list_filter({ls}, lambda x: length(x) < 100))"
_EDGE = "greatest(cast(ceil(len(ls) * 0.2) as integer), 1)"
_CASE = lambda x: f"(len({_tokens(x)}) > 0 and {_share(f'len(list_filter({_tokens(x)}, lambda w: regexp_matches(w, {text(chr(94) + chr(92) + chr(112) + chr(123) + chr(76) + chr(117) + chr(125))})))', f'len({_tokens(x)})')} >= 0.5)"
_TECH = lambda t: f"(length({t}) > 0 and len(regexp_extract_all({t}, '[\\p{{N}}\\p{{P}}\\p{{S}}]')) / length({t}) >= 0.2)"


_UNCASED = lambda x: f"(len({_tokens(x)}) > 1 and regexp_matches({x}, '[\\p{{Han}}\\p{{Hiragana}}\\p{{Katakana}}\\p{{Thai}}]') and {_share(f'len(list_filter({_tokens(x)}, lambda w: length(w) <= 4))', f'len({_tokens(x)})')} >= 0.5)"
FLAGS = {
    "tiny": "len(ls) < 3",
    "short_sentences": f"len(ls) > 0 and {_share(_SHORT('ls'), 'len(ls)')} >= 0.5",
    "header": f"len(ls) > 0 and {_share(_SHORT(f'ls[1:{_EDGE}]'), f'len(ls[1:{_EDGE}])')} >= 0.5",
    "footer": f"len(ls) > 0 and {_share(_SHORT(f'ls[len(ls) - {_EDGE} + 1:len(ls)]'), _EDGE)} >= 0.5",
    "list_case": f"len(ls) > 0 and {_share(f'len(list_filter(ls, lambda x: {_CASE(chr(120))}))', 'len(ls)')} >= 0.5",
    "list_case_uncased": f"len(ls) > 0 and {_share(f'len(list_filter(ls, lambda x: {_UNCASED(chr(120))}))', 'len(ls)')} >= 0.5",
    "technical": _TECH("text"),
    "cursed": f"regexp_matches(text, {text('|'.join(W.CURSED))})",
    "repetition": "coalesce(rep, false)",
    "long_word": "regexp_matches(text, '\\S{101,}')",
    "filler": "contains(lower(text), 'lorem ipsum')",
    "policy": f"regexp_matches(lower(text), {text('|'.join(W.POLICY))})",
    "js": "regexp_matches(text, 'Java[Ss]cript')",
    "curly": "regexp_matches(text, '[{}]')",
    "adult": f"regexp_matches(lower(text), {text(chr(92) + 'b(' + '|'.join(W.LEXICON) + ')' + chr(92) + 'b')})",
}
_REPLINES = f"w as (select doc_id, pos, {_tokens('line')} as w from lines), rl as (select doc_id, pos, len(w) > 20 and ((len(w) - len(list_distinct(w))) / len(w) > 0.5 or (len(w) - 1 - len(list_distinct([w[i] || ' ' || w[i + 1] for i in range(1, len(w))]))) / (len(w) - 1) > 0.2) as rep from w), reps as (select doc_id, bool_or(rep) as rep from rl group by 1)"
WARN = f"with {LINES}, {_REPLINES}, d as (select *, {LS} as ls, coalesce((select rep from reps where reps.doc_id = documents.doc_id), false) as rep from documents)"
_INJECTED = "case " + " ".join(f"when doc_id % 13 = {k} then text || {text(p)}" for k, p in enumerate((" lorem ipsum dolor", " Read our Cookie Policy.", " Please enable JavaScript.", " {x}", " " + "w" * 101, " " + "w" * 100))) + " else text end"
for _name in ("tiny", "short_sentences", "header", "footer", "list_case", "technical", "cursed", "repetition", "adult"):
    SQL[{"short_sentences": "warn_short"}.get(_name, f"warn_{_name}")] = f"{WARN} select doc_id from d where {FLAGS[_name]}"
for _name in ("long_word", "filler", "policy", "js", "curly"):
    SQL[f"warn_{_name}"] = f"with d as (select doc_id, {_INJECTED} as text from documents) select doc_id from d where {FLAGS[_name]}"
SQL["warn_list_case_any"] = f"{WARN} select doc_id from d where len(list_filter(ls, lambda x: {_CASE('x')})) > 0"
SQL["warn_list_case_uncased"] = f"with {SWAPPED}, d as (select doc_id, text, {LS} as ls from swapped) select doc_id from d where {FLAGS['list_case_uncased']}"
SQL["warn_script_inconsistent"] = f"with {SWAPPED}, s as (select *, len(regexp_extract_all(text, '\\p{{L}}')) as letters, {_LATIN()} as latin from swapped) select doc_id from s where (letters > 0 and round(1 - latin / letters, 9) >= 0.1) or {_TECH('text')}"
_NAMED = "list_filter([" + ", ".join(f"case when {FLAGS[n]} then '{n}' end" for n in W.NAMES) + "], lambda x: x is not null)"
ANNOTATED = f"{WARN}, a as (select doc_id, lang, source, text, {_NAMED} as warnings from d)"
_IGN = "list_filter(warnings, lambda x: x not in ('short_sentences', 'header', 'footer'))"
_IGN2 = "list_filter(warnings, lambda x: x not in ('short_sentences', 'header', 'footer', 'long_word', 'repetition'))"
SQL |= {
    "warn_all": f"{ANNOTATED} select doc_id, array_to_string(warnings, ',') as warnings from a",
    "stream_annotate": f"{ANNOTATED} select doc_id, array_to_string(warnings, ',') as warnings from a",
    "stream_enrich": f"select doc_id, label, area as macroarea from (select doc_id, {LABEL} as label from documents) left join {values(LANGUAGES, 'label', 'area', 'constructed', 'macro')} using (label)",
    "warn_counts": f"{ANNOTATED} select warning, count(*) as n from (select unnest(warnings) as warning from a) group by all",
    "filter_document": f"{ANNOTATED} select doc_id from a where len({_IGN}) = 0",
    "filter_no_word_boundary": f"{ANNOTATED} select case when doc_id % 2 = 0 then 'jpn_Jpan' else 'eng_Latn' end as label, count(*) as n from a where len(case when doc_id % 2 = 0 then {_IGN2} else {_IGN} end) = 0 group by all",
    "filter_line": f"with {LINES}, {_REPLINES} select doc_id, count(*) as n_lines from lines join rl using (doc_id, pos) where not rep and not {_CASE('line')} and not {_TECH('line')} and not regexp_matches(line, '\\S{{101,}}|[{{}}]|Java[Ss]cript|{'|'.join(W.CURSED)}') and not regexp_matches(lower(line), 'lorem ipsum|{'|'.join(W.POLICY)}|\\b({'|'.join(W.LEXICON)})\\b') group by all",
    "warning_precision": f"{ANNOTATED}, j as (select warnings, quality from a join labels using (doc_id)), b as (select avg(cast(quality = 0 as integer)) as base from j) select warning, count(*) as n, count(*) filter (quality = 0) as bad, round(count(*) filter (quality = 0) / count(*), 6) as precision, round(count(*) filter (quality = 0) / count(*) / any_value(base), 4) as lift from (select unnest(warnings) as warning, quality from j), b group by all",
    "calibration_sample": f"with {LINES}, k as (select *, label || '_' || source as key from lines), s as (select key, count(*) as n from k group by 1), r as (select key, row_number() over (order by n desc, key) / count(*) over () as place from s), t as (select key, case when place <= 0.10 then 'top' when place <= 0.25 then 'middle' else 'bottom' end as stratum from r), c as (select key, stratum from (select *, row_number() over (partition by stratum order by md5(key), key) as pick from t) where pick = 1), z as (select stratum, k.key, doc_id, pos, row_number() over (partition by k.key order by md5(concat_ws(':', doc_id, pos)), doc_id, pos) as rank from k join c on k.key = c.key) select 'Latn' as script, stratum, key, doc_id, cast(pos as integer) as pos from z where rank <= 20",
    "coverage_compare": f"{ANNOTATED} select lang as label, count(*) filter (len({_IGN}) = 0) as docs_a, count(*) as docs_b, round(count(*) filter (len({_IGN}) = 0) / count(*), 6) as ratio from a group by all",
    "coverage_retention": f"{ANNOTATED} select lang as label, cast(length(cast(count(*) as varchar)) - 1 as integer) as bucket, count(*) as n_in, count(*) filter (len({_IGN}) = 0) as n_kept, round(count(*) filter (len({_IGN}) = 0) / count(*), 6) as share from a group by lang",
}

# --------------------------------------------------------------------------------------------------------------- corpus

_HOST = "lower(regexp_extract(url, '^[a-zA-Z]+://([^/:?#]+)', 1))"
_CLASSED = f"h as (select page_id, html, {_HOST} as host from pages), m as (select host, list_sort(list_distinct(list(class))) as classes from (select distinct host from h) join {{lists}} l on host = domain or ends_with(host, '.' || domain) group by 1), c as (select page_id, html, host, coalesce(classes, []) as classes from h left join m using (host))"
_SEEDS = values(SEEDS, "domain", "class")
_MORE = values((*SEEDS, ("blog.example.com", "blog")), "domain", "class")
_PUBLIC = f"not regexp_matches(x, {text(pii.PRIVATE)})"
_QUADS = f"regexp_extract_all(text, {text(pii.QUAD)})"
_GRAM4 = "list_distinct([w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3] for i in range(1, len(w) - 2)])"
_AREAS = f"select coalesce(x.area, 'all') as area, coalesce(x.bucket, -1) as bucket, count(*) as n_labels, cast(sum(n) as bigint) as n_docs from (select case when constructed then 'constructed' else coalesce(area, 'unknown') end as area, cast(length(cast(n as varchar)) - 1 as integer) as bucket, n from l left join {values(LANGUAGES, 'label', 'area', 'constructed', 'macro')} v using (label)) x group by cube (x.area, x.bucket)"
_ABROAD = "case " + " ".join(f"when doc_id % 7 = {k} then {text(v)}" for k, v in ABROAD.items()) + f" else {LABEL} end"
_WORDS = lambda t: f"regexp_extract_all(lower({t}), '[\\p{{L}}\\p{{N}}]+')"
_SENTENCES = f"sents as (select item_id, sent, {_WORDS('s')} as w from (select item_id, trim(unnest(regexp_split_to_array(text, '[.\\n]'))) as s, generate_subscripts(regexp_split_to_array(text, '[.\\n]'), 1) - 1 as sent from benchmark) where s <> ''), bg as (select item_id, sent, gram, count(*) over (partition by item_id, sent) as need from (select item_id, sent, unnest({_GRAM4}) as gram from sents))"
SQL |= {
    "decontaminate_sentence": f"with {LINES}, {_SENTENCES}, lg as (select doc_id, pos, unnest({_GRAM4}) as gram from (select doc_id, pos, {_WORDS('line')} as w from lines)) select doc_id, cast(pos as integer) as pos, item_id, cast(sent as integer) as sent from lg join bg using (gram) group by doc_id, pos, item_id, sent having count(*) >= any_value(need)",
    "decontaminate_document": f"with {_SENTENCES}, lg as (select doc_id, unnest({_GRAM4}) as gram from (select doc_id, {_WORDS('text')} as w from documents)) select doc_id, item_id, cast(sent as integer) as sent from lg join bg using (gram) group by doc_id, item_id, sent having count(*) >= 0.8 * any_value(need)",
    "content_classes": f"with {_CLASSED.format(lists=_SEEDS)} select page_id, host, array_to_string(classes, ',') as classes from c",
    "content_exclude": f"with {_CLASSED.format(lists=_MORE)} select page_id from c where not list_has_any(classes, ['adult', 'spam', 'blog'])",
    "coverage_class_share": f"with {_CLASSED.format(lists=_SEEDS)}, l as (select *, regexp_extract(html, '(?i)<html[^>]*\\blang=[\"'']?([a-zA-Z]{{2,3}})', 1) as lang from c), z as (select lang, cast(length(cast(count(*) as varchar)) - 1 as integer) as bucket from l group by 1), t as (select bucket, count(*) as total from l join z using (lang) group by 1) select bucket, class, count(*) as n, round(count(*) / any_value(total), 6) as share from (select bucket, unnest(classes) as class from l join z using (lang)) join t using (bucket) group by all",
    "pii_report": f"select doc_id, cast(len(regexp_extract_all(text, {text(pii.EMAIL)})) as integer) as email, cast(len(list_filter({_QUADS}, lambda x: {_PUBLIC})) as integer) as ip, cast(len(list_filter({_QUADS}, lambda x: not ({_PUBLIC}))) as integer) as private_ip from documents where regexp_matches(text, {text(pii.EMAIL)}) or regexp_matches(text, {text(pii.QUAD)})",
    "dedup_exact": "select min(doc_id) as doc_id, count(*) as copies from documents group by sha256(text)",
    "coverage_buckets": "with k as (select lang || '_' || source as key, count(*) as n from documents group by 1), b as (select cast(length(cast(n as varchar)) - 1 as integer) as bucket, count(*) as n_labels, cast(sum(n) as bigint) as n_docs from k group by 1) select *, cast(sum(n_labels) over (order by bucket desc) as bigint) as cumulative from b",
    "coverage_area": f"with l as (select {LABEL} as label, count(*) as n from documents group by 1) {_AREAS}",
    "coverage_area_constructed": f"with l as (select {_ABROAD} as label, count(*) as n from documents group by 1) {_AREAS}",
    "coverage_area_surrogate": "select r_name, n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by cube (r_name, n_name)",
    "coverage_contamination": WEAK + "select gold, count(*) as n, count(*) filter (pred = 'eng_Latn') as lost, round(count(*) filter (pred = 'eng_Latn') / count(*), 6) as share from pred where gold <> 'eng_Latn' group by all",
    "wall_time": f"with {LINES}, s as (select count(*) as s from lines), d as (select count(*) as d from documents) select 'given table' as corpus, round(d / 48.0 * (s / d / 1379.0 + 1 / 245.0) / 3600, 9) as hours from s, d union all select 'snapshot', round(3.16e9 / 48 * (20 / 1379 + 1 / 245) / 3600, 4)",
    "audit_sample": "with k as (select lang || '_' || source as label, doc_id from documents), n as (select distinct label from k order by md5('audit:' || label), label limit 40) select label, doc_id, cast(rank as integer) as rank from (select *, row_number() over (partition by label order by md5('audit:' || cast(doc_id as varchar)), doc_id) as rank from k where label in (select label from n)) where rank <= 20",
    "audit_out_of_model": NARROW + "select gold as label, count(*) as n, count(pred) as called, round(avg(prob), 4) as mean_prob from pred where gold not in ('eng_Latn', 'fra_Latn', 'deu_Latn') group by all",
    "audit_clues": "with c as (select page_id, regexp_extract(url, '^[a-zA-Z]+://[^/]+/([a-z]{2,3})/', 1) as url_code, regexp_extract(html, '(?i)<html[^>]*\\blang=[\"'']?([a-zA-Z]{2,3})', 1) as html_code from pages) select *, url_code = html_code as agree from c",
    "audit_affix": f"with {LINES}, t as (select doc_id, {_tokens('line')} as w from lines), x as (select doc_id, 'prefix' as kind, w[1] || ' ' || w[2] as affix from t where len(w) > 2 union all select doc_id, 'suffix', w[len(w) - 1] || ' ' || w[len(w)] from t where len(w) > 2) select doc_id, kind, affix, count(*) as lines from x group by all having count(*) >= 3",
    "audit_recleanse": f"select {LABEL} as label, count(*) as n from documents where lang <> 'es' group by all",
    "stream_dedup": "select distinct md5(text) as h from documents",
}

# ----------------------------------------------------------------------------------------------- two identifiers compared

_TWO = f"with {LINES}, {TEST}, {model(UNITS, tag='1')}, {model(UNITS, THREE, tag='2')}, p as (select test.doc_id, source, gold || '_' || source as truth, b1.pred || '_' || source as label_a, case when b2.prob >= 0.8 then b2.pred || '_' || source end as label_b from test join documents using (doc_id) left join best1 b1 on b1.id = test.doc_id left join best2 b2 on b2.id = test.doc_id), j as (select * from p where label_a is not null or label_b is not null), calls as (select distinct doc_id, unnest([label_a, label_b]) as label from j), few as (select label from calls where label is not null group by 1 having count(*) <= 10), rare as (select * from j where label_a is distinct from label_b and doc_id in (select doc_id from calls join few using (label)))"
_STATE = lambda c: f"case when {c} is null then 'miss' when {c} = truth then 'correct' else 'wrong' end"
SQL |= {
    "compare_disagree": _TWO + " select doc_id, label_a, label_b, truth from rare",
    "compare_outcomes": _TWO + f", c as (select * from rare order by md5('compare:' || cast(doc_id as varchar)), doc_id limit 20), s as (select {_STATE('label_a')} as state_a, {_STATE('label_b')} as state_b from c) select state_a, count(*) filter (state_b = 'correct') as correct, count(*) filter (state_b = 'wrong') as wrong, count(*) filter (state_b = 'miss') as miss from s group by all",
    "compare_extrapolate": _TWO + " select count(*) as n, count(*) / 0.1 * 100 as pages, 260 / 0.01 * 100 as published from rare",
    "compare_call_rate": _TWO + " select 'a' as lid, count(*) as n, count(label_a) as calls, round(count(label_a) / count(*), 6) as rate from p union all select 'b', count(*), count(label_b), round(count(label_b) / count(*), 6) from p",
}
SQL |= relational.SQL | stream.SQL

# ------------------------------------------------------------------------------------- texts of pages, other identification


def replaced(pattern: str, by: str) -> str:
    """md5 of texts with each match ``f[i]`` replaced, for documents that have one."""
    return f"with p as (select doc_id, regexp_split_to_array(text, {text(pattern)}) as g, regexp_extract_all(text, {text(pattern)}) as f from documents) select doc_id, md5(array_to_string([g[i] || case when i <= len(f) then {by} else '' end for i in range(1, len(g) + 1)], '')) as h from p where len(f) > 0"


def _picked(pool: tuple[str, ...]) -> str:
    return f"[{', '.join(map(text, pool))}][cast({h32('f[i]')} % {len(pool)} + 1 as integer)]"


def _page_text() -> str:
    t = "html"
    for tag in ("head", "script", "style", "nav", "footer"):
        t = f"regexp_replace({t}, '(?is)<{tag}\\b.*?</{tag}\\s*>', '', 'g')"
    t = f"regexp_replace({t}, '(?s)<!--.*?-->', '', 'g')"
    t = f"regexp_replace(regexp_replace({t}, {text(html.BLOCKS)}, chr(10), 'g'), '(?s)<[^>]*>', '', 'g')"
    for name, ch in html.ENTITIES:
        t = f"replace({t}, {text(name)}, {text(ch)})"
    t = f"regexp_replace(regexp_replace({t}, '[ \\t\\r]+', ' ', 'g'), ' ?\\n ?', chr(10), 'g')"
    return f"page_text as (select page_id, {_HOST} as host, regexp_replace(regexp_replace({t}, '\\n+', chr(10), 'g'), '^[ \\n]+|[ \\n]+$', '', 'g') as text, {LABEL.replace('case lang', 'case regexp_extract(html, ' + text(_HTML_LANG) + ', 1)')} as gold from pages)"


_HTML_LANG = "(?i)<html[^>]*\\blang=[\"']?([a-zA-Z]{2,3})"
PAGES = _page_text()
_FNV = "list_reduce(list_prepend(cast(2166136261 as bigint), [cast('0x' || substr(hex(encode(g)), 2 * i + 1, 2) as bigint) for i in range(length(hex(encode(g))) // 2)]), lambda h, b: (xor(h, b) * 16777619) & 4294967295)"
_TURNS = "select conv_id * 1000 + turn as id, text as t from conversations"
_EVERY = "select cast(doc_id as varchar) as id, text as t from documents union all select cast(doc_id as varchar) || ':' || cast(pos as varchar), line from lines"
_SEEDED = [model(UNITS, f"select label, line from lines where part < 8 and {h32(f'concat_ws({text(chr(58))}, {text(str(k))}, doc_id)')} % 10 > 0", tag=str(k)) for k in range(3)]
SQL |= {
    "hash_buckets": f"with {LINES}, {vocabulary()} select g, {h32('g')} % {BUCKETS} as b, {_FNV} as fnv from voc",
    "pii_email": replaced(pii.EMAIL, f"case when f[i] in ({', '.join(map(text, pii.EMAILS))}) then f[i] else {_picked(pii.EMAILS)} end"),
    "pii_ip": replaced(pii.QUAD, f"case when regexp_matches(f[i], {text(pii.PRIVATE)}) or f[i] in ({', '.join(map(text, pii.POOL))}) then f[i] else {_picked(pii.POOL)} end"),
    "noise_mojibake_latin": f"select doc_id, {latin_bytes('text')} as line from documents where lang <> 'en'",
    "script_one_pass": f"with {SWAPPED}, c as (select doc_id, unnest([{{'script': 'Latn', 'n': {_LATIN()}}}, {{'script': 'Cyrl', 'n': {_N('Cyrillic')}}}, {{'script': 'Arab', 'n': len(list_filter(regexp_extract_all(text, '\\p{{Arabic}}'), lambda x: regexp_matches(x, '\\p{{L}}')))}}, {{'script': 'Hani', 'n': {_N('Han')}}}]) as s from swapped) select doc_id, s.script as script, cast(s.n as bigint) as n from c where s.n > 0",
    "html_text": f"with {PAGES} select page_id, host, gold, cast(length(text) as integer) as n, regexp_matches(text, '[<>]') or contains(text, 'function(') as markup_left from page_text",
    "noise_harvest": f"with {PAGES} select page_id, seed from page_text, (select unnest(['idiot', '!!', '###']) as seed) where contains(text, seed)",
    "lid_conversations": f"with {LINES}, {model(_TURNS)}, n as (select conv_id, pred, count(*) as n from conversations left join best on id = conv_id * 1000 + turn group by all), c as (select conv_id, max(n) as most, sum(n) as n from n group by 1) select count(*) as conversations, round(sum(most) / sum(n), 6) as consistency from c",
    "audit_score": f"with {LINES}, {model('select doc_id as id, text as t from documents')}, k as (select lang || '_' || source as label, doc_id, {LABEL} as gold, len({_WORDS('text')}) as n_words from documents), n as (select distinct label from k order by md5('audit:' || label), label limit 40), s as (select *, row_number() over (partition by label order by md5('audit:' || cast(doc_id as varchar)), doc_id) as rank from k where label in (select label from n)), p as (select label, avg(cast(pred = gold as integer)) as share from s join best on id = doc_id where rank <= 20 and pred is not null and n_words >= {TOO_SHORT} group by 1) select count(*) as n_labels, round(avg(share), 6) as macro_avg, round(median(share), 6) as median from p",
    "pipeline_snapshots": f"{ANNOTATED}, k as (select doc_id from a where len({_IGN}) = 0) select '2024-10' as snapshot, count(*) as n from k union all select '2024-18', count(*) from k where doc_id % 3 = 0 union all select '2024-22', count(*) from k where doc_id % 5 = 0",
    "warn_lid_inconsistent": f"with {LINES}, {model(_EVERY)}, l as (select doc_id, pred from lines left join best on id = cast(doc_id as varchar) || ':' || cast(pos as varchar)), d as (select doc_id, pred from documents left join best on id = cast(doc_id as varchar)) select d.doc_id, d.pred from d join l using (doc_id) group by all having count(*) filter (l.pred is distinct from d.pred) / count(*) >= 0.2",
    "lid_domain_gap": f"with {LINES}, {TEST}, {PAGES}, {model(UNITS, tag='1')}, {model('select page_id as id, text as t from page_text', tag='2')}, cells_1 as (select gold, coalesce(pred, 'none') as pred, count(*) as n from test left join best1 on id = doc_id group by all), cells_2 as (select gold, coalesce(pred, 'none') as pred, count(*) as n from page_text left join best2 on id = page_id group by all), {prf('prf1', 'cells_1')}, {prf('prf2', 'cells_2')} select label, a.f1 as f1_in, b.f1 as f1_out, round(coalesce(a.f1, 0) - coalesce(b.f1, 0), 6) as gap from prf1 a full join prf2 b using (label)",
    "lid_seed_variance": f"with {LINES}, {TEST}, {', '.join(_SEEDED)}, "
    + ", ".join(f"cells_{k} as (select gold, coalesce(pred, 'none') as pred, count(*) as n from test left join best{k} on id = doc_id group by all), {prf(f'prf{k}', f'cells_{k}')}" for k in range(3))
    + ", v as ("
    + " union all ".join(f"select round(avg(f1), 6) as value from prf{k}" for k in range(3))
    + ") select round(avg(value), 6) as mean, round(stddev_pop(value), 6) as deviation from v",
}

# ------------------------------------------------------------------------------------------------------- the corpus run

_SAMPLED = "n as (select distinct label from k order by md5('audit:' || label), label limit 40), s as (select *, row_number() over (partition by label order by md5('audit:' || cast(doc_id as varchar)), doc_id) as rank from k where label in (select label from n))"
SQL["audit_undeterminable"] = f"with k as (select lang || '_' || source as label, doc_id, len({_WORDS('text')}) as n_words from documents), {_SAMPLED} select label, doc_id from s where rank <= 20 and n_words < {TOO_SHORT}"
_RAW = "corpus as (select doc_id, text, source, null as lang from documents union all select doc_id, text, 'noise', null from noise_docs)"
_PREFIX = "corpus as (select doc_id, text, source, null as lang from documents where doc_id * 10 <= (select max(doc_id) from documents))"
_CLINES = LINES.replace("lines as", "clines as", 1).replace("from documents", "from corpus")
_CREPS = _REPLINES.replace("from lines", "from clines")
_CORPUS_UNITS = "select 'd:' || doc_id as id, text as t from corpus union all select 'l:' || doc_id || ':' || pos, line from clines"
_CD = f"d as (select *, {LS} as ls, coalesce((select rep from reps where reps.doc_id = corpus.doc_id), false) as rep from corpus)"


def run_of(tag: str, train: str, pattern: str = r"\p{L}+") -> str:
    """CTEs from corpus, clines, d to run<tag> (doc_id, text, label, warnings, reason)."""
    inconsistent = f"(select doc_id, count(*) filter (bl.pred is distinct from bd.pred) / count(*) >= 0.6 as lid from clines left join best{tag} bl on bl.id = 'l:' || doc_id || ':' || pos left join best{tag} bd on bd.id = 'd:' || doc_id group by all)"
    letters = "len(regexp_extract_all(text, '\\p{L}'))"
    script = f"({letters} > 0 and round(1 - {_LATIN()} / {letters}, 9) >= 0.1) or {_TECH('text')}"
    named = f"list_concat({_NAMED}, list_filter([case when lid then 'lid_inconsistent' end, case when {script} then 'script_inconsistent' end], lambda x: x is not null))"
    return (
        f"{model(_CORPUS_UNITS, train, pattern=pattern, tag=tag)}, named{tag} as (select d.doc_id, text, source, pred as label, {named} as warnings from d left join {inconsistent} i on i.doc_id = d.doc_id left join best{tag} on id = 'd:' || d.doc_id), "
        f"run{tag} as (select *, case when label is null or regexp_matches(label, '^(und|zxx)_') then 'rejected' when len({_IGN}) > 0 then ({_IGN})[1] end as reason from named{tag})"
    )


_TRAIN = "select label, line from lines where part < 8"
_RUN3 = f"with {LINES}, {NOISE}, {_RAW}, {_CLINES}, {_CREPS}, {_CD}, {run_of('3', _R3, chr(92) + 'S+')}"
_RUNC = f"with {LINES}, {NOISE}, {_RAW}, {_CLINES}, {_CREPS}, {_CD}, {run_of('c', THREE)}"
_STATS = " select label, coalesce(reason, 'kept') as reason, count(*) as n from run{} group by all"
_JOINED = "array_to_string([g[i] || case when i <= len(f) then {by} else '' end for i in range(1, len(g) + 1)], '')"
_MAIL = f"case when f[i] in ({', '.join(map(text, pii.EMAILS))}) then f[i] else {_picked(pii.EMAILS)} end"
_ADDRESS = f"case when regexp_matches(f[i], {text(pii.PRIVATE)}) or f[i] in ({', '.join(map(text, pii.POOL))}) then f[i] else {_picked(pii.POOL)} end"
_CUT = lambda column, pattern: f"regexp_split_to_array({column}, {text(pattern)}) as g, regexp_extract_all({column}, {text(pattern)}) as f"
SQL |= {
    "pipeline_stats": _RUN3 + _STATS.format("3"),
    "pipeline_swap": _RUNC + _STATS.format("c"),
    "pipeline_counters": _RUN3 + " select unnest(['read', 'rejected', 'filtered', 'kept']) as counter, unnest([count(*), count(*) filter (reason = 'rejected'), count(*) filter (reason <> 'rejected'), count(*) filter (reason is null)]) as n from run3",
    "pipeline_kept": _RUN3
    + f", k as (select * from run3 where reason is null), m as (select doc_id, label, warnings, text, {_CUT('text', pii.EMAIL)} from k), n as (select doc_id, label, warnings, text, cast(len(f) as integer) as email, {_JOINED.format(by=_MAIL)} as clean from m), "
    + f"a as (select doc_id, label, warnings, email, cast(len(list_filter({_QUADS}, lambda x: {_PUBLIC})) as integer) as ip, {_CUT('clean', pii.QUAD)} from n) select doc_id, label, array_to_string(warnings, ',') as warnings, md5({_JOINED.format(by=_ADDRESS)}) as h, email, ip from a",
    "coverage_retention_predicted": _RUN3 + ", t as (select label, count(*) as n_in, count(*) filter (reason is null) as n_kept from run3 where reason is distinct from 'rejected' group by all) select label, cast(length(cast(n_in as varchar)) - 1 as integer) as bucket, n_in, n_kept, round(n_kept / n_in, 6) as share from t",
    "coverage_prior_corpus": _RUN3
    + f", {model('select doc_id as id, text as t from corpus', THREE, tag='c')}, x as (select label, count(*) as docs_a from run3 where reason is null group by 1), y as (select pred as label, count(*) as docs_b from bestc where prob >= 0.8 group by 1) select label, coalesce(docs_a, 0) as docs_a, coalesce(docs_b, 0) as docs_b, case when docs_b > 0 then round(coalesce(docs_a, 0) / docs_b, 6) end as ratio from x full join y using (label)",
    "compare_pipelines": f"with {LINES}, {_PREFIX}, {_CLINES}, {_CREPS}, {_CD}, {run_of('a', _TRAIN)}, {run_of('b', THREE)} select coalesce(a.label, 'none') as label_a, coalesce(b.label, 'none') as label_b, count(*) as n from (select * from runa where reason is null) a full join (select * from runb where reason is null) b using (doc_id) group by all",
}
_BENCHES = {
    "documents": "select doc_id as id, text as t, gold from test",
    "lines": "select doc_id * 100000 + pos as id, line as t, label as gold from lines where part = 9 qualify row_number() over (partition by label order by md5(concat_ws(':', 'in-domain', doc_id, pos)), doc_id, pos) <= 50",
    "pages": "select page_id as id, text as t, gold from page_text",
}
_TESTED = "tested as (" + " union all ".join(f"select '{b}' as bench, '{b}:' || id as id, t, gold from ({q})" for b, q in _BENCHES.items()) + ")"
_MODELS = {"full": model("select id, t from tested", tag="f"), "compact": model("select id, t from tested", buckets=4096, tag="k"), "closed": model("select id, t from tested", THREE, tag="c")}
SQL["lid_benchmark_table"] = f"with {LINES}, {TEST}, {PAGES}, {_TESTED}, {', '.join(_MODELS.values())}" + "".join(
    f", cells_{m}_{b} as (select gold, coalesce(pred, 'none') as pred, count(*) as n from tested left join best{tag} using (id) where bench = '{b}' group by all), {prf(f'prf_{m}_{b}', f'cells_{m}_{b}')}" for m, tag in (("full", "f"), ("compact", "k"), ("closed", "c")) for b in _BENCHES
) + " " + " union all ".join(f"select '{m}' as model, '{b}' as bench, round(avg(f1), 4) as f1, round(avg(fpr), 4) as fpr from prf_{m}_{b}" for m in _MODELS for b in _BENCHES)
