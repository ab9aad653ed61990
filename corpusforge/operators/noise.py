"""Reject classes: text of unseen scripts, and six kinds of web noise, drawn by hash so that every run gives the same rows."""

from __future__ import annotations

import unicodedata
from functools import lru_cache

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corpusforge.functions.scripts import PATTERNS
from corpusforge.functions.text import col, drawn

#: ISO 15924 codes of the scripts that have letters in Unicode.
SCRIPTS = (
    "Adlm Aghb Ahom Arab Armi Armn Avst Bali Bamu Bass Batk Beng Bhks Bopo Brah Bugi Buhd Cakm Cans Cari Cham Cher Chrs Copt Cpmn Cprt Cyrl Deva Diak Dogr Dsrt Dupl Egyp Elba Elym Ethi Geor Glag Gong Gonm "
    "Goth Gran Grek Gujr Guru Hang Hani Hano Hatr Hebr Hira Hluw Hmng Hmnp Hung Ital Java Kali Kana Kawi Khar Khmr Khoj Kits Knda Kthi Lana Laoo Latn Lepc Limb Lina Linb Lisu Lyci Lydi Mahj Maka Mand Mani "
    "Marc Medf Mend Merc Mero Miao Mlym Modi Mong Mroo Mtei Mult Mymr Nagm Nand Narb Nbat Newa Nkoo Nshu Ogam Olck Orkh Orya Osge Osma Ougr Palm Pauc Perm Phag Phli Phlp Phnx Prti Rjng Rohg Runr Samr Sarb "
    "Saur Shaw Shrd Sidd Sind Sinh Sogd Sogo Sora Soyo Sund Sylo Syrc Tagb Takr Tale Talu Taml Tang Tavt Telu Tfng Tglg Thaa Thai Tibt Tirh Tnsa Toto Ugar Vaii Vith Wara Wcho Xpeo Xsux Yezi Yiii Zanb"
).split()
#: What the Latin gibberish of mis-rendered documents is made of, the vowels that come out mangled, and what
#: texts read in an Arabic code page are full of.
STROKES = "ijl"
VOWELS = "áàãâäéèêëíìîïóòõôöúùûü"
ARABIC_SIGNS = "ˆ®±§طظ"
#: How UTF-8 bytes of Latin letters look when read as Windows-1256, by letter.
ARABIC_MOJIBAKE = ("àáâäçèéêëíîïñóôöùúûü", "طظط±ط§طھظٹآ®طظ±ط¯ظˆآ§ط³طظظظظ")
#: The label of each kind of noise.
KINDS = {"pdf": "zxx_Latn", "spaced": "zxx_Latn", "binary": "zxx_Latn", "mojibake_latin": "zxx_Latn", "mojibake_arabic": "zxx_Arab", "replacement": "zxx_Zzzz"}


def unseen_scripts(trained: tuple[str, ...] = tuple(PATTERNS)) -> list[str]:
    """Scripts without training text: all but those of the trained languages, a label each."""
    return [s for s in SCRIPTS if s not in trained]


@lru_cache(maxsize=1)
def _letters() -> str:
    """All letters that lower case leaves as they are."""
    chars = map(chr, [*range(0xD800), *range(0xE000, 0x110000)])
    return "".join(c for c in chars if unicodedata.category(c)[0] == "L" and c.lower() == c)


@lru_cache(maxsize=len(SCRIPTS))
def alphabet(script: str) -> str:
    """The letters of a script, from the Unicode tables of the ``regex`` library."""
    import regex

    return "".join(regex.findall(rf"\p{{Script={script}}}", _letters()))


def _drawn_text(seed: str, name: Column, row: Column, letters: Column, words: tuple[int, int], length: tuple[int, int]) -> Column:
    """Words of drawn number, length and letters; ``letters`` is an array."""
    size = F.size(letters)
    between = lambda low, high, *parts: (drawn(seed, name, row, *parts) % (high - low + 1) + low).cast("int")

    def word(w: Column) -> Column:
        return F.array_join(F.transform(F.sequence(F.lit(1), between(*length, w, "n")), lambda i: F.get(letters, (drawn(seed, name, row, w, i) % size).cast("int"))), "")

    return F.array_join(F.transform(F.sequence(F.lit(1), between(*words)), word), " ")


def drawn_lines(spark: SparkSession, alphabets: dict[str, str], n: int, words: tuple[int, int], length: tuple[int, int], seed: str) -> DataFrame:
    """(name, row, line): n lines of random words for each named alphabet; the rows are spread by name and by hundreds."""
    table = spark.createDataFrame([(name, list(letters)) for name, letters in alphabets.items()], "name string, letters array<string>")
    many = min(len(alphabets) * ((n - 1) // 100 + 1), 16 * spark.sparkContext.defaultParallelism)
    blocks = table.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit((n - 1) // 100)))).repartition(many, "name", "block")
    rows = blocks.withColumn("row", F.explode(F.sequence(F.col("block").cast("long") * 100, F.least(F.col("block").cast("long") * 100 + 99, F.lit(n - 1).cast("long")))))
    return rows.select("name", "row", _drawn_text(seed, F.col("name"), F.col("row"), F.col("letters"), words, length).alias("line"))


def drawn_for(docs: DataFrame, alphabets: dict[str, str], words: tuple[int, int], length: tuple[int, int], seed: str) -> DataFrame:
    """(name, doc_id, line): for each document and named alphabet a line of random words, drawn by the document's text."""
    table = docs.sparkSession.createDataFrame([(name, list(letters)) for name, letters in alphabets.items()], "name string, letters array<string>")
    rows = docs.select("doc_id", F.md5("text").alias("of")).crossJoin(F.broadcast(table))
    return rows.select("name", "doc_id", _drawn_text(seed, F.col("name"), F.col("of"), F.col("letters"), words, length).alias("line"))


def undetermined_for(docs: DataFrame, scripts: list[str], words: tuple[int, int] = (5, 15), length: tuple[int, int] = (2, 10), seed: str = "train") -> DataFrame:
    """(label, doc_id, line): for each document a line of each unseen script."""
    rows = drawn_for(docs, {s: alphabet(s) for s in scripts}, words, length, seed)
    return rows.select(F.concat(F.lit("und_"), "name").alias("label"), "doc_id", "line")


def undetermined(spark: SparkSession, scripts: list[str], n: int = 100_000, words: tuple[int, int] = (5, 15), length: tuple[int, int] = (2, 10), seed: str = "train") -> DataFrame:
    """(label, row, line): for each unseen script n lines of random words of its letters."""
    rows = drawn_lines(spark, {s: alphabet(s) for s in scripts}, n, words, length, seed)
    return rows.select(F.concat(F.lit("und_"), "name").alias("label"), "row", "line")


def misrendered_pdf(spark: SparkSession, n: int, seed: str = "train") -> DataFrame:
    """(row, line): gibberish of one and two strokes between spaces."""
    return drawn_lines(spark, {"pdf": STROKES}, n, (10, 29), (1, 2), seed).select("row", "line")


def spaced(text: Column | str) -> Column:
    """Every character apart."""
    return F.array_join(F.split(F.regexp_replace(col(text), r"\s+", ""), ""), " ")


def misrendered_pdf_for(docs: DataFrame, seed: str = "train") -> DataFrame:
    """(doc_id, line): for each document a line of strokes."""
    return drawn_for(docs, {"pdf": STROKES}, (10, 29), (1, 2), seed).select("doc_id", "line")


def _bytes(key: Column, seed: str) -> Column:
    """64 bytes drawn by a key, as text."""
    chain = F.concat(*[F.md5(F.concat_ws(":", F.lit(seed), F.lit("bin"), key, F.lit(str(k)))) for k in range(4)])
    return visible_bytes(F.unhex(chain))


def binary(spark: SparkSession, n: int, seed: str = "train") -> DataFrame:
    """(row, line): 64 bytes read as Latin-1 text, without white space and control characters."""
    return spark.range(n).select(F.col("id").alias("row"), _bytes(F.col("id").cast("string"), seed).alias("line"))


def binary_for(docs: DataFrame, seed: str = "train") -> DataFrame:
    """(doc_id, line): for each document 64 bytes read as text, drawn by its text."""
    return docs.select("doc_id", _bytes(F.md5("text"), seed).alias("line"))


def visible_bytes(content: Column) -> Column:
    """Bytes as an editor shows them in Latin-1, without white space and control characters."""
    return F.regexp_replace(F.decode(content, "ISO-8859-1"), "[\\x00-\\x20\\x7F-\\xA0]", "")


def binary_files(spark: SparkSession, path: str, width: int = 256, most: int = 64 << 20) -> DataFrame:
    """(path, row, line): files of any kind opened as text, in lines of ``width`` bytes; larger files than ``most`` are an error.

    Such a file is one value in memory, as Spark's binary source reads it; images and the like are far smaller.
    """
    files = spark.read.format("binaryFile").load(path)
    whole = files.select("path", F.when(F.col("length") <= most, F.col("content")).otherwise(F.raise_error(F.lit("file too large"))).alias("content"))
    cut = whole.select("path", "content", F.posexplode(F.sequence(F.lit(0), F.greatest(F.ceil(F.octet_length("content") / width).cast("int") - 1, F.lit(0)))).alias("row", "at"))
    return cut.select("path", F.col("row").cast("long").alias("row"), visible_bytes(F.substring("content", F.col("at") * width + 1, F.lit(width))).alias("line"))


def mangled(spark: SparkSession, kind: str, n: int, seed: str = "train") -> DataFrame:
    """(row, line) of mojibake: accented vowels in words, read in a Latin or an Arabic code page."""
    rows = drawn_lines(spark, {kind: VOWELS if kind == "mojibake_latin" else ARABIC_SIGNS}, n, (5, 15), (2, 8), seed)
    return rows.select("row", (mojibake_latin("line") if kind == "mojibake_latin" else F.col("line")).alias("line"))


def from_lines(lines: DataFrame, kind: str, n: int, seed: str = "train") -> DataFrame:
    """(row, line): n lines of a corpus (doc_id, pos, line), chosen by hash, spaced out or with replacement characters."""
    order = F.md5(F.concat_ws(":", F.lit(seed), F.lit(kind), "doc_id", "pos"))
    chosen = lines.select("doc_id", "pos", "line").orderBy(order, "doc_id", "pos").limit(n)
    key = F.concat_ws(":", "doc_id", "pos")
    bad = spaced("line") if kind == "spaced" else replacement_char("line", key, 0.5, seed)
    return chosen.select((F.row_number().over(Window.orderBy(order, "doc_id", "pos")) - 1).cast("long").alias("row"), bad.alias("line"))  # n rows


def rejects(spark: SparkSession, lines: DataFrame, n: int, seed: str = "train", scripts: list[str] | None = None, words: tuple[int, int] = (5, 15)) -> DataFrame:
    """(kind, label, row, line): n lines of every undetermined label and of every kind of noise."""
    und = undetermined(spark, unseen_scripts() if scripts is None else scripts, n, words=words, seed=seed)
    out = und.select(F.col("label").alias("kind"), "label", "row", "line")
    made = {
        "pdf": misrendered_pdf(spark, n, seed), "binary": binary(spark, n, seed), "spaced": from_lines(lines, "spaced", n, seed), "replacement": from_lines(lines, "replacement", n, seed),
        "mojibake_latin": mangled(spark, "mojibake_latin", n, seed), "mojibake_arabic": mangled(spark, "mojibake_arabic", n, seed),
    }
    for kind, rows in made.items():
        out = out.union(rows.select(F.lit(kind).alias("kind"), F.lit(KINDS[kind]).alias("label"), "row", "line"))
    return out


def mojibake_latin(text: Column | str) -> Column:
    """UTF-8 read as Latin-1."""
    return F.decode(F.encode(col(text), "UTF-8"), "ISO-8859-1")


def mojibake_arabic(text: Column | str) -> Column:
    """Accented letters as an Arabic code page shows them, letter by letter."""
    return F.translate(col(text), *ARABIC_MOJIBAKE)


def replacement_char(text: Column | str, key: Column | str, rate: float = 0.3, seed: str = "train") -> Column:
    """Some characters become U+FFFD; ``key`` tells rows apart."""
    per_mille = int(rate * 1000)
    chars = F.split(col(text), "")
    return F.array_join(F.transform(chars, lambda c, i: F.when(drawn(seed, "fffd", col(key), i) % 1000 < per_mille, F.lit("�")).otherwise(c)), "")


def harvest(pages: DataFrame, seeds: DataFrame, text: str = "text") -> DataFrame:
    """(page_id, seed) of pages that hold a seed phrase; the seeds are a short list."""
    return pages.join(F.broadcast(seeds), F.contains(F.col(text), F.col("seed"))).select("page_id", "seed")
