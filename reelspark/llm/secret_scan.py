"""Secret scan with a random forest that removes false positives; DataFrame functions only.

Candidates are, whatever their length: values that follow an assignment (``=`` or ``:``) or a keyword, strings with a
known prefix, a private key's heading; and anywhere else runs of at least ``SHORTEST`` key-like characters with a digit.
A name and its value are two candidates at most, cut at the ``=``; a value ends at white space or its quote, and without
quotes at a separator. All of a text's candidates are found by one regular expression, cut out row-locally and kept with
what stands around them in the whole text. Features: length, transitions between character kinds, dictionary coverage, spread of
characters, shapes (hex, UUID, digits only, known prefixes, placeholders), path, and the neighbouring words. The forest is
fitted by Spark's own learner on labelled findings and compiled into one column expression, so that
scoring needs neither a join nor Python and no text is ever shuffled. The dictionary is the corpus' own most frequent
words (``dictionary``: counted over all texts; a user's table of words can take its place), as one expression that tries common beginnings once.

Defined results: null and empty texts have no findings; repeated rows give repeated findings; many
candidates in one very long text are dealt with in chunks of ``CHUNK``; the two sentinels (Unicode
noncharacters) in a text count as replacement characters.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SHORTEST, CHUNK, THRESHOLD, MASK = 16, 512, 0.5, "[SECRET]"
_RUN = "A-Za-z0-9+/_-"
_PREFIXES = "AKIA|ASIA|ghp_|gho_|glpat-|sk-|sk_live_|xox[abp]-|eyJ|AIza"
#: Written out in both cases, and white space as a list: Java's and Python's classes differ beyond ASCII.
_NAMES = "|".join("".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in w) for w in ("token", "secret", "passwd", "password", "passphrase", "pwd", "api[ _-]?key", "access[ _-]?key", "private[ _-]?key", "authorization", "auth", "credential", "bearer", "basic", "signature")).replace("[[", "[").replace("]]", "]")
#: Tried at the first letters of words only, which most places of a text are not.
_WORD = rf"(?<![A-Za-z])(?=[TtSsPpAaCcBb])(?:{_NAMES})s?"
_SPACE = r" \t\n\x0B\f\r\x85\xA0   　"
_SET = r"[=:]{1,2}+>?"
#: A keyword in a value's place ("Authorization: Bearer ...") leads on to the value.
_LED = rf"""(?!(?:{_NAMES})s?[ \t"'`=:])"""
_QUOTED = rf"""{_LED}[^{_SPACE}"'`=:]+(?:={{1,2}}(?![^{_SPACE}"'`]))?"""
_PLAIN = rf"""{_LED}(?!//)[^{_SPACE}"'`=:,;|<>(){{}}\[\]]*[^{_SPACE}"'`=:,;|<>(){{}}\[\].!?](?:={{1,2}}(?![={_RUN}]))?"""
_LOOSE = rf"(?<![{_RUN}])(?:(?:{_PREFIXES})[{_RUN}]+(?:={{1,2}}(?![={_RUN}]))?|(?=[A-Za-z+/_-]*[0-9])(?=[={_RUN}]{{{SHORTEST}}})[{_RUN}]+(?:={{1,2}}(?![={_RUN}]))?)"
#: What stands before the value (groups 1 and 3) and the value (2, 4 and 5).
CANDIDATE = rf"""((?:{_SET}|{_WORD})[ \t]*+["'`])({_QUOTED})|({_SET}[ \t]*+|{_WORD}[ \t]++(?:is[ \t]++)?)(?!-----BEGIN )({_PLAIN})|({_LOOSE}|-----BEGIN [A-Z ]{{0,30}}PRIVATE KEY-----)"""
_OPEN, _CLOSE = "﷐", "﷑"
#: Words of the dictionary where no table is given (own choice): plain words and common letter groups.
GROUPS = tuple("the and ing ion ent for tha nth int ere tio ter est ers ati hat ate all eth hes ver his oft ith fth sth oth res ont que est les ein ich und sch den man user name data file test http html index image page main config value version release build object class string number".split())
WORDS, SHORTEST_WORD, LONGEST_WORD = 2_000, 4, 16
_KEYWORD = "(?i)(token|secret|passw|pwd|api.?key|access.?key|auth|credential|private|bearer|signature)"
_HASHWORD = "(?i)(sha-?[0-9]{0,3}|md5|commit|checksum|digest|uuid|guid|etag|revision|isbn|hash|order|invoice|phone|card|account)"
_PLACEHOLDER = r"(?i)^(true|false|null|none|nil|undefined|yes|no|string|str|int|bool|required|optional|empty|todo|changeme|xxx+|\*+|\.+|-+|\$.*|%.*|the|a|an|of|for|and|is|el|la|le|der|die|das)$"
FEATURES = ["length", "transitions", "coverage", "spread", "digits", "uppers", "hex", "uuid", "only_digits", "known_prefix", "path", "keyword_before", "assigned", "quoted", "hashword_before", "url_before", "letters_after", "pem", "symbols", "keyword_set", "placeholder"]


def _flag(c: Column) -> Column:
    return F.coalesce(c, F.lit(False)).cast("double")


def dictionary(docs: DataFrame, size: int = WORDS, text: str = "text") -> DataFrame:
    """(word, n): the ``size`` most frequent words of ``SHORTEST_WORD`` to ``LONGEST_WORD`` plain letters over all texts; of equals the first by name.

    Words are counted in every task before they are shuffled, so a word that every text holds is no hot key."""
    words = docs.select(F.explode(F.split(F.lower(F.col(text)), "[^a-z]+")).alias("word"))
    words = words.where(F.length("word").between(SHORTEST_WORD, LONGEST_WORD)).groupBy("word").agg(F.count("*").alias("n"))
    return words.orderBy(F.desc("n"), "word").limit(size)


def alternatives(words) -> str:
    """A regular expression for any of the words, longest first, that tries common beginnings once."""
    tree: dict = {}
    for w in words:
        at = tree
        for ch in w:
            at = at.setdefault(ch, {})
        at[""] = {}

    def text(node: dict) -> str:
        kids = [re.escape(ch) + text(kid) for ch, kid in sorted(node.items()) if ch]
        if not kids:
            return ""
        inner = kids[0] if len(kids) == 1 and "" not in node else "(?:" + "|".join(kids) + ")"
        return inner + "?" if "" in node else inner

    return text({k: v for k, v in tree.items() if k}) or "(?!)"


def features(before: Column, value: Column, after: Column, words: tuple[str, ...] = GROUPS) -> Column:
    """array<double> in the order of FEATURES; before and after are the text's parts around the value."""
    n = F.greatest(F.length(value), F.lit(1)).cast("double")
    tail, head = F.right(before, F.lit(48)), F.left(after, F.lit(24))
    kinds = F.regexp_replace(F.regexp_replace(F.regexp_replace(value, "[a-z]+", "a"), "[A-Z]+", "b"), "[0-9]+", "c")
    left_over = F.length(F.regexp_replace(F.lower(value), alternatives(words), ""))
    return F.array(
        F.least(n, F.lit(200.0)), F.length(kinds) / n, 1 - left_over / n, F.size(F.array_distinct(F.split(value, ""))) / n,
        F.length(F.regexp_replace(value, "[^0-9]", "")) / n, F.length(F.regexp_replace(value, "[^A-Z]", "")) / n,
        _flag(value.rlike("^([0-9a-f]+|[0-9A-F]+)$")), _flag(value.rlike("(?i)[0-9a-f]{8}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{12}")), _flag(value.rlike("^[0-9]+$")),
        _flag(value.rlike(f"^({_PREFIXES})")), _flag(value.rlike("[A-Za-z0-9_-]{2,}/[A-Za-z0-9_-]{2,}")),
        _flag(tail.rlike(_KEYWORD + r"[^\n]{0,12}$")), _flag(tail.rlike("[=:]\\s*[\"'`]?$")), _flag(tail.rlike("[\"'`]$") & head.rlike("^[\"'`]")),
        _flag(tail.rlike(_HASHWORD + r"[^\n]{0,12}$")), _flag(tail.rlike("(?i)(https?://|www\\.)\\S*$")), _flag(head.rlike("^[A-Za-z.@]")), _flag(value.startswith("-----BEGIN")),
        F.length(F.regexp_replace(value, "[A-Za-z0-9]", "")) / n, _flag(tail.rlike(_KEYWORD + r"[A-Za-z0-9_.-]{0,8}[\"'`]?\s*[=:]{1,2}>?\s*[\"'`]?$")), _flag(value.rlike(_PLACEHOLDER)),
    )


def labelled_findings(spark: SparkSession, rows: int = 6000, words: tuple[str, ...] = GROUPS) -> DataFrame:
    """Own labelled findings (before, value, after, label), made from hashes of a number: keys in assignments against
    digests, identifiers, paths, numbers and words of the dictionary. A user's own table of this shape can take its place."""
    known = F.array(*map(F.lit, words[:500] or GROUPS))
    drawn = lambda k: F.element_at(known, (F.pmod(F.xxhash64(F.lit(k), "id"), F.size(known)) + 1).cast("int"))
    h = lambda k: F.sha2(F.concat(F.lit(f"{k}:"), F.col("id").cast("string")), 256)
    pick = lambda k, *choices: F.element_at(F.array(*map(F.lit, choices)), (F.pmod(F.xxhash64(F.lit(k), "id"), F.lit(len(choices))) + 1).cast("int"))
    u = lambda k, n: F.pmod(F.xxhash64(F.lit(k), "id"), F.lit(n))
    b64 = F.regexp_replace(F.base64(F.unhex(h(1))), "=+$", "")
    cut = lambda c, lo, span: F.left(c, (lo + u(9, span)).cast("int"))
    key = F.element_at(F.array(F.left(h(2), F.lit(40)), F.left(h(2), F.lit(32)), h(2), cut(b64, 20, 23), F.upper(F.left(h(2), F.lit(40))), F.concat(F.lit("AKIA"), F.upper(F.left(F.regexp_replace(b64, "[+/]", "Q"), F.lit(16)))), F.concat(F.lit("ghp_"), F.left(F.regexp_replace(b64, "[+/]", "x"), F.lit(36))), F.concat(F.lit("sk-"), F.regexp_replace(b64, "[+/]", "z"))), (u(3, 8) + 1).cast("int"))
    named = F.concat(pick(4, "the of and ", "export ", "x\n", "en la ", ""), pick(5, "token", "TOKEN", "secret", "api_key", "apikey", "password", "access-key", "auth_token", "Authorization: Bearer", "client_secret", "private_key"), pick(6, " = ", "=", ": ", " = ", ":"), pick(7, '"', "'", "", '"'))
    close = lambda k: F.concat(pick(7, '"', "'", "", '"'), pick(k, " and the", "\n", "!! ", " ### ", ", ", ""))
    uuid = F.concat_ws("-", F.substring(h(2), 1, 8), F.substring(h(2), 9, 4), F.substring(h(2), 13, 4), F.substring(h(2), 17, 4), F.substring(h(2), 21, 12))
    syllables = F.col("w_syllables")
    made_up = F.concat(*[pick(20 + i, "the", "ing", "tion", "ver", "est", "and", "que", "lich", "ment", "er", "on", "re") for i in range(6)])
    digits = F.left(F.regexp_replace(F.concat(h(2), h(8)), "[^0-9]", ""), (16 + u(10, 4)).cast("int"))
    path = F.concat(pick(11, "static/", "images/", "src/main/", "docs/2021/"), syllables, pick(12, "/page-", "_v", "-"), u(13, 9999).cast("string"))
    plain = F.element_at(F.array(
        F.struct(F.concat(pick(14, "commit ", "sha256: ", "md5 = ", "checksum: ", "revision ", "etag: "), F.lit("")).alias("before"), F.left(h(2), F.element_at(F.array(*map(F.lit, (32, 40, 64))), (u(15, 3) + 1).cast("int"))).alias("value"), pick(16, " in the", "\n", ", ").alias("after")),
        F.struct(pick(14, "uuid ", "id = ", "the ", "session: ").alias("before"), uuid.alias("value"), pick(16, " in the", "\n", ", ").alias("after")),
        F.struct(pick(14, "card ", "call ", "the ", "no. ", "\n", "y el ").alias("before"), digits.alias("value"), pick(16, " in the", "\n", "!! ", "*** ").alias("after")),
        F.struct(pick(14, "see https://example.org/", "in ", "from www.example.com/").alias("before"), path.alias("value"), pick(16, ".html", ".png ", " ", ".").alias("after")),
        F.struct(pick(14, "the ", "a ", "token of ", "password for ").alias("before"), F.concat(syllables, u(17, 99).cast("string")).alias("value"), pick(16, " in the", "\n", ", ").alias("after")),
        F.struct(pick(14, "name = ", "the ", "version: ").alias("before"), F.concat(pick(18, "release", "build", "index"), F.lit("-"), syllables, F.lit("-20"), (10 + u(17, 15)).cast("string")).alias("value"), pick(16, " in the", "\n", ", ").alias("after")),
    ), (u(19, 6) + 1).cast("int"))
    pem = F.struct(pick(14, "", "\n", "key: ").alias("before"), F.concat(F.lit("-----BEGIN "), pick(15, "", "RSA ", "EC ", "OPENSSH "), F.lit("PRIVATE KEY-----")).alias("value"), F.lit("\n").alias("after"))
    made = {"w_syllables": F.when(u(47, 2) == 0, F.concat(drawn(48), drawn(49))).otherwise(made_up)}
    made["w_word"] = F.when(u(45, 2) == 0, drawn(46)).otherwise(F.concat(*[F.when(u(50, 3) >= i, pick(51 + i, "the", "ing", "tion", "ver", "est", "and", "que", "lich", "ment", "er", "on", "re", "bo", "ka", "lu", "zi")).otherwise("") for i in range(3)]))
    word, hand, letters = F.col("w_word"), F.col("w_hand"), F.col("w_letters")
    made["w_hand"] = F.concat(word, pick(54, "!", "&", "#", "$", "@", "_", "-", ""), F.initcap(pick(55, "dor", "gun", "pax", "mio", "zet")), u(56, 997).cast("string"), pick(57, "!", "?x", "&3", "", ""))
    made["w_letters"] = F.translate(F.left(h(6), (8 + u(58, 24)).cast("int")), "0123456789", "ghijkqxyzw")
    short = F.element_at(F.array(hand, letters, F.concat(word, letters), F.left(h(7), (8 + u(59, 8)).cast("int")), F.concat(F.initcap(word), hand), F.concat(letters, F.upper(word))), (u(60, 6) + 1).cast("int"))
    made["w_quote"] = pick(61, '"', "'", '"', "`")
    quote = F.col("w_quote")
    told = F.struct(F.concat(pick(4, "the of and ", "export ", "x\n", "en la ", ""), pick(62, "password", "PASSWORD", "passwd", "pwd", "secret", "token", "api_key", "client_secret", "oauth2_client_secret", "db.password"), pick(63, " = ", "=", ": ", '": '), quote).alias("before"), short.alias("value"), F.concat(quote, pick(8, " and the", "\n", "!! ", " ### ", ", ", "")).alias("after"))
    mixed = F.struct(F.concat(pick(4, "the of and ", "export ", "x\n", "en la ", ""), pick(62, "password", "PASSWORD", "passwd", "pwd", "secret", "token", "api_key", "client_secret", "oauth2_client_secret", "db.password"), pick(63, " = ", "=", ": ", " is ")).alias("before"), F.concat(hand, F.left(h(7), F.lit(4))).alias("value"), pick(8, "\n", " ", "", "\n", " and", "").alias("after"))
    lead = pick(64, "the ", "note: ", "name = ", "size=", "title: ", "see: ", "at 12:", "color = ", "lang: ", "1:")
    everyday = F.element_at(F.array(word, F.initcap(word), u(65, 9999).cast("string"), F.concat(word, u(66, 30).cast("string")), F.concat_ws("-", word, pick(67, "one", "two", "end")), F.concat(word, F.lit("/"), word), hand, letters), (u(68, 8) + 1).cast("int"))
    prose = F.struct(F.concat(pick(69, "of ", "\n", "", "y "), lead, F.when(u(70, 3) == 0, quote).otherwise("")).alias("before"), everyday.alias("value"), F.concat(F.when(u(70, 3) == 0, quote).otherwise(""), pick(16, " in the", "\n", ", ")).alias("after"))
    talk = F.struct(pick(71, "the password ", "a secret ", "token ", "password: ", "secret: ", "authentication ", "a bearer ", "password is ").alias("before"), F.element_at(F.array(word, word, F.initcap(word), F.lit("the"), pick(72, "of", "for", "is", "was", "that", "and")), (u(73, 5) + 1).cast("int")).alias("value"), pick(16, " in the", "\n", ", ").alias("after"))
    empty = F.struct(F.concat(pick(62, "password", "PASSWORD", "passwd", "pwd", "secret", "token", "api_key", "client_secret"), pick(63, " = ", "=", ": ", '": '), F.when(u(70, 2) == 0, quote).otherwise("")).alias("before"), pick(74, "true", "false", "null", "None", "string", "required", "$VAR", "xxxx", "****", "changeme").alias("value"), F.concat(F.when(u(70, 2) == 0, quote).otherwise(""), pick(16, " in", "\n", ", ")).alias("after"))
    begins = F.struct(pick(14, "the ", "in ", "an ", "of ").alias("before"), pick(75, "ASIAN", "ASIATIC", "ASIAS", "sk-the", "eyJo", "sk-word").alias("value"), pick(16, " in the", "\n", ", ").alias("after"))
    name = F.struct(pick(4, "the of and ", "export ", "x\n", "en la ", "").alias("before"), F.concat(pick(76, "oauth2_", "app2_", "db1-", "s3_"), pick(77, "client_secret", "access_key_name", "service_password", "api_token_value")).alias("value"), pick(78, " = ", "=", ": ", " = ", "=").alias("after"))
    known = F.struct(pick(14, "the ", "key ", "see ", "\n").alias("before"), F.element_at(F.array(key, F.concat(pick(79, "ghp_", "gho_", "sk-", "sk_live_", "glpat-", "xoxb-", "AKIA", "AIza"), F.left(h(9), (8 + u(80, 8)).cast("int")))), F.lit(2)).alias("value"), pick(16, " in the", "\n", ", ").alias("after"))
    secret = F.when(u(40, 25) == 0, pem).when(u(41, 4) == 0, told).when(u(41, 4) == 1, F.when(u(42, 2) == 0, mixed).otherwise(known)).otherwise(F.struct(named.alias("before"), key.alias("value"), close(8).alias("after")))
    plain = F.when(u(43, 2) == 0, plain).when(u(44, 8) < 4, prose).when(u(44, 8) < 5, talk).when(u(44, 8) < 6, empty).when(u(44, 8) < 7, begins).otherwise(name)
    steps = spark.range(rows)
    for new, column in made.items():  # columns of their own: one expression would be too long to compile
        steps = steps.withColumn(new, column)
    return steps.select("id", (F.col("id") % 2 == 0).cast("int").alias("label"), F.when(F.col("id") % 2 == 0, secret).otherwise(plain).alias("f")).select("label", "f.before", "f.value", "f.after")


def train(findings: DataFrame, trees: int = 24, depth: int = 6, seed: int = 7, words: tuple[str, ...] = GROUPS):
    """A random forest over labelled findings (before, value, after, label)."""
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.functions import array_to_vector

    rows = findings.select(array_to_vector(features(F.coalesce("before", F.lit("")), F.coalesce("value", F.lit("")), F.coalesce("after", F.lit("")), words)).alias("x"), F.col("label").cast("double").alias("y"))
    return RandomForestClassifier(featuresCol="x", labelCol="y", numTrees=trees, maxDepth=depth, seed=seed, featureSubsetStrategy="sqrt").fit(rows)


def compile_forest(model) -> list:
    """Nested (feature, threshold, left, right) per tree; leaves are the share of label 1."""

    def walk(node):
        if node.getClass().getSimpleName() == "LeafNode":
            stats = list(node.impurityStats().stats())
            return stats[1] / max(1e-12, sum(stats)) if len(stats) > 1 else 0.0
        split = node.split()
        return (split.featureIndex(), split.threshold(), walk(node.leftChild()), walk(node.rightChild()))

    return [walk(t._call_java("rootNode")) for t in model.trees]


def forest_score(x: Column, forest: list) -> Column:
    def column(node) -> Column:
        if not isinstance(node, tuple):
            return F.lit(float(node))
        k, at, left, right = node
        return F.when(F.get(x, F.lit(k)) <= F.lit(at), column(left)).otherwise(column(right))

    return sum((column(t) for t in forest[1:]), column(forest[0])) / F.lit(float(len(forest)))


def _parts(text: Column) -> Column:
    """The text cut at its candidates: they stand at the odd places; null if it has none."""
    clean = F.translate(text, _OPEN + _CLOSE, "��")
    cut = F.split(F.regexp_replace(clean, CANDIDATE, f"$1$3{_OPEN}$2$4$5{_CLOSE}"), f"[{_OPEN}{_CLOSE}]", -1)
    return F.when(text.rlike(CANDIDATE), cut)


def _around(parts: Column, i: Column) -> tuple[Column, Column]:
    """The 48 characters before part i and the 24 after it, in the whole text: neighbouring candidates belong to it.

    A candidate holds a character and so does what stands between two of them, so 48 and 24 parts on each side are enough.
    """
    near = lambda lo, hi, cut: F.array_join(F.transform(F.slice(parts, lo + 1, hi - lo), cut), "")
    lo, hi = F.greatest(i - 48, F.lit(0)), F.least(i + 25, F.size(parts))
    return F.right(near(lo, i, lambda p: F.right(p, F.lit(48))), F.lit(48)), F.left(near(i + 1, hi, lambda p: F.left(p, F.lit(24))), F.lit(24))


def findings(docs: DataFrame, forest: list, text: str = "text", words: tuple[str, ...] = GROUPS) -> DataFrame:
    """doc_id, start and end (characters from 0), value, score, is_secret: one row per candidate.

    A text's parts are cut into chunks, each with its own parts, the context beside them and the place where it starts, so that a text
    of many candidates becomes many rows of bounded size."""
    rows = docs.where(F.col(text).rlike(CANDIDATE)).select(F.col("doc_id").cast("bigint").alias("doc_id"), _parts(F.col(text)).alias("parts"))
    span = lambda lo, hi: F.slice("parts", lo + 1, hi - lo)
    length = lambda parts: F.aggregate(F.transform(parts, F.length), F.lit(0).cast("bigint"), lambda a, b: a + b)
    n = F.size("parts")
    rows = rows.withColumn("heads", F.sequence(F.lit(0), n - 2, F.lit(CHUNK)))
    rows = rows.withColumn("lengths", F.transform("heads", lambda at: length(span(at, F.least(at + CHUNK, n)))))
    rows = rows.select("doc_id", F.inline(F.transform("heads", lambda at, c: F.struct(
        F.aggregate(F.slice("lengths", F.lit(1), c), F.lit(0).cast("bigint"), lambda a, b: a + b).alias("base"), F.least(at, F.lit(48)).alias("lead"), F.least(F.lit(CHUNK), n - at).alias("own"),
        span(F.greatest(at - 48, F.lit(0)), F.least(at + CHUNK + 25, n)).alias("parts"),
    ))))
    inside = F.sequence(F.col("lead") + 1, F.col("lead") + F.col("own") - 1, F.lit(2))
    one = lambda i: F.struct((F.col("base") + length(F.slice("parts", F.col("lead") + 1, i - F.col("lead")))).alias("start"), _around(F.col("parts"), i)[0].alias("before"), F.get("parts", i).alias("value"), _around(F.col("parts"), i)[1].alias("after"))
    rows = rows.where("own > 1").select("doc_id", F.explode(F.transform(inside, one)).alias("f")).select("doc_id", "f.start", (F.col("f.start") + F.length("f.value")).alias("end"), "f.value", features(F.col("f.before"), F.col("f.value"), F.col("f.after"), words).alias("x"))
    rows = rows.select("doc_id", F.col("start").cast("bigint").alias("start"), F.col("end").cast("bigint").alias("end"), "value", F.array("x").alias("xs"))
    scored = rows.withColumn("score", F.transform("xs", lambda x: forest_score(x, forest))[0])
    return scored.select("doc_id", "start", "end", "value", "score", (F.col("score") >= THRESHOLD).alias("is_secret"))


def masked(docs: DataFrame, forest: list, words: tuple[str, ...] = GROUPS) -> DataFrame:
    """The documents with every secret replaced by ``MASK``; all rows and columns stay (pipeline stage)."""
    from reelspark.llm.common import fresh

    parts, xs, scores = fresh(docs, "s_parts", "s_x", "s_score")
    rows = docs.withColumn(parts, _parts(F.col("text")))
    odd = F.sequence(F.lit(1), F.size(parts) - 2, F.lit(2))
    rows = rows.withColumn(xs, F.when(F.col(parts).isNotNull(), F.transform(odd, lambda i: features(_around(F.col(parts), i)[0], F.get(parts, i), _around(F.col(parts), i)[1], words))))
    rows = rows.withColumn(scores, F.transform(xs, lambda x: forest_score(x, forest)))
    new = F.array_join(F.transform(parts, lambda p, i: F.when((i % 2 == 1) & (F.get(scores, ((i - 1) / 2).cast("int")) >= THRESHOLD), F.lit(MASK)).otherwise(p)), "")
    found = F.exists(scores, lambda s: s >= THRESHOLD)
    changes = {"text": F.when(found, new).otherwise(F.col("text"))}
    out = rows.withColumns(changes)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.exists(scores, lambda s: s >= THRESHOLD), F.length("text").cast(dict(docs.dtypes)["n_chars"])).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def fitted(docs: DataFrame) -> tuple[list, tuple[str, ...]]:
    """The corpus' dictionary and the forest that goes with it; at most ``WORDS`` words and the trees come to the driver."""
    words = tuple(r["word"] for r in dictionary(docs).collect()) or GROUPS
    return compile_forest(train(labelled_findings(docs.sparkSession, words=words), words=words)), words


def digest(docs: DataFrame) -> DataFrame:
    """What op5 returns: every candidate with its verdict; the value itself stays inside."""
    forest, words = fitted(docs)
    return findings(docs, forest, words=words).drop("value")


def mask_secrets(docs: DataFrame) -> DataFrame:
    """The pipeline's stage: a dictionary and a forest for these documents, then the documents with their secrets masked."""
    return masked(docs, *fitted(docs))
