"""Secrets in texts: patterns find candidates, a random forest removes the false ones.

Everything is one row expression of built-in functions: a text's words are tested for
candidates, each candidate is described (length, changes between character classes, how much
of it dictionary words cover, whether it looks like a path, the words beside it), and the
trees of the forest, written out as CASE expressions, vote. No row leaves its
partition and nothing runs in Python.

The forest is trained by Spark's own tree learner on labelled findings: rows
``(before, word, label)`` of a candidate word, the two words before it, and whether it is a
secret. :func:`labelled_findings` makes a bounded set of them by rule for where no reviewed
findings are at hand.

Defined results: a null or empty text has no finding; every place of a repeated secret in one word
counts once; repeated rows have the same findings each; other columns pass through, and
a column named like a result is replaced by :func:`with_findings` and kept by :func:`redact`; a very long text is read
whole, in time that grows with its length; an empty table gives an empty table.

Candidates are narrow by default: long runs and short assigned ones, each with a digit. With
``wide`` every value after an assignment or a credential word is a candidate, of any characters and length,
and so is every long run; only the forest decides. The queries and the pipeline are wide. A forest
serves the candidates it was trained on: pass the same ``wide`` everywhere.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: What may be a secret: long runs, or shorter ones right after an assignment.
CANDIDATE = r"[A-Za-z0-9+/_\-]{12,}={0,2}|(?<=[=:\"'])[A-Za-z0-9+/_\-]{6,11}(?![A-Za-z0-9+/_\-])"
_MAYBE = r"[0-9]"
#: What else may be one with ``wide``, as (pattern, group): long runs without a digit, all that follows an assignment, that up to the next separator, and quoted words.
WIDE = [(r"[A-Za-z0-9+/_\-]{12,}={0,2}", 0), (r"[=:][=:>]*[\"']?([^\s\"']+)", 1), (r"(?<=[=:\"'&;,>])[^\s\"'=:&;,]+", 0), (r'"([^"\s]+)"', 1), (r"'([^'\s]+)'", 1)]
_WIDE_PLACE = r"[=:\"']|[A-Za-z0-9+/_\-]{12,}"

# Words that speak for a secret, or against it, beside a candidate.
FOR = "password passwd pwd passphrase secret token key apikey auth authorization bearer credential private access".split()
AGAINST = "commit sha sha1 sha256 md5 checksum digest hash uuid guid id version build revision isbn order invoice example sample placeholder".split()
# Common parts of identifiers, paths and prose.
DICTIONARY = (
    "about account action address admin after agent application archive array backup base before begin block branch browser buffer build button cache call candidate category change changeme "
    "channel check class client cluster code column command comment common component config connection console contact content context control controller count create customer data database date "
    "default delete demo detail device directory display document domain download driver dummy edit element email engine entity entry error event example export factory field file filter final folder "
    "format forms function gateway global group handler header height history host http image import index info input install instance integer interface internal item java json label language layer length "
    "level library limit line link list loader local location login logs main manager map master message method model module name network node note number object option order output package page parameter "
    "parent parser password path payment picture plugin point policy port post process product profile project property provider proxy public query queue read record release remote render report repository "
    "request resource response result role root route sample schema screen script search section select sequence server service session setting setup source stack start state static status storage store "
    "string style system table target task template test text theme thread time title token tool type update upload user util value vector version video view web window word work write year your"
).split()


def _any(words: list[str]) -> str:
    return "|".join(sorted(words, key=len, reverse=True))


def _runs(value: Column) -> Column:
    return F.length(F.regexp_replace(value, "[a-z]+|[A-Z]+|[0-9]+|[^A-Za-z0-9]+", "x"))


def _share(value: Column, kind: str) -> Column:
    return (F.length(value) - F.length(F.regexp_replace(value, kind, ""))) / F.length(value)


#: The features in order: each from the candidate, its word, and the two words before.
FEATURES: dict[str, Callable[[Column, Column, Column], Column]] = {
    "length": lambda v, w, b: F.length(v).cast("double"),
    "transitions": lambda v, w, b: (_runs(v) - 1) / F.length(v),
    "digits": lambda v, w, b: _share(v, "[0-9]"),
    "uppers": lambda v, w, b: _share(v, "[A-Z]"),
    "beyond_hex": lambda v, w, b: _share(F.lower(v), "[g-z]"),
    "dictionary": lambda v, w, b: _share(F.lower(v), _any(DICTIONARY)),
    "path": lambda v, w, b: (F.length(w) - F.length(F.regexp_replace(w, r"[/\\]|\.[a-z]{1,5}\b", ""))).cast("double"),
    "separators": lambda v, w, b: _share(v, r"[_\-]"),
    "assigned": lambda v, w, b: F.rlike(F.concat(b, F.lit(" "), w), F.lit(r"[=:][\s\"']*[A-Za-z0-9+/_\-]+={0,2}[^A-Za-z0-9]*$")).cast("double"),
    "word_for": lambda v, w, b: F.rlike(F.lower(F.concat(b, F.lit(" "), w)), F.lit(rf"(^|[^a-z0-9])([a-z0-9]*[_\-.])?({_any(FOR)})[\"']?\s*([=:]|\s|$)")).cast("double"),
    "word_against": lambda v, w, b: F.rlike(F.lower(b), F.lit(rf"(^|[^a-z0-9])({_any(AGAINST)})([^a-z0-9]|$)")).cast("double"),
}


#: The credential word, perhaps with a linking word or sign, that ends what stands before a value.
_CREDENTIAL = rf"(?i)(^|[^a-z0-9])([a-z0-9]*[_\-.])?({_any(FOR)}|pin)[\"']?\s*(is|was|[=:][=:>]*|->)?[\s\"'(]*$"
_ASSIGNMENT = r"([=:][=:>]*|->)[\s\"'(]*$"
_PLACEHOLDER = rf"({_any(AGAINST)}|changeme|your|null|none|true|false|require|option|string|dummy|test|redacted|\*\*|xxx|[<>{{}}()\[\]])"


def _last(value: Column, word: Column) -> Column:
    """Characters of ``word`` before the last place of ``value``."""
    return F.length(word) - F.length(value) - F.position(F.reverse(value), F.reverse(word)) + 1


def _lead(v: Column, w: Column, b: Column) -> Column:
    return F.concat(b, F.lit(" "), F.substring(w, F.lit(1), _last(v, w)))


#: The features of wide candidates: context is what stands directly before the value, not anywhere in its word.
WIDE_FEATURES: dict[str, Callable[[Column, Column, Column], Column]] = FEATURES | {
    "assigned": lambda v, w, b: F.rlike(_lead(v, w, b), F.lit(_ASSIGNMENT)).cast("double"),
    "word_for": lambda v, w, b: F.rlike(_lead(v, w, b), F.lit(_CREDENTIAL)).cast("double"),
    "symbols": lambda v, w, b: _share(v, r"[^A-Za-z0-9+/_\-]"),
    "vowels": lambda v, w, b: _share(F.lower(v), "[aeiou]"),
    "prose": lambda v, w, b: F.rlike(v, F.lit(r"^([A-Z]?[^\x00-\x40\x5b-\x60\x7b-\x7f]+[\-/'.,!?]*)+$")).cast("double"),
    "capitals": lambda v, w, b: F.length(F.regexp_replace(v, "[^A-Z]", "")).cast("double"),
    "placeholder": lambda v, w, b: F.rlike(F.lower(v), F.lit(_PLACEHOLDER)).cast("double"),
    "known": lambda v, w, b: F.rlike(v, F.lit(r"^(A[KS]IA[A-Z0-9]{16}|gh[pousr]_|xox[abprs]-|sk_live_|glpat-|AIza)")).cast("double"),
}


def _described(value: Column, word: Column, before: Column, wide: bool = False) -> list[Column]:
    return [f(value, word, before).alias(k) for k, f in (WIDE_FEATURES if wide else FEATURES).items()]


def _candidates(word: Column) -> Column:
    """Distinct candidates of a word: those with a digit."""
    return F.array_distinct(F.filter(F.regexp_extract_all(word, F.lit(CANDIDATE), F.lit(0)), lambda v: F.rlike(v, F.lit(_MAYBE))))


def _leads(before: Column) -> Column:
    return F.rlike(before, F.lit(_ASSIGNMENT)) | F.rlike(before, F.lit(_CREDENTIAL))


def _wide_candidates(word: Column, before: Column) -> Column:
    """Distinct candidates of a word by the wide patterns, and the word itself after an assignment or a credential word."""
    whole = F.when(_leads(before), F.array(F.regexp_replace(word, r"^[\"'(\[{<`=:]+", ""))).otherwise(F.array().cast("array<string>"))
    found = F.concat(*(F.regexp_extract_all(word, F.lit(p), F.lit(g)) for p, g in WIDE), whole)
    return F.array_distinct(F.filter(F.transform(found, lambda v: F.regexp_replace(v, r"[\"'`][^A-Za-z0-9]*$|[,;.)\]}>]+$", "")), lambda v: F.length(v) > 0))


def labelled_findings(spark: SparkSession, n: int = 3200, *, wide: bool = False) -> DataFrame:
    """``n`` findings ``(before, word, label)`` made by rule from hashes of their numbers."""
    h = F.sha2(F.col("id").cast("string"), 256)
    more = F.sha2(F.concat(F.lit("b"), F.col("id").cast("string")), 256)
    base62 = F.regexp_replace(F.concat(F.base64(F.unhex(h)), F.base64(F.unhex(more))), "[+/=]", "")
    part = lambda c, a, k: F.substring(c, a, k)
    pick = lambda options, a: F.element_at(F.array(*map(F.lit, options)), (F.conv(part(h, a, 3), 16, 10).cast("int") % len(options) + 1).cast("int"))
    plain = ["the", "of and", "said that", "in una", "der", "les", "with a", "", "para el", "it."]
    words = [w for w in DICTIONARY if len(w) > 3]
    number = F.conv(part(h, 20, 3), 16, 10)
    digits = part(F.regexp_replace(F.concat(h, more), "[^0-9]", ""), 1, 16)
    names = F.concat_ws("_", pick(words, 1), pick(words, 4), pick(words, 7))
    uuid = F.concat_ws("-", part(h, 1, 8), part(h, 9, 4), part(h, 13, 4), part(h, 17, 4), part(h, 21, 12))
    kinds = [
        # secrets
        (pick(plain, 40), F.concat(F.lit("AKIA"), part(F.upper(base62), 1, 16)), 1),
        (pick(plain, 40), F.concat(pick(["password=", "passwd=", "pwd:", "db_password="], 44), part(h, 1, 18)), 1),
        (pick(["token =", "secret =", "api_key =", "access_token:", "auth ="], 40), F.concat(F.lit('"'), part(h, 1, 40), F.lit('"')), 1),
        (pick(["api_key:", "secret_key =", "private key", "apikey ="], 40), F.concat(part(base62, 1, 32), pick(["", ",", ";", "."], 44)), 1),
        (pick(["Authorization: Bearer", "bearer", "use token"], 40), part(base62, 1, 40), 1),
        (pick(plain, 40), part(base62, 1, 36), 1),
        (pick(plain, 40), F.concat(pick(["ghp_", "xoxb-", "sk_live_", "glpat-"], 44), part(base62, 1, 36)), 1),
        (pick(plain, 40), F.concat(pick(["secret=", "token:", "auth_token=", "key="], 44), part(base62, 1, 24)), 1),
        # none
        (pick(["commit", "sha", "md5 checksum", "digest", "at revision", "hash"], 40), part(h, 1, 40), 0),
        (pick(["at", "see", "in file", "open", ""], 40), F.concat(F.lit("/"), pick(words, 1), F.lit("/"), pick(words, 4), number, F.lit("/"), pick(words, 7), F.lit("_"), number, F.lit(".py")), 0),
        (pick(plain, 40), F.concat(names, number), 0),
        (pick(plain, 40), digits, 0),
        (pick(["id", "uuid", "guid:", "request"], 40), uuid, 0),
        (pick(plain, 40), F.concat(pick(["password=", "token=", "secret:", "key="], 44), pick(["example", "changeme", "your-token-", "sample", "password", "test_"], 47), number), 0),
        (pick(["version", "build", "released", "on"], 40), F.concat(F.lit("2024-01-"), part(digits, 1, 2), pick(["T10-22-33", "-release-", "_backup_"], 44), number), 0),
        (pick(plain, 40), F.concat(F.regexp_replace(part(F.lower(base62), 1, 20), "[0-9]", "a"), part(digits, 1, 1)), 0),
    ]
    if wide:
        letters = F.translate(base62, "0123456789", "qwzxkvjyQZ")
        habits = "correct horse battery dragon monkey purple tiger orange winter summer hunter coffee silver shadow letmein sunshine welcome football".split()
        prose = "the a to of and is was for in with that he they reset issues property law owner information available people government however reported holder rights once when".split()
        long = "responsibilities internationalization notwithstanding recommendations representatives characteristics Unfortunately straightforward administration Wissenschaftler particularly neighbourhood telecommunications".split()
        credential = ["password:", "password =", "the passwd:", "db_password =", "secret:", "password is", "Pwd =", "passphrase:"]
        glued = ["password=", "passwd=", "pwd:", "secret=", "db_password=", 'password="', "passphrase='", "token="]
        camel = F.concat(*(F.initcap(pick(habits, a)) for a in (1, 4, 7)))
        leet = F.concat(F.initcap(F.translate(pick(habits, 1), "aeos", "@30$")), pick(["!", "#", "", "%", "&", "_"], 7), part(digits, 1, 4))
        kinds += [
            # secrets
            (pick(plain, 40), F.concat(pick(glued, 44), camel), 1),
            (pick(credential, 40), camel, 1),
            (pick(credential, 40), F.concat(pick(habits, 1), part(digits, 1, 2), pick(["", "x", "!", "$", "z"], 7)), 1),
            (pick(plain, 40), F.concat(pick(glued, 44), leet, pick(['"', "", ";", "'"], 47)), 1),
            (pick(credential, 40), leet, 1),
            (pick(credential, 40), part(base62, 1, 8), 1),
            (pick(credential, 40), part(letters, 1, 12), 1),
            (pick(plain, 40), F.concat(pick(glued, 44), part(F.lower(letters), 1, 9)), 1),
            (pick(credential, 40), part(h, 1, 5), 1),
            (pick(plain, 40), F.concat(F.lit("AKIA"), part(F.upper(letters), 1, 16)), 1),
            (pick(plain, 40), part(letters, 1, 36), 1),
            (pick(["Authorization: Bearer", "api_key:", "use token"], 40), part(letters, 1, 32), 1),
            # none
            (pick(["note:", "name:", "title =", "see:", "said:", "type =", "und:", "10:30 ="], 40), pick(prose + long + words, 1), 0),
            (pick(["password", "secret", "access", "private", "the key", "a token", "authorization", "credential", "secret is", "key was"], 40), F.concat(pick(prose + long + words, 1), pick(["", ",", "."], 44)), 0),
            (pick(plain, 40), F.concat(pick(["", '"', "'"], 44), pick(long, 1), pick(["", ",", '"'], 47)), 0),
            (pick(plain, 40), F.concat_ws("-", pick(words, 1), pick(prose, 4), pick(words, 7)), 0),
            (pick([*credential, "token:"], 40), pick(["required", "null", "none", "string", "true", "optional", "changeme", "example", "****", "<password>", "your_password", "the", "must", "is"], 1), 0),
            (pick(plain, 40), F.concat(pick(["width=", "lang:", 'class="', "style=", "12:", "href='"], 44), pick([*words, "100%", "30", "bold"], 1)), 0),
            (pick(plain, 40), F.concat(F.initcap(pick(words, 1)), F.initcap(pick(words, 4)), F.initcap(pick(words, 7))), 0),
            (pick(plain, 40), F.upper(names), 0),
            (pick(plain, 40), F.concat(F.lit("https://www."), pick(words, 1), F.lit(".com/"), pick(words, 4), F.lit("/"), pick(prose, 7)), 0),
            (pick(plain, 40), F.concat(F.upper(pick(long + words, 1)), pick(["", ",", ".", "!"], 44)), 0),
            (pick(plain, 40), F.upper(F.concat(pick(prose, 1), pick(prose + words, 4), pick(long, 7))), 0),
            (pick(plain, 40), F.concat(F.lit('"'), F.initcap(pick(prose + words, 1)), pick(["", ",", "!"], 47)), 0),
        ]
    kind = F.col("id") % len(kinds)
    chosen = lambda k: reduce(lambda c, i: c.when(kind == i, kinds[i][k]), range(1, len(kinds)), F.when(kind == 0, kinds[0][k]))
    label = F.element_at(F.array(*(F.lit(x[2]) for x in kinds)), (kind + 1).cast("int"))
    return spark.range(0, n, 1, 1).select(chosen(0).alias("before"), chosen(1).alias("word"), label.alias("label"))


def described_findings(findings: DataFrame, *, wide: bool = False) -> DataFrame:
    """The features and the label of every labelled finding; a wide one is its word's longest candidate that follows an assignment, or the longest."""
    if wide:
        key = lambda v: F.struct(F.rlike(_lead(v, F.col("word"), F.col("before")), F.lit(rf"{_ASSIGNMENT}|{_CREDENTIAL}")).alias("led"), F.length(v).alias("n"), v.alias("v"))
        found = F.array(F.array_max(F.transform(_wide_candidates(F.col("word"), F.col("before")), key))["v"])
        one = findings.select("before", "word", "label", F.explode(found).alias("value")).where("value is not null")
    else:
        one = findings.select("before", "word", "label", F.explode(_candidates(F.col("word"))).alias("value"))
    return one.select(F.col("label").cast("double").alias("label"), *_described(F.col("value"), F.col("word"), F.col("before"), wide))


#: A tree: a leaf's vote, or (feature, threshold, left, right) with left where the feature is at most the threshold.
Tree = float | tuple[str, float, "Tree", "Tree"]


def train(findings: DataFrame, *, trees: int = 15, depth: int = 6, seed: int = 7, wide: bool = False) -> list[Tree]:
    """A random forest learned by the tree learner of Spark's ML library; labels of one kind give one leaf."""
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.feature import VectorAssembler

    names = list(WIDE_FEATURES if wide else FEATURES)
    rows = described_findings(findings, wide=wide).coalesce(1)
    labels = [r.label for r in rows.select("label").distinct().limit(3).collect()]
    if len(labels) < 2:
        return [labels[0] if labels else 0.0]
    model = RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=seed, subsamplingRate=0.8, minInstancesPerNode=3).fit(VectorAssembler(inputCols=names, outputCol="features").transform(rows))

    def read(node) -> Tree:
        if node.subtreeDepth() == 0:
            return float(node.prediction())
        split = node.split()
        return names[split.featureIndex()], float(split.threshold()), read(node.leftChild()), read(node.rightChild())

    return [read(t._call_java("rootNode")) for t in model.trees]


def vote(forest: list[Tree], feature: Callable[[str], Column]) -> Column:
    """The share of trees that call it a secret."""

    def case(t: Tree) -> Column:
        if isinstance(t, float):
            return F.lit(t)
        name, threshold, left, right = t
        return case(left) if left == right else F.when(feature(name) <= threshold, case(left)).otherwise(case(right))

    return reduce(lambda a, b: a + b, map(case, forest)) / len(forest)


#: Words of a block, within which starts are summed anew for every candidate.
BLOCK = 128


def with_findings(df: DataFrame, forest: list[Tree], *, text: str = "text", keep: float = 0.5, wide: bool = False, name: str = "findings") -> DataFrame:
    """``df`` with the column ``name``: an array of ``(start, length, value, score, secret)`` for every candidate.

    ``start`` counts characters from 0; ``secret`` is whether the score exceeds ``keep``.
    """
    words = F.split(F.coalesce(F.col(text), F.lit("")), r"\s", -1)

    def started(w: Column, before: Column, i: Column) -> Column:
        """Where word ``i`` begins: the length of all earlier blocks, and of the earlier words of its own."""
        block = F.floor(i / BLOCK).cast("int")
        inside = F.slice(w, block * BLOCK + 1, (i - block * BLOCK).cast("int"))
        return F.get(before, block) + F.aggregate(inside, F.lit(0).cast("bigint"), lambda a, x: a + F.length(x) + 1)

    def scored(found: Column) -> Column:
        voted = F.transform(found, lambda x: F.struct(x["start"].alias("start"), x["value"].alias("value"), vote(forest, lambda k: x[k]).alias("score")))
        return F.transform(voted, lambda x: F.struct(x["start"].alias("start"), F.length(x["value"]).alias("length"), x["value"].alias("value"), x["score"].alias("score"), (x["score"] > keep).alias("secret")))

    def judged(w: Column, before_block: Column) -> Column:
        at = lambda i: F.get(w, i)
        suspicious = lambda i: (F.length(at(i)) >= 8) & F.rlike(at(i), F.lit(_MAYBE)) & F.rlike(at(i), F.lit(CANDIDATE))

        def described(i: Column) -> Column:
            before = F.concat(F.coalesce(at(i - 2), F.lit("")), F.lit(" "), F.coalesce(at(i - 1), F.lit("")))
            start = started(w, before_block, i)
            return F.transform(_candidates(at(i)), lambda v: F.struct((start + F.position(v, at(i)) - 1).alias("start"), v.alias("value"), *_described(v, at(i), before)))

        places = F.filter(F.sequence(F.lit(0), F.size(w) - 1), suspicious)
        return scored(F.flatten(F.transform(places, described)))

    def judged_wide(w: Column, before_block: Column) -> Column:
        """Blanks are no words here: the two before a value are those that are not empty."""

        def of(full: Column) -> Column:
            at = lambda i: F.coalesce(F.get(full, i)["word"], F.lit(""))
            known = F.transform(full, lambda x, i: F.struct(x["word"].alias("word"), x["at"].alias("at"), F.concat(at(i - 2), F.lit(" "), at(i - 1)).alias("before")))
            places = F.filter(known, lambda x: F.rlike(x["word"], F.lit(_WIDE_PLACE)) | _leads(x["before"]))

            def described(x: Column) -> Column:
                word, before = x["word"], x["before"]
                values = F.transform(F.array(started(w, before_block, x["at"])), lambda s: F.transform(_wide_candidates(word, before), lambda v: F.struct((s + _last(v, word)).alias("start"), v.alias("value"), *_described(v, word, before, True))))
                return F.get(values, 0)

            return scored(F.flatten(F.transform(places, described)))

        full = F.filter(F.transform(w, lambda x, i: F.struct(x.alias("word"), i.alias("at"))), lambda x: x["word"] != "")
        return F.get(F.transform(F.array(full), of), 0)

    judge = judged_wide if wide else judged

    def with_blocks(w: Column) -> Column:
        # Every lambda's variable is an array computed once: sums of blocks, then sums of all blocks before each.
        sums = F.transform(F.sequence(F.lit(0), F.floor((F.size(w) - 1) / BLOCK).cast("int")), lambda k: F.aggregate(F.slice(w, k * BLOCK + 1, F.lit(BLOCK)), F.lit(0).cast("bigint"), lambda a, x: a + F.length(x) + 1))
        before = lambda s: F.transform(s, lambda _, k: F.aggregate(F.slice(s, F.lit(1), k), F.lit(0).cast("bigint"), lambda a, x: a + x))
        return F.get(F.transform(F.transform(F.array(sums), before), lambda b: judge(w, b)), 0)

    # The words are bound once, as a lambda's variable: as a column of their own the optimizer could split the text anew for every word.
    return df.withColumn(name, F.get(F.transform(F.array(words), with_blocks), 0))


def scan(df: DataFrame, forest: list[Tree], *, doc_id: str = "doc_id", text: str = "text", wide: bool = False) -> DataFrame:
    """One row per candidate: ``doc_id, start, length, value_sha256, score, secret``; values themselves are not returned."""
    found = with_findings(df.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")), forest, wide=wide)
    # The outer form, as for the other one the optimizer computes the array again to see whether it is empty.
    rows = found.select("doc_id", F.explode_outer("findings").alias("f")).where("f is not null")
    return rows.select("doc_id", "f.start", "f.length", F.sha2("f.value", 256).alias("value_sha256"), "f.score", "f.secret")


def redact(df: DataFrame, forest: list[Tree], *, text: str = "text", mark: str = "[SECRET]", wide: bool = False) -> DataFrame:
    """``df`` with every secret in ``text`` replaced by ``mark``; wide ones of under 12 characters only where no letter or digit touches them."""
    columns = df.columns
    found = with_findings(df, forest, text=text, wide=wide, name="_gp_findings")
    secrets = F.array_sort(F.array_distinct(F.transform(F.filter("_gp_findings", lambda x: x["secret"]), lambda x: x["value"])), lambda a, b: F.length(b) - F.length(a))

    def replaced(t: Column, s: Column) -> Column:
        if not wide:
            return F.replace(t, s, F.lit(mark))
        alone = F.concat(F.lit("(?<![A-Za-z0-9])"), F.regexp_replace(s, "([^A-Za-z0-9])", r"\\$1"), F.lit("(?![A-Za-z0-9])"))
        return F.when(F.length(s) >= 12, F.replace(t, s, F.lit(mark))).otherwise(F.regexp_replace(t, alone, F.lit(mark)))

    clean = F.aggregate(secrets, F.col(text), replaced)
    return found.withColumn(text, clean).select(*(F.col(f"`{c}`") for c in columns))
