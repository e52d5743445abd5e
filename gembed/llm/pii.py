"""Operator 3: personal data, found by generators and judged by boosted trees; DataFrame functions only.

Base kinds (email, ip, card, phone) follow fixed patterns and stay as they are. Beside them generators
with high recall propose further spans, overlapping at will: telephone numbers without a plus or cut
short by a following number, blocks of digits like a card (dotted, of 13 digits, or beside another
number, which the base pattern swallows), e-mail addresses spelled with "at" and "dot", and secrets
(values of passwords, tokens and keys, of kind ``secret``, which no base pattern has). Boosted trees see
each candidate's format and the text around it; a span is added when its score reaches its kind's
threshold, which is calibrated for a precision on held-out labelled candidates, and it overlaps neither
a base span nor a better accepted candidate.

The trees are fitted once per application on ``LABELLED_ROWS`` candidates that are made by a rule (no
corpus holds labels of this kind), and turned into one SQL expression; on the main path nothing but
built-in functions runs, in one pass over the text and without a shuffle. Lists of spans are built and
resolved in pieces of about the root of their length, and overlaps only inside groups of spans that
touch, so a text with very many spans takes little more than linear time.

Defined results: null or empty text has no spans (empty lists, digest of the empty string); repeated
rows each give a row; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_and_text

KINDS = ("email", "ip", "card", "phone")
#: Kinds that only the method adds come after the base kinds.
ALL_KINDS = (*KINDS, "secret")
_JUDGED = ("phone", "card", "email", "secret")
#: Candidates that the trees are fitted and calibrated on.
LABELLED_ROWS = 4000
PRECISION = 0.98

# The base patterns. Each equals the plain form given in its comment, written so that
# Java's engine neither recurses nor starts anew inside a run that has failed already.
BASE = {
    # [A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    # [0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    # [0-9]([\x20-]?[0-9])+ with 14 digits or more
    "card": r"(?<![0-9])[0-9](?:[\x20-]?[0-9]){13,}+",
    # \+[0-9][\x20().0-9-]+[0-9]
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Cheap tests that text must pass before its pattern is tried.
GUARD = {"email": "contains(text, '@')", "ip": "text rlike '[0-9]\\\\.[0-9]'", "card": "text rlike '[0-9][\\\\x20-]?[0-9][\\\\x20-]?[0-9][\\\\x20-]?[0-9]'", "phone": "contains(text, '+')"}

_AT, _DOT = r"\x20?(?:\[at\]|\(at\)|\x20at\x20)\x20?", r"\x20?(?:\[dot\]|\(dot\)|\x20dot\x20)\x20?"
_CARD_GUARD = "text rlike '[0-9]{4}[\\\\x20.-]?[0-9]{4}[\\\\x20.-]?[0-9]{2}'"
#: Generators: kind, pattern, guard. What a group inside a lookahead finds belongs to the candidate, but the next one may begin in it.
_NAMES = "password|passwd|passphrase|pwd|secret|token|api[_-]?key|access[_-]?key|private[_-]?key|client[_-]?secret|bearer|auth"
GENERATORS = (
    ("secret", rf"(?<=(?i:{_NAMES})[\x22']?\x20?[=:]\x20?[\x22']?)(?<![A-Za-z0-9+/_.-])[A-Za-z0-9+/_.-]{{6,}}+", rf"text rlike '(?i)(?:{_NAMES})[\\x22\\x27]?\\x20?[=:]'"),
    ("secret", r"(?<![A-Za-z0-9])(?:[A-Z]{4}[A-Z0-9]{16}|gh[a-z]_[A-Za-z0-9]{36}|[sp]k[-_][A-Za-z0-9_-]{20,}+|eyJ[A-Za-z0-9_-]{10,}+\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+)(?![A-Za-z0-9])", "text rlike '(?:[A-Z]{4}[A-Z0-9]{16}|gh[a-z]_|[sp]k[-_][A-Za-z0-9]|eyJ)'"),
    ("phone", r"(?<![0-9+])(?:\+[0-9]{1,3}[\x20.-]?)?\(?[0-9]{3}\)?[\x20.-]?[0-9]{3}[\x20.-][0-9]{4}(?![0-9])", "text rlike '[0-9]{3}[\\\\x20.-][0-9]{4}'"),
    ("card", r"(?<![0-9])[0-9]{4}(?=((?:[\x20.-]?[0-9]{4}){2}[\x20.-]?[0-9]{1,7})(?![0-9]))", _CARD_GUARD),
    ("card", r"(?<![0-9])[0-9]{4}(?=([\x20.-][0-9]{6}[\x20.-][0-9]{4,5})(?![0-9]))", _CARD_GUARD),
    ("card", r"(?<![0-9])[0-9]{4}(?=((?:[\x20.-][0-9]{4}){3}[\x20.-][0-9]{1,3})(?![0-9]))", _CARD_GUARD),
    ("email", rf"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++(?:{_DOT}[A-Za-z0-9_%+-]++){{0,3}}{_AT}[A-Za-z0-9-]++(?:{_DOT}[A-Za-z0-9-]++){{0,3}}{_DOT}[A-Za-z]{{2,6}}(?![A-Za-z])", "text rlike '(?:\\\\[dot\\\\]|\\\\(dot\\\\)|\\\\x20dot\\\\x20)'"),
)
FEATURES = ("letters", "distinct", "named", "kind_no", "digits", "size", "gaps", "dots", "parens", "plus", "luhn", "equal_digits", "word_before", "glued", "bracketed", "money", "slot", "issuer", "ending", "plain")


# First digits and lengths of card numbers, common last labels of addresses, and words around "at" in plain prose.
ISSUER = "^(?:4(?:[0-9]{12}|[0-9]{15}|[0-9]{18})|(?:5[1-5]|2[2-7])[0-9]{14}|3[47][0-9]{13}|3[0689][0-9]{12}|6[0-9]{15,18}|5[0678][0-9]{11,17})$"
ENDING = "(?:com|org|net|edu|gov|mil|int|info|biz|name|io|ai|dev|app|eu|uk|us|ca|au|nz|ie|de|at|ch|fr|be|nl|lu|es|pt|it|gr|pl|cz|sk|hu|ro|bg|hr|si|dk|se|no|fi|ee|lv|lt|ru|ua|tr|il|in|pk|cn|hk|tw|jp|kr|sg|my|id|th|vn|ph|br|ar|cl|mx|co|za|ng|ke|eg|ae|sa|me|tv)"
_DETERMINERS = "(?:the|a|an|this|that|these|those|my|your|his|her|its|our|their|each|every|one|any|some|no)"
_PROSE = "(?:us|me|him|them|it|look|looks|looked|looking|available|found|find|shop|visit|visited|online|site|website|page|more|out|here|is|are|was|be|live|stay|store|sold|buy|read|see|seen|and|or|up|only|now|point|pointed|aim|aimed|stare|stared|arrive|arrived|start|stop|stopped)"
PLAIN = rf"^(?:{_PROSE}\\x20+at\\x20|.*\\x20at\\x20+{_DETERMINERS}\\x20)"


def _sql(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


#: Length of the pieces in which a list of n parts is summed up.
_PIECE = "greatest(64, cast(sqrt({n}) as int))"


def _bind(body: str, **columns: str) -> str:
    """SQL: ``body`` with v.name for columns. The optimiser may put a column's expression in place of its
    name; inside a lambda it would be evaluated for every element, bound like this it is once."""
    fields = ", ".join(f"'{k}', {c}" for k, c in columns.items())
    return f"transform(array(named_struct({fields})), v -> {body})[0]"


def _pieces(xs: str) -> str:
    """SQL: an array cut into pieces of about the root of its length."""
    step = _PIECE.format(n="size(v.xs)")
    return _bind(f"transform(sequence(0, (size(v.xs) - 1) div {step}), c -> slice(v.xs, c * {step} + 1, {step}))", xs=xs)


_BLOCK = 512


def _context(at: str, first: str, n: str) -> str:
    """SQL: ``n`` code points of the text from ``at`` + ``first`` on (fewer at its ends), out of v.blocks."""
    k, block = f"cast({at} div {_BLOCK} as int)", lambda k: f"coalesce(get(v.blocks, {k}), '')"
    near = f"concat(if({k} > 0, {block(f'{k} - 1')}, ''), {block(k)}, {block(f'{k} + 1')})"
    begin = f"({at} + {first} - if({k} > 0, {k} - 1, 0) * {_BLOCK})"
    return f"substr({near}, greatest({begin}, 0) + 1, {n} + least({begin}, 0))"


def _spans(df: DataFrame, name: str, pattern: str, guard: str) -> DataFrame:
    """Adds column ``name``: array of (s, e, t) of all matches, from what lies between and in them."""
    hits, rest, cut, at = f"_{name}_hits", f"_{name}_rest", f"_{name}_cut", f"_{name}_at"
    df = df.withColumn(hits, F.expr(f"if({guard}, regexp_extract_all(text, {_sql(pattern)}, 0), cast(array() as array<string>))"))
    df = df.withColumn(rest, F.expr(f"if(size({hits}) > 0, slice(split(text, {_sql(pattern)}, -1), 1, size({hits})), cast(array() as array<string>))"))
    ahead = f"if(size({hits}) > 0, regexp_extract_all(text, {_sql(pattern)}, 1), cast(array() as array<string>))" if "(?=(" in pattern else f"transform({hits}, h -> '')"
    df = df.withColumn(rest, F.expr(f"zip_with({rest}, zip_with({hits}, {ahead}, (h, more) -> named_struct('h', h, 't', concat(h, more))), (r, x) -> named_struct('r', length(r), 'h', length(x.h), 't', x.t))"))
    none = "cast(array() as array<struct<s:int,e:int,t:string>>)"
    df = df.withColumn(cut, F.expr(f"if(size({rest}) > 0, {_pieces(rest)}, cast(array() as array<array<struct<r:int,h:int,t:string>>>))"))
    df = df.withColumn(at, F.expr(f"aggregate({cut}, array(0), (a, piece) -> concat(a, array(element_at(a, -1) + aggregate(piece, 0, (n, x) -> n + x.r + x.h))))"))
    return df.withColumn(name, F.expr(f"""
        flatten(zip_with({cut}, slice({at}, 1, size({cut})), (piece, begin) ->
          aggregate(piece, named_struct('at', begin, 'out', {none}),
            (a, x) -> named_struct('at', a.at + x.r + x.h, 'out',
               concat(a.out, array(named_struct('s', a.at + x.r, 'e', a.at + x.r + length(x.t), 't', x.t)))),
            a -> a.out)))""")).drop(hits, rest, cut, at)


#: What a base match must also fulfil; x is the match.
VALID = {
    "email": "true",
    "ip": "forall(split(x.t, '[.]'), p -> length(ltrim('0', p)) < 4 and coalesce(cast(right(p, 3) as int), 0) <= 255)",
    "card": "length(regexp_replace(x.t, '[^0-9]', '')) between 14 and 19 and luhn_check(regexp_replace(x.t, '[^0-9]', ''))",
    "phone": "length(regexp_replace(x.t, '[^0-9]', '')) between 10 and 15",
}


def _features(kind: str, before: str, t: str, after: str) -> str:
    """SQL of a candidate's features: its own format and the text on both sides."""
    no = _JUDGED.index(kind) if kind in _JUDGED else kind
    digits = f"regexp_replace({t}, '[^0-9]', '')"
    return f"""named_struct('letters', cast(length(regexp_replace({t}, '[^A-Za-z]', '')) as double), 'distinct', cast(size(array_distinct(split({t}, ''))) as double),
      'named', cast(if({before} rlike '(?i)(?:{_NAMES})[\\x22\\x27]?\\x20?[=:]\\x20?[\\x22\\x27]?$', 1, 0) as double),
      'kind_no', cast({no} as double), 'digits', cast(length({digits}) as double), 'size', cast(length({t}) as double),
      'gaps', cast(length(regexp_replace({t}, '[^\\\\x20-]', '')) as double), 'dots', cast(length(regexp_replace({t}, '[^.]', '')) as double),
      'parens', cast(if({t} rlike '\\\\([0-9]+\\\\)', 1, 0) as double), 'plus', cast(if(startswith({t}, '+'), 1, 0) as double),
      'luhn', cast(if(length({digits}) > 11 and luhn_check({digits}), 1, 0) as double),
      'equal_digits', cast(length({digits}) - size(array_distinct(split({digits}, ''))) as double),
      'word_before', cast(if(lower({before}) rlike '(?:tel|phone|call|mobile|fax|card|visa|credit|mail|contact)[^0-9]*$', 1, 0) as double),
      'glued', cast(if({before} rlike '[A-Za-z0-9=/:.,#_-]$' or {after} rlike '^[A-Za-z0-9=/:_%-]', 1, 0) as double),
      'bracketed', cast(if({t} rlike '[\\\\[(](?:at|dot)[\\\\])]', 1, 0) as double),
      'money', cast(if({before} rlike '[$€£]\\\\s*$', 1, 0) as double),
      'slot', cast(if({t} rlike '^(?:\\\\+[0-9]{{1,3}}[\\\\x20.-]?)?\\\\(?[0-9]{{3}}\\\\)?[\\\\x20.-][0-9]{{3}}[\\\\x20.-][0-9]{{4}}$', 1, 0) as double),
      'issuer', cast(if({digits} rlike '{ISSUER}', 1, 0) as double),
      'ending', cast(if(lower({t}) rlike '[^a-z]{ENDING}$', 1, 0) as double),
      'plain', cast(if(lower({t}) rlike '{PLAIN}', 1, 0) as double))"""


def labelled_candidates(spark: SparkSession, rows: int = LABELLED_ROWS) -> DataFrame:
    """Candidates made by rule with their label: kind, t, before, after, label."""
    d = lambda salt, n: f"substr(translate(md5(concat(id, '{salt}')), 'abcdef', '012345'), 1, {n})"
    w = lambda salt, n: f"substr(translate(md5(concat(id, '{salt}')), '0123456789', 'ghijklmnop'), 1, {n})"
    area = f"concat(2 + id % 8, {d('a', 2)})"
    pick = lambda salt, words: f"element_at(array({', '.join(map(repr, words))}), cast(1 + pmod(crc32(concat(id, '{salt}')), {len(words)}) as int))"
    ends = lambda first, n, ok: f"concat({first}, {d('a', n)}, element_at(filter(sequence(0, 9), c -> {'' if ok else 'not '}luhn_check(concat({first}, {d('a', n)}, c))), 1))"
    cut = lambda t, by, gap: f"regexp_replace({t}, '^{''.join(f'(.{{{k}}})' for k in by)}', '{''.join(f'${k + 1}{gap}' for k in range(len(by)))}')"
    fours, ending = (4, 4, 4), pick("e", ("com", "org", "net", "de", "io", "edu", "in"))
    master, good, bad = ends("concat(5, 1 + id % 5)", 13, True), ends("'4'", 14, True), ends("'4'", 14, False)
    made = (
        ("phone", f"concat('(', {area}, ') ', {d('b', 3)}, '-', {d('c', 4)})", 1, "' ring '", "' '"),
        ("phone", f"concat('+', 1 + id % 80, ' (', {area}, ') ', {d('b', 3)}, '-', {d('c', 4)})", 1, "' of '", "' 45'"),
        ("phone", f"concat({area}, '-', {d('b', 3)}, '-', {d('c', 4)})", 1, "' phone '", "'.'"),
        ("phone", f"concat({area}, '.', {d('b', 3)}, '.', {d('c', 4)})", 1, "' call me at '", "', '"),
        ("email", f"concat({w('m', 6)}, ' [at] ', {w('n', 7)}, ' [dot] ', 'com')", 1, "' mail '", "' '"),
        ("email", f"concat({w('m', 5)}, '(at)', {w('n', 6)}, '(dot)', 'org')", 1, "' '", "', '"),
        ("phone", f"concat({d('b', 6)}, '-', {d('c', 4)})", 0, "' no. '", "' '"),
        ("phone", f"concat({area}, {d('b', 3)}, '-', {d('c', 4)})", 0, "'id='", "'x'"),
        ("phone", f"concat({area}, '.', {d('b', 3)}, '.', {d('c', 4)})", 0, "'$'", "'%'"),
        ("phone", f"concat({area}, ' ', {d('b', 3)}, ' ', {d('c', 4)})", 0, "' row '", "' 17 '"),
        ("card", f"concat({d('a', 4)}, '-', {d('b', 4)}, '-', {d('c', 4)}, '-', {d('e', 4)})", 0, "' key '", "'-00'"),
        ("card", ends(f"concat({d('b', 7)}, {d('c', 4)})", 4, False), 0, "' '", "' '"),
        ("email", f"concat({w('m', 4)}, ' at ', {w('n', 5)}, ' dot ', {w('o', 4)})", 0, "' look '", "' '"),
        ("phone", f"concat({d('a', 3)}, '-', {d('b', 3)}, '-', {d('c', 4)})", 0, "'978-'", "'-1'"),
        ("card", cut(good, fours, " "), 1, "' paid with '", "' 12/27 '"),
        ("card", cut(master, fours, "-"), 1, "' card '", "' 123'"),
        ("card", cut(pick("g", ("v", "m")).replace("'v'", good).replace("'m'", master), fours, "."), 1, "' no. '", "', '"),
        ("card", ends("'4'", 11, True), 1, "' is '", "' '"),
        ("card", cut(ends("concat(3, 4 + 3 * (id % 2))", 12, True), (4, 6), " "), 1, "' '", "' 09/28'"),
        ("card", ends("'6'", 14, True), 1, "' of '", "' 4417 '"),
        ("card", cut(good, fours, " "), 1, "' card:'", "'.'"),
        ("card", cut(ends("'6'", 17, True), (4, 4, 4, 4), " "), 1, "' '", "' 12/27'"),
        ("card", cut(ends("concat(3, 4 + 3 * (id % 2))", 12, True), (4, 6), "."), 1, "' no. '", "', '"),
        ("card", cut(bad, fours, " "), 0, "' paid with '", "' 12/27 '"),
        ("card", cut(bad, fours, "."), 0, "' card '", "', '"),
        ("card", ends("'4'", 11, False), 0, "' is '", "' '"),
        ("card", master, 0, "'id='", "'x'"),
        ("card", good, 0, "' 0.'", "' '"),
        ("card", cut(good, fours, "-"), 0, "' key '", "'-1417'"),
        ("card", cut(ends(pick("f", ("0", "1", "7", "8", "9")), 14, True), fours, " "), 0, "' row '", "' 12 '"),
        ("email", f"concat({w('m', 6)}, '[at]', {w('n', 7)}, '[dot]', {w('o', 4)})", 1, "' '", "' '"),
        ("email", f"concat({w('m', 6)}, ' at ', {w('n', 7)}, ' dot ', {ending})", 1, "' write to '", "' '"),
        ("email", f"concat({w('m', 4)}, ' at ', {w('n', 9)}, ' dot ', {ending})", 1, "' '", "'. '"),
        ("email", f"concat({w('m', 4)}, ' dot ', {w('o', 6)}, ' at ', {w('n', 5)}, ' dot co dot uk')", 1, "' mail '", "', '"),
        ("email", f"concat({pick('v', ('us', 'look', 'available', 'shop', 'site', 'found', 'store'))}, ' at ', {w('n', 7)}, ' dot ', {ending})", 0, "' '", "' '"),
        ("email", f"concat({w('m', 5)}, ' at ', {pick('v', ('the', 'a', 'this', 'each', 'his'))}, ' dot ', {pick('e', ('in', 'at', 'it', 'is', 'and', 'matrix'))})", 0, "' '", "' '"),
        ("email", f"concat({w('m', 6)}, ' at ', {pick('v', ('the', 'a', 'this', 'each', 'his'))}, ' ', 'dot ', {ending})", 0, "' mail '", "' '"),
    )
    hexes = lambda salt, n: f"substr(concat(md5(concat(id, '{salt}')), md5(concat(id, '{salt}z'))), 1, {n})"
    caps = lambda salt, n: f"upper(substr(translate(md5(concat(id, '{salt}')), '018', 'XKQ'), 1, {n}))"
    quoted, equals = "concat(' ', " + pick("n", ("token", "secret", "api_key", "password", "auth")) + ", ' = \"')", "concat(' ', " + pick("n", ("password", "pwd", "token", "access_key", "secret")) + ", " + pick("q", ("=", ": ", ":", " = ")) + ")"
    plain_word = pick("w", ("required", "authentication", "expired", "invalid", "generator", "optional", "protected", "management", "undefined", "placeholder"))
    made += (
        ("secret", hexes("s", 40), 1, quoted, "'\" '"),
        ("secret", hexes("t", 18), 1, equals, "' '"),
        ("secret", f"concat({w('u', 7)}, {d('v', 3)})", 1, equals, "' '"),
        ("secret", f"concat(upper({w('u', 3)}), {w('v', 4)}, '_', {d('x', 4)}, {w('y', 4)})", 1, quoted, "'\" '"),
        ("secret", f"concat('AKIA', {caps('k', 16)})", 1, "' '", "' '"),
        ("secret", f"concat('ghp_', {hexes('g', 36)})", 1, "' use '", "'.'"),
        ("secret", f"concat('sk-', {hexes('k', 32)})", 1, "' '", "' '"),
        ("secret", plain_word, 0, equals, "' '"),
        ("secret", plain_word, 0, quoted, "'\" '"),
        ("secret", w("u", 8), 0, equals, "' '"),
        ("secret", f"concat(upper({w('u', 10)}), upper({w('v', 10)}))", 0, "' '", "' '"),
        ("secret", f"concat('pk_', {w('u', 10)}, '_', {w('v', 10)})", 0, "' '", "' '"),
    )
    assert len(made) % 2 and len(made) % 5, "the fitted and the held-out rows (id % 10) need rows of every template"
    case = lambda i: f"case id % {len(made)} " + " ".join(f"when {k} then {m[i] if i in (1, 3, 4) else repr(m[i])}" for k, m in enumerate(made)) + " end"
    out = spark.range(rows)
    return out.select("id", F.expr(case(0)).alias("kind"), F.expr(case(1)).alias("t"), F.expr(case(3)).alias("before"), F.expr(case(4)).alias("after"), F.expr(case(2)).cast("double").alias("label"))


class Trees:
    """Boosted trees as an SQL expression over a features struct, and the threshold of each kind."""

    def __init__(self, spark: SparkSession, rows: int = LABELLED_ROWS, trees: int = 24, depth: int = 3):
        from pyspark.ml.classification import GBTClassifier
        from pyspark.ml.feature import VectorAssembler

        no = "case kind " + " ".join(f"when '{k}' then {i}" for i, k in enumerate(_JUDGED)) + " end"
        made = labelled_candidates(spark, rows).withColumn("x", F.expr(_features(no, "before", "t", "after")))
        flat = made.select("kind", "label", "x", F.expr("id % 10 < 7").alias("fit"), *[F.col(f"x.{f}").alias(f) for f in FEATURES]).coalesce(1).cache()
        data = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(flat.where("fit"))
        model = GBTClassifier(maxIter=trees, maxDepth=depth, seed=1, labelCol="label").fit(data)
        parts = []
        for tree, weight in zip(model.trees, model.treeWeights, strict=True):
            parts.append(f"({float(weight)!r}D) * ({self._walk(tree._call_java('rootNode'))})")
        self.sql = " + ".join(parts)
        held = flat.where("not fit").withColumn("score", F.expr(self.score("x")))
        grid = [g / 20 for g in range(4, 40)]
        row = held.groupBy("kind").agg(F.sum("label").alias("all"), *[F.sum(F.when(F.col("score") >= g, F.col("label"))).alias(f"good{i}") for i, g in enumerate(grid)], *[F.count_if(F.col("score") >= g).alias(f"taken{i}") for i, g in enumerate(grid)]).collect()
        self.threshold = dict.fromkeys(_JUDGED, 9.0)
        #: Precision and recall of each kind on the held-out candidates, at its threshold.
        self.held_out: dict[str, tuple[float, float]] = {}
        for r in row:
            for i, g in enumerate(grid):
                if r[f"taken{i}"] and (r[f"good{i}"] or 0) >= PRECISION * r[f"taken{i}"]:
                    self.threshold[r["kind"]] = g
                    self.held_out[r["kind"]] = (r[f"good{i}"] / r[f"taken{i}"], r[f"good{i}"] / r["all"])
                    break
        flat.unpersist()

    def _walk(self, node) -> str:
        if node.getClass().getSimpleName() == "LeafNode":
            return f"{float(node.prediction())!r}D"
        split = node.split()
        name = FEATURES[split.featureIndex()]
        return f"if(x.{name} <= {float(split.threshold())!r}D, {self._walk(node.leftChild())}, {self._walk(node.rightChild())})"

    def score(self, x: str) -> str:
        return self.sql.replace("x.", f"{x}.")


_fitted: dict = {}


def trees(spark: SparkSession) -> Trees:
    """The fitted trees of this application; the rows that they are fitted on never change."""
    key = spark.sparkContext.applicationId
    if key not in _fitted:
        _fitted.clear()  # those of an application that has ended
        _fitted[key] = Trees(spark)
    return _fitted[key]


def find(docs: DataFrame, model: Trees | None = None) -> DataFrame:
    """doc_id, text, base: array of (s, k, e, kind) and added: the same, of spans that the trees accept."""
    model = model or trees(docs.sparkSession)
    df = id_and_text(docs)
    for kind in KINDS:
        df = _spans(df, kind, BASE[kind], GUARD[kind])
        df = df.withColumn(kind, F.expr(f"filter({kind}, x -> {VALID[kind]})"))
    struct = lambda kind, x: f"named_struct('s', {x}.s, 'k', {ALL_KINDS.index(kind)}, 'e', {x}.e, 'kind', '{kind}')"
    df = df.withColumn("base", F.expr("array_sort(concat(" + ", ".join(f"transform({k}, x -> {struct(k, 'x')})" for k in KINDS) + "))"))
    # code points are found by counting from a text's start; pieces of it keep that short
    df = df.withColumn("_blocks", F.expr(f"regexp_extract_all(text, '(?s).{{1,{_BLOCK}}}', 0)"))
    pools = []
    for i, (kind, pattern, guard) in enumerate(GENERATORS):
        df = _spans(df, f"_g{i}", pattern, guard)
        feats = _features(kind, _context("x.s", "-20", "20"), "x.t", _context("x.e", "0", "12"))
        with_features = _bind(f"transform(v.spans, x -> named_struct('f', {feats}, 'c', {struct(kind, 'x')}))", spans=f"_g{i}", blocks="_blocks")
        scored = f"transform({with_features}, x -> named_struct('s', x.c.s, 'score', -({model.score('x.f')}), 'c', x.c))"
        df = df.withColumn(f"_g{i}", F.expr(f"filter({scored}, x -> x.score <= {-model.threshold[kind]!r}D)"))
        pools.append(f"_g{i}")
    df = df.withColumn("_pool", F.expr("concat(" + ", ".join(pools) + ")"))
    df = _resolve(df).withColumn("added", F.expr("array_sort(added)"))
    return df.select("doc_id", "text", "base", "added", *[F.size(k).cast("long").alias(f"n_{k}") for k in KINDS])


def _resolve(df: DataFrame) -> DataFrame:
    """Adds ``added``: the candidates of ``_pool``, best first, that overlap neither ``base`` nor one taken before.

    Base spans and candidates are sorted by start and parted wherever none reaches over; only inside a
    part are spans compared with each other. A base span has a score before all others.
    """
    some = lambda value, kind: f"if(size(_pool) > 0, {value}, cast(array() as array<{kind}>))"
    row = "struct<s:int,score:double,c:struct<s:int,k:int,e:int,kind:string>>"
    df = df.withColumn("_all", F.expr(some("array_sort(concat(_pool, transform(base, b -> named_struct('s', b.s, 'score', -1e9D, 'c', b))))", row)))
    df = df.withColumn("_cut", F.expr(some(_pieces("_all"), f"array<{row}>")))
    df = df.withColumn("_reach", F.expr("aggregate(_cut, array(0), (a, piece) -> concat(a, array(greatest(element_at(a, -1), array_max(transform(piece, x -> x.c.e))))))"))
    df = df.withColumn("_before", F.expr("""
        flatten(zip_with(_cut, slice(_reach, 1, size(_cut)), (piece, reach) ->
          aggregate(piece, named_struct('top', reach, 'out', cast(array() as array<int>)),
            (a, x) -> named_struct('top', greatest(a.top, x.c.e), 'out', concat(a.out, array(a.top))), a -> a.out)))"""))
    starts = _bind("filter(sequence(0, size(v.rows) - 1), i -> get(v.rows, i).s >= get(v.before, i))", rows="_all", before="_before")
    df = df.withColumn("_from", F.expr(some(starts, "int")))
    # slices of slices: cutting a long array once for every part would read all of it each time
    df = df.withColumn("_groups", F.expr(some(_pieces("_from"), "array<int>")))
    inner = "transform(x.g, (a, j) -> slice(x.rows, a - x.g[0] + 1, coalesce(get(x.g, j + 1), x.end) - a))"
    outer = "transform(v.groups, (g, j) -> named_struct('g', g, 'end', coalesce(get(get(v.groups, j + 1), 0), size(v.rows)), 'rows', slice(v.rows, g[0] + 1, coalesce(get(get(v.groups, j + 1), 0), size(v.rows)) - g[0])))"
    parts = _bind(f"flatten(transform({outer}, x -> filter({inner}, part -> exists(part, y -> y.score > -1e9D))))", rows="_all", groups="_groups")
    df = df.withColumn("_parts", F.expr(some(parts, f"array<{row}>")))
    one = "cast(array() as array<struct<s:int,k:int,e:int,kind:string>>)"
    return df.withColumn("added", F.expr(f"""
        flatten(transform(_parts, part ->
          aggregate(array_sort(transform(part, x -> named_struct('score', x.score, 'c', x.c))), named_struct('out', {one}, 'new', {one}),
            (a, x) -> if(x.score > -1e9D and exists(a.out, b -> b.s < x.c.e and x.c.s < b.e), a,
                        named_struct('out', concat(a.out, array(x.c)), 'new', if(x.score > -1e9D, concat(a.new, array(x.c)), a.new))),
            a -> a.new)))""")).drop("_pool", "_all", "_cut", "_reach", "_before", "_from", "_groups", "_parts")


def _joined(spans: str) -> Column:
    return F.expr(f"array_join(transform({spans}, x -> concat(x.kind, ':', x.s, ':', x.e)), ',')")


def report(docs: DataFrame, model: Trees | None = None) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added, n_secret and n_spans of every document."""
    rows = find(docs, model)
    return rows.select("doc_id", *[f"n_{k}" for k in KINDS], F.sha2(_joined("base"), 256).alias("base_sha256"), _joined("array_sort(concat(base, added))").alias("spans"), F.size("added").cast("long").alias("n_added"), F.expr("cast(size(filter(added, x -> x.kind = 'secret')) as long)").alias("n_secret"), F.expr("cast(size(base) + size(added) as long)").alias("n_spans"))


def redact(docs: DataFrame, model: Trees | None = None) -> DataFrame:
    """doc_id and the text with every span replaced by its kind in brackets; overlapping spans become one."""
    rows = find(docs, model).withColumn("all", F.expr("array_sort(concat(base, added))"))
    return rows.select("doc_id", F.expr("""
        aggregate(all, named_struct('at', 0, 'out', ''),
          (a, x) -> named_struct('at', greatest(a.at, x.e), 'out', if(x.s >= a.at, concat(a.out, substr(text, a.at + 1, x.s - a.at), '[', x.kind, ']'), a.out)),
          a -> concat(a.out, substr(text, a.at + 1)))""").alias("text"))
