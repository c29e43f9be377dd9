"""Secret scan: long tokens and assigned values judged by a random forest on form, dictionary coverage, paths and the text around them.

The scan is one projection of built-in functions: candidates, features and the forest are SQL expressions.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tricount.llm.forest import Forest

#: Findings with at least this share of the forest's votes are reported.
THRESHOLD = 0.5

# A candidate is a run of 16 or more of the characters of _TOKEN, or what is assigned to a name with one of the words of _ASKS, of any characters
# and of 4 or more. Quoted values go to their closing quote, others to white space or one of ,;&|<>.
_TOKEN = r"[A-Za-z0-9+/_\\-]{16,}={0,2}(?![A-Za-z0-9])"
_ASKS = "(?i:token|secret|pass|pwd|api[_-]?key|auth|credential|bearer|private|access|signing)"
_ASSIGNED = r"(?<=[=:>][\\s\"\\x27`]{0,6})(?<=" + _ASKS + r"[A-Za-z0-9_.\\-]{0,64}[\\])\"\\x27`]{0,2}\\s{0,8}(?:={1,3}|:=|=>|->|:)>?\\s{0,8}[\"\\x27`]?)"
_VALUE = r"(?:(?<=\")[^\"\\r\\n]{4,}(?=\")|(?<=\\x27)[^\\x27\\r\\n]{4,}(?=\\x27)|(?<=`)[^`\\r\\n]{4,}(?=`)|(?![=:>])[^\\s\"\\x27`,;&|<>]{4,})"
_KNOWN = r"^(AKIA|ASIA|ghp_|gho_|github_pat_|glpat-|sk-|sk_live_|xox[abp]-|AIza|eyJ)"
_SECRET_WORDS = "(?i)(token|secret|passw|pwd|api_?key|auth|credential|bearer|private|access|signing)"
_PLAIN_WORDS = "(?i)(sha[0-9]*|md5|hash|uuid|commit|checksum|digest|etag|version|href|src|path|file|url|rev|build)"
_DICTIONARY = (
    "the ing ion and ent ter for tha ere his tio all her ver ate con com ect ive ment able ness less ight ould "
    "user name file path test data key value token secret example config default function class index table column service server client "
    "request response message error handler manager controller factory string number object array list map set get put post update delete create "
    "image script style public private static return library python java site package module version content page link button view model order item "
    "ung keit lich heit sch ein ver ge ber ción mente que los las des les eau oux elle est une dans your here goes bucket rate limit"
)
_FEATURES = {
    "len": "CAST(length({c}) AS DOUBLE)",
    "digits": "length(regexp_replace({c}, '[^0-9]', '')) / CAST(length({c}) AS DOUBLE)",
    "upper": "length(regexp_replace({c}, '[^A-Z]', '')) / CAST(length({c}) AS DOUBLE)",
    "hex": "length(regexp_replace({c}, '[^0-9a-f]', '')) / CAST(length({c}) AS DOUBLE)",
    "vowels": "length(regexp_replace(lower({c}), '[^aeiou]', '')) / CAST(length({c}) AS DOUBLE)",
    "turns": "regexp_count({c}, '[a-z](?=[0-9A-Z])|[0-9](?=[A-Za-z])|[A-Z](?=[0-9])') / CAST(length({c}) AS DOUBLE)",
    "kinds": "size(array_distinct(split({c}, ''))) / CAST(length({c}) AS DOUBLE)",
    "covered": "1D - length(regexp_replace(lower({c}), '" + "|".join(sorted(set(_DICTIONARY.split()), key=lambda w: (-len(w), w))) + "', '')) / CAST(length({c}) AS DOUBLE)",
    "slashes": "CAST(regexp_count({c}, '/') AS DOUBLE)",
    "joins": "CAST(regexp_count({c}, '[_-]') AS DOUBLE)",
    "known": "CAST({c} RLIKE '" + _KNOWN + "' AS DOUBLE)",
    "asked": "CAST({w} RLIKE '" + _SECRET_WORDS + "' AS DOUBLE)",
    "plain": "CAST({w} RLIKE '" + _PLAIN_WORDS + "' AS DOUBLE)",
    "assigned": "CAST({w} RLIKE '[=:]' AS DOUBLE)",
    "signs": "length(regexp_replace({c}, '[A-Za-z0-9]', '')) / CAST(length({c}) AS DOUBLE)",
    "spaces": "CAST(regexp_count({c}, '[\\\\s]') AS DOUBLE)",
    "told": "CAST({b} RLIKE '" + _SECRET_WORDS + "' AS DOUBLE)",
    "follows": "CAST({a} RLIKE '" + _SECRET_WORDS + "' AS DOUBLE)",
    "quoted": "CAST({w} RLIKE '[\"\\x27]$' AS DOUBLE)",
}


#: A candidate alone: what stands around it is no part of the match.
_MATCH = f"(?:{_ASSIGNED}{_VALUE}|{_TOKEN})"
#: The name nearest before a candidate, to the end of a text, and characters of text around one that are read.
_NAME = r"([A-Za-z0-9_.\\-]{1,128}[^A-Za-z0-9]{0,12})\\z"
_AROUND = 64
#: Candidates whose lengths are added up at a time, so that the work of placing findings grows evenly with a text.
_BLOCK = 256


def _candidates(docs: DataFrame) -> DataFrame:
    """Adds found, the candidates of the text, gaps, the text between them, and around, an array of (w: the nearest name and what joins it, b and a: text before and after, c: the candidate)."""
    found = docs.withColumn("found", F.expr(f"regexp_extract_all(coalesce(text, ''), '{_MATCH}', 0)")).withColumn("gaps", F.expr(f"split(coalesce(text, ''), '{_MATCH}', -1)"))
    name = f"regexp_extract(right(concat(coalesce(get(found, i - 1), ''), gaps[i]), 160), '{_NAME}', 1)"
    return found.withColumn("around", F.expr(f"transform(found, (c, i) -> named_struct('w', {name}, 'b', right(gaps[i], {_AROUND}), 'a', left(gaps[i + 1], {_AROUND}), 'c', c))"))


def _described(candidate: str) -> str:
    fields = ", ".join(f"'{k}', {v.format(**{x: f'{candidate}.{x}' for x in 'wbac'})}" for k, v in _FEATURES.items())
    return f"named_struct({fields})"


def labelled_findings(spark: SparkSession, n: int = 2400, start: int = 0) -> DataFrame:
    """(text, secret) rows written from hashes of their numbers, from `start` on: keys in the forms they are issued in and set in, and what scanners mistake for them."""
    words = "array('user','config','service','request','handler','table','image','button','order','token','bucket','manager','string','server','default','value')"
    parts = "array('th','er','an','ing','on','re','en','at','or','es','ha','nd','ou','ti','sch','ver','ge','ung','eau','que','ci','ment','lich','ra')"
    word = lambda k: f"element_at({words}, 1 + CAST(conv(substr(h, {k}, 2), 16, 10) AS INT) % 16)"
    part = lambda k: f"element_at({parts}, 1 + CAST(conv(substr(h, {k}, 2), 16, 10) AS INT) % 24)"
    name = "element_at(array('token','api_key','secret','password','auth_token','access_key','client_secret','private_key'), 1 + CAST(conv(substr(h, 1, 2), 16, 10) AS INT) % 8)"
    sign = "element_at(array(' = \"','=',': ',' = ',':\"'), 1 + CAST(conv(substr(h, 3, 2), 16, 10) AS INT) % 5)"
    mixed = "translate(base64(unhex(h)), '+/=\\n', 'xY')"
    yes = [
        f"concat({name}, {sign}, substr(h, 1, 40), '\"')", f"concat({name}, {sign}, substr(h, 5, 32))", f"concat({name}, {sign}, substr({mixed}, 1, 36))",
        f"concat({name}, {sign}, substr({mixed}, 1, 24), '\"')", "concat('AKIA', upper(substr(h, 1, 16)))", f"concat('export KEY=ghp_', substr({mixed}, 1, 36))", f"concat('use sk-', substr({mixed}, 1, 40), ' now')",
        f"concat({name}, {sign}, {word(1)}, substr(h, 7, 1), '-', initcap({part(3)}), substr(h, 5, 1), '!\"')", f"concat({name}, ': ', initcap({part(1)}), substr(h, 3, 2), '!', initcap({word(5)}), '#', substr(h, 7, 4))",
        f"concat({name}, ' = \"', substr({mixed}, 1, 6), '$', substr({mixed}, 7, 4), '\"')", f"concat('\\'', {word(9)}, '-', {name}, '\\' => \\'', substr(h, 1, 40), '\\'')", f"concat('S3_', upper({name}), '=', substr({mixed}, 1, 40))",
        f"concat('the ', {name}, ' of the ', {word(9)}, ' is ', substr(h, 1, 40))", f"concat(substr(h, 1, 40), ' is the ', {name}, ' of the ', {word(9)})",
    ]
    no = [
        "concat('commit ', substr(h, 1, 40))", "concat('sha256: ', h)", "concat('checksum=', substr(h, 1, 32))",
        f"concat({word(1)}, '_', {word(3)}, '_', {word(5)}, '_', {word(7)}, '_for_', {word(9)})", f"concat({name}, ' = ', {word(1)}, initcap({word(3)}), initcap({word(5)}), initcap({word(7)}))",
        f"concat('path: /usr/lib/', {word(1)}, '/', {word(3)}, '/', {word(5)})", "concat('id = ', substr(h, 1, 8), '-', substr(h, 9, 4), '-', substr(h, 13, 4), '-', substr(h, 17, 12))",
        "concat('order ', repeat('0', 12), CAST(conv(substr(h, 1, 8), 16, 10) AS STRING))", f"concat({part(1)}, ' ', {', '.join(part(k) for k in range(3, 25, 2))})", f"concat(initcap({part(1)}), {', '.join(part(k) for k in range(3, 21, 2))}, '.')",
        f"concat({name}, {sign}, 'YOUR_', upper({word(1)}), '_KEY_GOES_HERE')", f"concat({name}, ' ', {', '.join(part(k) for k in range(3, 29, 2))})", "concat(repeat(substr(h, 1, 1), 20), '-', repeat('-', 10))", "concat('see ', repeat(substr(h, 1, 2), 12))",
        f"concat({name}, ': ', {word(1)}, {part(3)})", f"concat({name}, ' = ', {word(1)}, '_', {word(5)}, '()')", f"concat('author: ', initcap({part(1)}), {part(3)}, {part(5)})", f"concat({name}, ' = \"', {word(1)}, ' ', {word(3)}, ' ', {part(5)}, {part(7)}, '\"')",
        f"concat({name}, '=', repeat('*', 4 + CAST(conv(substr(h, 5, 1), 16, 10) AS INT)))", f"concat({name}, ' = $\\{{', upper({word(5)}), '\\}}')", f"concat(upper({word(1)}), '_S3_', upper({word(3)}), '_ACCESS_KEY')", f"concat('the ', {name}, ' in ', {word(1)}, '_', {word(3)}, '_', {word(5)}, '_', {word(7)})",
    ]
    kinds = [(e, 1) for e in yes] * 2 + [(e, 0) for e in no]
    cases = " ".join(f"WHEN {k} THEN {e}" for k, (e, _) in enumerate(kinds))
    labels = " ".join(f"WHEN {k} THEN {v}" for k, (_, v) in enumerate(kinds))
    return spark.range(start, start + n, 1, 1).selectExpr("id", "sha2(CAST(id AS STRING), 256) AS h").selectExpr(f"CASE id % {len(kinds)} {cases} END AS text", f"CASE id % {len(kinds)} {labels} END AS secret")


def train(findings: DataFrame, bound: int = 20_000) -> Forest:
    """A forest from labelled findings (text, secret), at most `bound` of them: their candidates are described by the scan's own expressions."""
    rows = _candidates(findings.limit(bound)).selectExpr("secret", "explode(around) AS c").selectExpr("secret", f"{_described('c')} AS f").select("secret", "f.*").collect()
    names = list(_FEATURES)
    x, y = np.array([[r[k] for k in names] for r in rows], dtype=float), np.array([r.secret for r in rows], dtype=float)
    return Forest(names).fit(x, y)


def scan_secrets(docs: DataFrame, forest: Forest, threshold: float = THRESHOLD) -> DataFrame:
    """Per document: doc_id, n_candidates, and findings, an array of (position, length, score, sha256) in the order of the text.

    position is where the token stands in the text (code points, from 1), so a value that stands there twice has two findings; the value itself is only
    given as its hash. Null and empty texts have none. Rows are independent, so repeated rows agree and a null id passes through. An empty table gives no
    rows. Other columns are ignored.

    Positions are sums of lengths: the matches and the gaps between them make up the text. They are only formed where a text has a finding.
    """
    told = _candidates(docs.selectExpr("CAST(doc_id AS BIGINT) AS doc_id", "text"))
    scored = told.withColumn("described", F.expr(f"transform(around, x -> named_struct('c', x.c, 'f', {_described('x')}))"))
    judged = scored.withColumn("judged", F.expr(f"transform(described, (x, i) -> named_struct('c', x.c, 'i', i, 'score', {forest.sql('x.f')}))"))
    kept = judged.withColumn("kept", F.expr(f"filter(judged, x -> x.score >= {threshold}D)"))
    between = "CASE WHEN size(kept) > 0 THEN transform(gaps, x -> CAST(length(x) AS BIGINT)) ELSE CAST(array() AS ARRAY<BIGINT>) END"
    steps = "zip_with(between, found, (g, x) -> g + coalesce(length(x), 0))"
    block = f"slice(steps, b * {_BLOCK} + 1, {_BLOCK})"
    starts = f"aggregate(sequence(0, CAST(size(steps) DIV {_BLOCK} AS INT)), CAST(array(0) AS ARRAY<BIGINT>), (a, b) -> concat(a, array(element_at(a, -1) + aggregate({block}, 0L, (s, x) -> s + x))))"
    placed = kept.withColumn("between", F.expr(between)).withColumn("steps", F.expr(steps)).withColumn("starts", F.expr(starts))
    before = f"starts[CAST(x.i DIV {_BLOCK} AS INT)] + aggregate(slice(steps, CAST(x.i DIV {_BLOCK} AS INT) * {_BLOCK} + 1, x.i % {_BLOCK}), 0L, (s, y) -> s + y)"
    return placed.selectExpr(
        "doc_id", "CAST(size(found) AS BIGINT) AS n_candidates",
        f"transform(kept, x -> named_struct('position', {before} + between[x.i] + 1, 'length', CAST(length(x.c) AS BIGINT), 'score', x.score, 'sha256', sha2(x.c, 256))) AS findings",
    )


def digest(found: DataFrame) -> DataFrame:
    """Counts, the highest score (0 without findings) and the hash of the findings' positions and lengths."""
    listed = F.array_join(F.transform("findings", lambda x: F.concat_ws(":", x["position"], x["length"])), ",")
    best = F.coalesce(F.array_max(F.transform("findings", lambda x: x["score"])), F.lit(0.0))
    return found.select("doc_id", "n_candidates", F.size("findings").cast("long").alias("n_secrets"), best.alias("score"), listed.alias("spans"), F.sha2(listed.cast("binary"), 256).alias("spans_sha256"))
