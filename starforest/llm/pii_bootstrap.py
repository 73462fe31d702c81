"""Personal data by bootstrapped contextual extraction, in DataFrame operations only.

Base spans (e-mail, IPv4 address, payment card, phone) are found by their formats. They are the seeds of their kinds;
a fifth kind, ``secret``, is seeded by public key formats and by values assigned to a credential's name. The words around
each seed become lexical patterns (two words before, one word before, one word after, and for strings of letters and
digits their first four characters). Identifier-like strings in any slot are the instances: what holds an @ or a written-out
at, runs of digits, long mixes of letters and digits, and assigned values. Patterns and instances form a bipartite graph
that is scored in rounds: a pattern's score for a kind is the mean score of its instances, smoothed;
an instance's score is the noisy-or of its patterns that have enough support. Unlabelled instances whose
score passes ``threshold`` by at least two patterns become additional spans, and so do unlabelled occurrences of
a string that is a seed elsewhere (its score is one), and the secrets. Base spans always stay.

Scale: texts are scanned once and never shuffled; what is shuffled are identifier-like strings with
their contexts and pre-aggregated (pattern, instance) pairs. Nothing is collected or broadcast by hand.

Edge cases: a null text counts as empty (no spans); rows with a null or repeated doc_id are documents of
their own; ties cannot occur (spans are ordered by start, then kind, then end); an empty table gives an
empty result; other columns are ignored. Positions are code points, ends exclusive.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from starforest.runtime import cut

KINDS = ("email", "ip", "card", "phone")
#: The kind that the method adds, after the base kinds in every order.
SECRET = "secret"
_NAMES = (*KINDS, SECRET)
# Possessive forms of the contract's formats: the same leftmost matches, without backtracking. A match may
# begin inside a run of e-mail characters only where the previous match ended (\G).
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){11,18}+(?![\x20-]?[0-9])"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
_OCTETS = r"^0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])(?:\.0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])){3}$"
#: Names of credentials, and what joins a value to them.
_CREDENTIAL = r"(?i:passw(?:or)?d|passphrase|pwd|secret|token|credential|(?:api|access|auth|private)[_ -]?key)"
_ASSIGN = r"[\"']?\x20{0,2}[=:]\x20{0,2}[\"']?"
#: A mix of letters and digits of twelve characters and more.
_CODE = r"(?<![A-Za-z0-9_+/])(?=[A-Za-z_+/]*+[0-9])(?=[0-9_+/]*+[A-Za-z])[A-Za-z0-9_+/]{12,}+"
#: Public formats of access keys: fixed prefixes of well-known services.
_KEYS = r"(?:A(?:KIA|SIA)[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36,}+|AIza[0-9A-Za-z_-]{35}|xox[abprs]-[0-9A-Za-z-]{10,}+)(?![A-Za-z0-9_])"
_AT = r"[A-Za-z0-9._%+-]{1,64}+\x20?[\[(](?i:at)[\])]\x20?[A-Za-z0-9._-]++"
#: Identifier-like strings: something around an @ or a written-out at; a value assigned to a credential; a mix of letters and digits;
#: a run of seven characters and more that begins and ends as a number.
# Whatever the kind, it begins after no ASCII letter or digit: that one check spares the others most places.
INSTANCE = rf"(?<![A-Za-z0-9])(?![\s.,;])(?:(?<![^\s@,;<>\"'])[^\s@,;<>\"']++@[^\s@,;<>\"']++|(?<![A-Za-z0-9._%+-]){_AT}|(?<=[=:\x20\"'])(?<=[=:][\x20\"']{{0,3}})(?<={_CREDENTIAL}{_ASSIGN})[^\s\"',;<>]{{6,}}+|(?<![A-Za-z0-9_]){_KEYS}|{_CODE}|[0-9(][0-9()./\x20-]{{5,}}[0-9])"
#: Texts without a digit or an @ are searched if they hold one of these.
_HINTS, _LOWER_HINTS = ("AKIA", "ASIA", "(at", "[at", "(AT", "[AT"), ("passw", "passphrase", "pwd", "secret", "token", "credential", "key")
_BEFORE = 48


def _matches(text: Column, pattern: str) -> tuple[Column, Column]:
    """All matches, and the gaps around them."""
    return F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.split(text, pattern, -1)


def _place(found: Column, gaps: Column) -> Column:
    """``array<struct<s, e, hit>>``: code-point positions of the matches."""
    steps = F.zip_with(F.slice(gaps, 1, F.size(found)), found, lambda g, m: F.struct(F.length(g).alias("gap"), F.length(m).alias("size"), m.alias("hit")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<s:int,e:int,hit:string>>").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        s = acc["at"] + x["gap"]
        return F.struct((s + x["size"]).alias("at"), F.concat(acc["out"], F.array(F.struct(s.alias("s"), (s + x["size"]).alias("e"), x["hit"].alias("hit")))).alias("out"))

    return F.aggregate(steps, start, step, lambda acc: acc["out"])


def _digits(c: Column) -> Column:
    return F.regexp_replace(c, r"[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the Luhn check."""
    figures = F.filter(F.split(F.reverse(digits), ""), lambda x: x != "")

    def value(x: Column, i: Column) -> Column:
        d = x.cast("int")
        return F.when(i % 2 == 0, d).otherwise(d * 2 - F.when(d > 4, 9).otherwise(0))

    return F.aggregate(F.transform(figures, value), F.lit(0), lambda a, b: a + b) % 10 == 0


def _keeps(kind: str, hit: Column) -> Column:
    if kind == "ip":
        return hit.rlike(_OCTETS)
    if kind == "card":
        return luhn(_digits(hit))
    n = F.length(_digits(hit))
    return (n >= 9) & (n <= 15) if kind == "phone" else F.lit(True)


def _kept(kind: str):
    return lambda x: _keeps(kind, x["hit"])


def _of_kind(i: int):
    return lambda x: F.struct(x["s"].alias("s"), F.lit(i).alias("k"), x["e"].alias("e"))


def _is_kind(i: int):
    return lambda x: x["k"] == i


def _join_spans(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in _NAMES])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(names, x["k"] + 1), x["s"].cast("string"), x["e"].cast("string"))), ",")


def base_spans(docs: DataFrame) -> DataFrame:
    """``(rid, doc_id, base, instances)``; base: sorted ``array<struct<s, k, e>>``; instances: labelled strings with context."""
    d = docs.select(F.monotonically_increasing_id().alias("rid"), F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    need = {"email": F.col("text").contains("@"), "ip": F.col("digit"), "card": F.col("digit"), "phone": F.col("text").contains("+") & F.col("digit")}
    d = d.withColumn("digit", F.col("text").rlike("[0-9]"))
    hinted = reduce(Column.__or__, [F.col("text").contains(h) for h in _HINTS])
    # Lower case is dear: only where something could be assigned.
    hinted |= (F.col("text").contains("=") | F.col("text").contains(":")) & reduce(Column.__or__, [F.lower("text").contains(h) for h in _LOWER_HINTS])
    d = d.withColumn("maybe", F.col("digit") | need["email"] | hinted)
    nothing = F.array().cast("array<string>")
    d = d.withColumns({f"m_{k}": F.when(need[k], F.regexp_extract_all("text", F.lit(p), F.lit(0))).otherwise(nothing) for k, p in zip(KINDS, (EMAIL, IP, CARD, PHONE), strict=True)} | {"m_any": F.when(F.col("maybe"), F.regexp_extract_all("text", F.lit(INSTANCE), F.lit(0))).otherwise(nothing)})
    d = d.withColumns({f"g_{k}": F.when(F.size(f"m_{k}") > 0, F.split("text", p, -1)).otherwise(nothing) for k, p in zip((*KINDS, "any"), (EMAIL, IP, CARD, PHONE, INSTANCE), strict=True)})
    d = d.withColumns({f"s_{k}": F.when(F.size(f"m_{k}") > 0, _place(F.col(f"m_{k}"), F.col(f"g_{k}"))).otherwise(F.array().cast("array<struct<s:int,e:int,hit:string>>")) for k in (*KINDS, "any")})
    kept = [F.transform(F.filter(f"s_{k}", _kept(k)), _of_kind(i)) for i, k in enumerate(KINDS)]
    d = d.withColumn("base", F.when(F.col("digit") | need["email"], F.array_sort(F.concat(*kept))).otherwise(F.array().cast("array<struct<s:int,k:int,e:int>>")))
    word = r"([\p{L}\p{N}_]+)[^\p{L}\p{N}_]*$"

    def instance(x: Column, i: Column) -> Column:
        before, after = F.lower(F.right(F.get("g_any", i), F.lit(_BEFORE))), F.lower(F.left(F.get("g_any", i + 1), F.lit(_BEFORE)))
        label = F.get(F.filter("base", lambda b: (b["s"] < x["e"]) & (b["e"] > x["s"])), F.lit(0))["k"]
        # A value with letters that is assigned to a credential is a secret, whatever formats its digits happen to meet.
        assigned = before.rlike(rf"{_CREDENTIAL}{_ASSIGN}$") & x["hit"].rlike("[A-Za-z]") & ~x["hit"].contains("@")
        label = F.coalesce(F.when(assigned | x["hit"].rlike(rf"^{_KEYS}"), len(KINDS)), label)
        prefix = F.when(x["hit"].rlike(rf"^{_CODE}$"), F.left(x["hit"], F.lit(4))).otherwise("")
        return F.struct(prefix.alias("prefix"), x["s"].alias("s"), x["e"].alias("e"), x["hit"].alias("hit"), F.regexp_extract(before, word, 1).alias("one"), F.regexp_extract(before, r"([\p{L}\p{N}_]+[^\p{L}\p{N}_]+[\p{L}\p{N}_]+)[^\p{L}\p{N}_]*$", 1).alias("two"), F.regexp_extract(after, r"^[^\p{L}\p{N}_]*([\p{L}\p{N}_]+)", 1).alias("next"), label.alias("label"))

    return d.select("rid", "doc_id", "base", F.transform("s_any", instance).alias("instances"))


def _form(kind: Column, hit: Column) -> Column:
    """Whether an unlabelled string could be of a kind at all."""
    n = F.length(_digits(hit))
    return F.when(kind == 0, hit.rlike(r"@|[\[(](?i:at)[\])]")).when(kind == 1, F.size(F.split(hit, r"[.]")) >= 4).when(kind == 2, ~hit.rlike("[@A-Za-z]") & (n >= 12) & (n <= 19)).when(kind == 3, ~hit.rlike("[@A-Za-z]") & (n >= 7) & (n <= 15)).otherwise(hit.rlike("[0-9]") & hit.rlike("[A-Za-z]") & ~hit.contains("@"))


def discover(found: DataFrame, *, rounds: int = 3, support: int = 3, threshold: float = 0.9) -> DataFrame:
    """``(rid, s, k, e)``: spans that the scored graph adds to ``found`` (of :func:`base_spans`)."""
    inst = cut(found.where(F.size("instances") > 0).select("rid", F.explode("instances").alias("i")).select("rid", "i.*").withColumn("key", F.lower("hit")))
    sides = F.array(*[F.when(F.col(c) != "", F.concat(F.lit(f"{c}:"), F.col(c))) for c in ("one", "two", "next", "prefix")])
    edges = inst.select("key", "label", F.explode(sides).alias("pattern")).where("pattern is not null")
    known = inst.where("label is not null").groupBy("key", F.col("label").alias("k")).agg(F.lit(1.0).alias("seed"))
    # Only patterns that some seed induced can score; counts are aggregated before anything is joined.
    pairs = edges.groupBy("pattern", "key").agg(F.count("*").alias("uses"), F.count("label").alias("seeds"))
    induced = pairs.groupBy("pattern").agg(F.count("*").alias("instances"), F.sum(F.when(F.col("seeds") > 0, 1).otherwise(0)).alias("seeded")).where((F.col("seeded") >= support) & (F.col("seeded") * 2 >= F.col("instances")))
    pairs = cut(pairs.join(induced.select("pattern", "instances"), "pattern").select("pattern", "key", "instances"))
    scores = known.select("key", "k", F.col("seed").alias("score"))
    for _ in range(rounds):
        by_pattern = pairs.join(scores, "key").groupBy("pattern", "k").agg((F.sum("score") / (F.first("instances") + 1)).alias("trust"))
        raised = pairs.select("pattern", "key").join(by_pattern, "pattern").groupBy("key", "k").agg((1 - F.exp(F.sum(F.log(F.greatest(1 - F.col("trust"), F.lit(1e-9)))))).alias("score"), F.countDistinct("pattern").alias("by"))
        scores = cut(raised.join(known, ["key", "k"], "full").select("key", "k", F.coalesce("seed", F.when(F.col("by") >= 2, F.col("score")).otherwise(0.0)).alias("score"), "seed"))
    # Seeds too: a string that is a base span in one document may stand in another without what makes it one there.
    best = scores.where(F.col("score") >= threshold).groupBy("key").agg(F.max_by("k", F.struct("score", -F.col("k"))).alias("k"))
    return inst.where("label is null").join(best, "key").where(_form(F.col("k"), F.col("hit"))).select("rid", "s", "k", "e")


def find_pii(docs: DataFrame, **parameters) -> DataFrame:
    """One row for each document: counts of base spans by kind, the base digest, all spans, and counts of secrets and of added spans."""
    found = base_spans(docs)
    kept = cut(found)
    more = discover(kept, **parameters).groupBy("rid").agg(F.collect_set(F.struct("s", "k", "e")).alias("more"))
    counts = {f"n_{k}": F.size(F.filter("base", _is_kind(i))).cast("long") for i, k in enumerate(KINDS)}
    empty = F.array().cast("array<struct<s:int,k:int,e:int>>")
    secrets = F.transform(F.filter("instances", lambda x: x["label"] == len(KINDS)), lambda x: F.struct(x["s"].alias("s"), x["label"].alias("k"), x["e"].alias("e")))
    added = F.concat(secrets, F.coalesce("more", empty))
    spans = F.array_sort(F.concat("base", added))
    return kept.join(more, "rid", "left").select(
        "doc_id",
        *[c.alias(n) for n, c in counts.items()],
        F.sha2(_join_spans(F.col("base")), 256).alias("base_sha256"),
        _join_spans(spans).alias("spans"),
        F.size(F.filter(added, _is_kind(len(KINDS)))).cast("long").alias("n_secret"),
        F.size(added).cast("long").alias("n_added"),
    )
