"""Printed examples and idempotence of the field rules."""

from pyspark.sql import functions as F
from pyspark.sql import types as T

from biblake.functions import dates, ids, text, volissue


def each(spark, values, f):
    df = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "i int, v string")
    return [r[0] for r in df.orderBy("i").select(f(F.col("v"))).collect()]


def test_eid_parse(spark):
    got = each(spark, ["br/0601", "br/062601067530", "re/06260837633", "br/061401975837", "br/061", "xx/0601", "br/06001", None], ids.parse_eid)
    assert [g and (g.kind, g.prefix, int(g.num)) for g in got] == [("br", "060", 1), ("br", "06260", 1067530), ("re", "06260", 837633), ("br", "06140", 1975837), None, None, None, None]


def test_prefixes(spark):
    assert each(spark, ["060", "0610", "06230", "06", "0600", "061", "070"], ids.is_prefix) == [True] * 3 + [False] * 4
    assert [ids.prefix_word(i) for i in (0, 1, 9, 10, 18, 19, 91)] == ["060", "0610", "0690", "06110", "06190", "06210", "061110"]


def test_address_round_trip(spark):
    base = "https://example.org/meta/"
    assert each(spark, ["br/0601", "ra/061012"], lambda c: ids.url_eid(ids.eid_url(c, base), base)) == ["br/0601", "ra/061012"]


def test_supplier(spark):
    listed = spark.createDataFrame([("010", "other")], "prefix string, supplier string")
    df = spark.createDataFrame([("br/0601",), ("br/06120 7".replace(" ", ""),), ("br/0105",), ("br/0203",)], "e string")
    got = {r.e: r.supplier for r in ids.supplier_of(df, "e", listed).collect()}
    assert got["br/0601"] == "this" and got["br/0105"] == "other" and got["br/0203"] is None


def test_check_digits(spark):
    assert each(spark, ["1588-2861", "0138-9130", "1588-2862", "2049-3630", "2049363x", "", None], ids.valid_issn) == [True, True, False, True, False, False, False]
    assert each(spark, ["978-0-306-40615-7", "0-306-40615-2", "978-0-306-40615-8", "080442957X"], ids.valid_isbn) == [True, True, False, True]
    assert each(spark, ["0000-0002-1825-0097", "https://orcid.org/0000-0001-5109-3700", "0000-0002-1825-0098", "0000-0002-1694-233X"], ids.valid_orcid) == [True, True, False, True]
    assert each(spark, ["10.1000/182", "https://doi.org/10.1000/ABC", "11.1000/1", "10.1/x"], ids.valid_doi) == [True, True, False, False]
    assert each(spark, ["HTTPS://Example.ORG/A/b/?q=1#x", "http://a.b"], ids.norm_url) == ["https://example.org/A/b", "http://a.b"]


def test_dates(spark):
    got = each(spark, ["2020-02-30", "2020-27-12", "10000", "12000-01-01", "2012-07-25", "2020-02-29", "2019-02-29", "1900-02-29", "0000-01-01", "2020-1-5", "x", None], dates.norm_date)
    assert [g.text for g in got] == ["2020-02", "2020", None, None, "2012-07-25", "2020-02-29", "2019-02", "1900-02", None, "2020", None, None]
    assert [g.precision for g in got[:2]] == [2, 1] and got[4].day.isoformat() == "2012-07-25"
    assert each(spark, ["2020-1-5"], lambda c: dates.norm_date(c, lenient=True))[0].text == "2020-01-05"


def test_titles(spark):
    got = each(spark, ["the FaBiO and CiTO ontologies", "A WHOLE TITLE", "open access and online publishing", "(ieee) x", "iPhone use", "", None, "élan vital"], text.norm_title)
    assert got == ["The FaBiO And CiTO Ontologies", "A Whole Title", "Open Access And Online Publishing", "(Ieee) X", "iPhone Use", "", None, "Élan Vital"]
    assert each(spark, ["the FaBiO"], lambda c: text.norm_title(c, "lower")) == ["The Fabio"]


def test_spaces_and_hyphens(spark):
    assert each(spark, ["a\tb", "a b", "a b"], text.norm_space) == ["a b"] * 3
    assert each(spark, ["1–2", "1−2", "1‑2"], text.norm_hyphen) == ["1-2"] * 3


def pairs(spark, rows, **kw):
    schema = T.StructType([T.StructField("i", T.IntegerType()), T.StructField("volume", T.StringType()), T.StructField("issue", T.StringType())])
    df = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], schema)
    return [(r.volume, r.issue) for r in volissue.fix_vol_issue(df, **kw).orderBy("i").collect()]


VOL = [
    (("Vol. 35 N° spécial 1", None), ("Vol. 35", "N° spécial 1")),
    ((".38", None), ("38", None)),
    (("19/", None), ("19", None)),
    (("5â\x80\x926", None), ("5-6", None)),
    (("38â39", None), ("38-39", None)),
    (("3???4", None), ("3-4", None)),
    (("5â\\x80\\x926", None), ("5-6", None)),
    ((None, "Volume 1"), ("Volume 1", None)),
    (("Special Issue 2", "Volume 1"), ("Volume 1", "Special Issue 2")),
    (("Special Issue 2", None), (None, "Special Issue 2")),
    (("7", "Volume 1"), ("7", "Volume 1")),
    ((None, ".Vol 71"), ("Vol 71", None)),
    (("12", "3"), ("12", "3")),
    ((None, None), (None, None)),
    (("", " "), (None, None)),
]


def test_volume_and_issue(spark):
    assert pairs(spark, [a for a, _ in VOL]) == [b for _, b in VOL]
    done = [b for _, b in VOL]
    assert pairs(spark, done) == done
    assert pairs(spark, [("Vol. 35 N° 1", None)], strip_labels=True) == [("35", "1")]


def test_vocabulary(spark):
    volumes = ["Original Series", "Volume 1", "Vol 71", "Tome 1", "Cilt: 1"]
    issues = ["issue 2", "special issue 2", "Special issue 'Urban Morphology'", "Özel Sayı 5", "Hors-série 5", "ÖZEL SAYI 5"]
    assert all(each(spark, volumes, volissue.volume_like)) and not any(each(spark, volumes, volissue.issue_like))
    assert all(each(spark, issues, volissue.issue_like)) and not any(each(spark, issues, volissue.volume_like))


def test_registered_functions(spark):
    from biblake.functions.register import register

    register(spark)
    assert spark.sql("select eid_prefix('br/062601067530'), eid_num('br/062601067530')").first()[:] == ("06260", 1067530)
