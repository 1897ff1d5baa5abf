"""What the template codec takes apart."""

from pyspark.sql import functions as F

from relcodec.codecs import Expansion, TemplateId


def test_texts_of_a_template_are_those_that_its_last_digits_rebuild(spark):
    class ByDigits(TemplateId):
        def split(self, c):
            return {"number": F.regexp_extract(c, "([0-9]{1,17})$", 1).try_cast("long")}

    from relcodec import codecs

    for prefix, width in (("No#", 3), ("", 1), ("é 'x", 17)):
        tails = ["001", "1", "0", "-5", "+5", " 5", "5 ", "5\n", "", "12.0", "1e3", "9" * 17, "9" * 18, "1" + "0" * 17, "0" * 17, "0" * 20, "00a1", "٣", "-0", "123456", "1 2"]
        df = spark.createDataFrame([(p + t,) for p in (prefix, "No", "") for t in tails] + [(None,)], "s string").coalesce(1)
        e = Expansion([("s", "string", "template", {"prefix": prefix, "width": width})])
        found = e.expand(df).collect()
        codecs.REGISTRY["template"] = ByDigits
        try:
            assert found == e.expand(df).collect()
        finally:
            codecs.REGISTRY["template"] = TemplateId
        assert e.collapse(e.expand(df), None).collect() == df.collect()
