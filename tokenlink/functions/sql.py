"""The cleaning functions for SQL users: SQL-language functions that inline into the plan, and a table function."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .cleaning import ACCENTS, DEFAULT_DENY, PLAIN


def register(spark: SparkSession) -> None:
    deny = ", ".join(f"'{x}'" for x in DEFAULT_DENY)
    digits = "regexp_replace(x, '[^0-9]', '')"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION std_name(x STRING, n INT) RETURNS STRING RETURN nullif(substring(upper(regexp_replace(translate(x, '{ACCENTS}', '{PLAIN}'), '[^A-Za-z]', '')), 1, n), '')")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION std_date(x STRING) RETURNS STRING RETURN CASE WHEN length({digits}) = 8 AND substring({digits}, 1, 4) BETWEEN '1850' AND '2022' THEN {digits} END")
    spark.sql(
        f"""CREATE OR REPLACE TEMPORARY FUNCTION std_ssn(x STRING) RETURNS STRING RETURN CASE WHEN length({digits}) = 9 AND substring({digits}, 1, 3) NOT IN ('000', '666') AND substring({digits}, 1, 1) <> '9'
        AND substring({digits}, 4, 2) <> '00' AND substring({digits}, 6, 4) <> '0000' AND {digits} NOT IN ({deny}) THEN {digits} END"""
    )
    spark.udtf.register("token_rows", TokenRows)


@udtf(returnType="rule string, token string")
class TokenRows:
    """Keys of one record for ad-hoc rules: fields as a map, rules as a comma-separated list of part codes."""

    def eval(self, fields: dict[str, str], rules: str) -> Iterator[tuple[str, str]]:
        from ..operators.rules import Part
        from .phonetic import double_metaphone_codes, metaphone_code

        for codes in (x.strip() for x in rules.split(",")):
            values = []
            for p in map(Part.parse, codes.split()):
                v = fields.get(p.field)
                if v is not None and p.transform == "prefix":
                    v = v[: p.n]
                elif v is not None and p.transform == "last":
                    v = v[-p.n :]
                elif v is not None and p.transform == "metaphone":
                    v = metaphone_code(v)
                elif v is not None and p.transform == "double_metaphone":
                    v = double_metaphone_codes(v)[0]
                elif p.transform == "soundex":
                    raise ValueError("Soundex parts need the DataFrame functions")
                values.append(v)
            if all(values):
                yield codes, "".join(values)
