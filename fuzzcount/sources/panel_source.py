"""A Python data source of invented people: spark.read.format("fuzzcount_people").option("persons", 171).load()."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from fuzzcount.functions.python_udfs import draw
from fuzzcount.sources.fixtures import GIVEN, SUBURB, SURNAME

SCHEMA = "rec_id bigint, owner string, entity_id bigint, given string, surname string, suburb string, postcode string, gender string"


class Persons(InputPartition):
    def __init__(self, first: int, end: int):
        self.first, self.end = first, end


class PeopleReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.persons, self.owners, self.slices = (int(options.get(k, d)) for k, d in (("persons", 171), ("owners", 3), ("slices", 8)))

    def partitions(self) -> list[InputPartition]:
        ends = [self.persons * i // self.slices for i in range(self.slices + 1)]
        return [Persons(a, b) for a, b in zip(ends[:-1], ends[1:], strict=True) if a < b] or [Persons(0, 0)]

    def read(self, partition: Persons) -> Iterator[tuple]:
        pick = lambda field, names, i: names[draw(f"{field}|{i}") % len(names)]
        for i in range(partition.first, partition.end):
            person = (pick("given", GIVEN, i), pick("surname", SURNAME, i), pick("suburb", SUBURB, i), str(27000 + draw(f"postcode|{i}") % 1000), "mf"[i % 2 == 0])
            for n in range(self.owners):
                yield (i * self.owners + n, f"o{n}", i, *person)


class PeopleSource(DataSource):
    """The records that `fixtures.of_owners` makes of customers 0 to `persons` - 1, without a customer table."""

    @classmethod
    def name(cls) -> str:
        return "fuzzcount_people"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> PeopleReader:
        return PeopleReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PeopleSource)
