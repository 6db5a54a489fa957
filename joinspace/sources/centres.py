"""A data source for small sets of centres."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader


class CentreSource(DataSource):
    """Centres as text, 'x,y;x,y', in the option `centres`: (center_id, coords)."""

    @classmethod
    def name(cls) -> str:
        return "centres"

    def schema(self) -> str:
        return "center_id int, coords array<double>"

    def reader(self, schema):
        return CentreReader(self.options.get("centres", ""))


class CentreReader(DataSourceReader):
    def __init__(self, text: str):
        self.text = text

    def read(self, partition):
        for i, part in enumerate(x for x in self.text.split(";") if x):
            yield i, [float(v) for v in part.split(",")]
