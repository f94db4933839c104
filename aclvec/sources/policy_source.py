"""A data source of synthetic policies: spark.read.format("aclvec-policy").option("roles", 100).load()."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class PolicySource(DataSource):
    """pa rows (role_id, doc_id) of roles that draw documents by the portable hash; options roles, docs, max_docs, splits."""

    @classmethod
    def name(cls) -> str:
        return "aclvec-policy"

    def schema(self) -> str:
        return "role_id int, doc_id bigint"

    def reader(self, schema) -> DataSourceReader:
        return PolicyReader(self.options)


class Roles(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class PolicyReader(DataSourceReader):
    def __init__(self, options):
        self.roles, self.docs = int(options.get("roles", 100)), int(options.get("docs", 1000))
        self.max_docs, self.splits = int(options.get("max_docs", 50)), int(options.get("splits", 4))

    def partitions(self):
        step = -(-self.roles // self.splits)
        return [Roles(i, min(i + step, self.roles)) for i in range(0, self.roles, step)]

    def read(self, part: Roles):
        from aclvec.functions.portable import draw_py

        for r in range(part.first, part.last):
            m = 1 + draw_py(r, 3, self.max_docs)
            for d in sorted({draw_py(r * 1000003 + i, 4, 1 << 20) % self.docs for i in range(1, m + 1)}):
                yield r, d
