"""Files: study folders as a Python data source, reference documents, partitioned results."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class StudyFolder(DataSource):
    """format('study_folder'): one row per header line `key: value` of the text files under a local folder; files are the partitions."""

    @classmethod
    def name(cls):
        return "study_folder"

    def schema(self):
        return "file string, key string, value string"

    def reader(self, schema):
        return _Reader(self.options["path"])


class _Reader(DataSourceReader):
    def __init__(self, path):
        self.path = path

    def partitions(self):
        import os

        return [InputPartition(os.path.join(self.path, f)) for f in sorted(os.listdir(self.path)) if f.endswith(".hdr")]

    def read(self, partition):
        import os

        with open(partition.value, encoding="utf-8") as lines:
            for line in lines:
                key, colon, value = line.rstrip("\n").partition(": ")
                if colon:
                    yield os.path.basename(partition.value), key, value
