"""Regular path queries over a web of linked documents, as Spark dataflow."""
