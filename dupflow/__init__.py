"""Alignment pre-processing on Spark: ingest, plug-ins, pooling, duplicate marking, sorted block output."""
