"""All queries of the reference's own methods, and their SQL."""

from clipflow.workloads import audio_sync, corpus, decode, lexicon, networks, relational, scoring, streams, surface, tables_main  # noqa: F401
from clipflow.workloads.registry import ORACLES, QUERIES  # noqa: F401
