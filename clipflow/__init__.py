"""clipflow: mining, decoding and scoring of lip-reading corpora on Spark."""
