"""Level-synchronous graph search on Spark, with message codecs, sieving directories and a byte ledger."""
