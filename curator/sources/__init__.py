"""Table sources with declared schemas, the two corpora, and sinks."""
