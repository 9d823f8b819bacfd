"""Sources and sinks: tables, vector files, stored indexes, text embeddings."""
