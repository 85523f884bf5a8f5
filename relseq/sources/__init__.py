"""Reading the given tables and events, and storing corpora, occurrences and patterns."""
