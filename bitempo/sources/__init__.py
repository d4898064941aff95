"""Tables, corpora derived from them, generated stores, storage adapters."""
