"""Training-data operators for very large text corpora (self-contained: nothing else imports it)."""
