"""Methods, audits, measures and relational operators."""
