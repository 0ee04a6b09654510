"""DataFrame operators: encoding, blocking, comparison, classification, review, measures, audits."""
