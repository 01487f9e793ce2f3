"""lexfold: dictionary folding of repetitive text for token-priced readers, as Spark plans."""
