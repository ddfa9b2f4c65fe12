"""Mining of weighted ordered patterns over event sequences whose items carry existence probabilities."""
