"""Which method to use: volumes compared before anything is moved."""
