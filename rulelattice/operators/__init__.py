"""Mining operators: encoding, counting, level-wise search, families, rules, sessions, baselines."""
