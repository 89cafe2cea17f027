"""Named plans: every query of the entry module, with the SQL that checks it."""
