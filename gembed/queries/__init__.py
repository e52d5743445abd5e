"""The engine's registered queries, each with the SQL that checks it where SQL can express it."""
