"""Tables, derived vector sets, indexes on storage."""
