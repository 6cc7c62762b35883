"""Tables, lifts of tables to congruence graphs, files of terms and graphs."""
