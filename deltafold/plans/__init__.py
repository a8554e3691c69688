"""Terms, their rewriting into partial results and answers, and the compiler."""
