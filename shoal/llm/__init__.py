"""Training-data operators (text corpora, web pages); nothing outside this folder imports it."""
