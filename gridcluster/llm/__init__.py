"""Operators of a training-data pipeline over documents, conversations and benchmark tables.

Nothing outside this subpackage imports it. Conventions shared by all of them:

* null text counts as empty text; what that gives is said in each operator;
* rows with the same id and the same text are one document: each row gets the same answer;
* only the named id and text columns are read, so further columns, whatever their names, do no harm;
* an empty table gives an empty result with the same columns.
"""
