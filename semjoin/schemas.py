"""Fixed schemas of the engine's tables."""

TEXT_ROW = "row_id bigint, text string, key string, tokens int"
ITEM = "struct<pos:int,row_id:bigint,text:string,key:string,tokens:int>"
ANSWER = "left_batch bigint, right_batch bigint, left_ids array<bigint>, right_ids array<bigint>, answer string, stopped boolean, tokens_read int, tokens_written int, latency_ms double"
PAIR = "left_id bigint, right_id bigint"
LEDGER = "run_id string, round int, left_batch bigint, right_batch bigint, tokens_read int, tokens_written int, latency_ms double, overflow boolean, malformed boolean"
